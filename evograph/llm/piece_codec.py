"""Encoding and decoding with a byte-fallback BPE piece model, in vectorised merge rounds.

``encode`` gives the ids that the sentencepiece library gives (identity normaliser,
dummy prefix, no sampling); ``decode`` gives what its ``decode(ids)`` gives.

No piece of such a model has a space mark after another character, so a text falls
into words (a run of marks, then other characters) that merge independently. All
distinct words of a slice lie in one flat symbol array; each round finds the least
pair rank of every word, merges the leftmost such pair in every word at once, and
compacts the array, until no word has a pair left. Ranks are piece scores, so this is
the library's order: best score first, leftmost among equals.

Nulls and empty texts encode to the end id alone and decode to an empty text. A word
of over ``LONG_WORD`` symbols is merged with a heap instead (rounds would cost its
square). Memory: one slice of text and a word table of at most ``TABLE_WORDS`` words.
Repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from evograph.llm.common import kept, table

MARK = "▁"
LONG_WORD = 512
TABLE_WORDS = 800_000
SLICE_CHARS = 2_000_000
_WORD = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
_NONE = np.int64(2**62)


def model_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class PieceCodec:
    """The tables of one model: symbols, mergeable pairs with their ranks, byte ids."""

    def __init__(self, model_file: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        n = sp.get_piece_size()
        self.eos, self.unk = sp.eos_id(), sp.unk_id()
        self.text: list[str] = [sp.id_to_piece(i) for i in range(n)]
        self.kind = ["byte" if sp.is_byte(i) else "mark" if sp.is_control(i) or sp.is_unknown(i) else "piece" for i in range(n)]
        self.byte_of = {i: int(self.text[i][3:5], 16) for i in range(n) if self.kind[i] == "byte"}
        self.byte_id = {b: i for i, b in self.byte_of.items()}
        self.symbol = {p: i for i, p in enumerate(self.text) if self.kind[i] == "piece"}
        self.n = n
        self.number = [str(i) for i in range(n)]
        self.shown = {i: p.replace(MARK, " ") for i, p in enumerate(self.text) if self.kind[i] == "piece"}
        for p in list(self.symbol):  # characters that only occur inside pieces get symbols past the ids
            for c in p:
                if c not in self.symbol:
                    self.symbol[c] = n + len(self.symbol)
        self.span = max(self.symbol.values()) + 2  # the last is for characters without a symbol
        keys, ranks, made = [], [], []
        for piece, i in self.symbol.items():
            if i >= n:
                continue
            rank = -sp.get_score(i)
            for k in range(1, len(piece)):
                a, b = self.symbol.get(piece[:k]), self.symbol.get(piece[k:])
                if a is not None and b is not None:
                    keys.append(a * self.span + b)
                    ranks.append(rank)
                    made.append(i)
        order = np.argsort(keys, kind="stable")
        self.keys = np.array(keys, dtype=np.int64)[order]
        self.made = np.array(made, dtype=np.int64)[order]
        # scores are distinct by piece; rank them so that one integer holds rank and order
        self.ranks = np.unique(np.array(ranks), return_inverse=True)[1].astype(np.int64)[order]
        self.pair = {int(k): (int(r), int(m)) for k, r, m in zip(self.keys, self.ranks, self.made)}
        self.words: dict[str, tuple[int, str, str]] = {}
        self.older: dict[str, tuple[int, str, str]] = {}

    def pairs(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (or none) and merged symbol of each pair."""
        key = a * self.span + b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], _NONE), self.made[at]

    def encode_words(self, words: list[str]) -> list[list[int]]:
        """Ids of each word."""
        out: list[list[int] | None] = [self._by_heap(w) if len(w) > LONG_WORD else None for w in words]
        todo = [k for k, x in enumerate(out) if x is None and words[k]]
        if todo:
            lens = np.array([len(words[k]) for k in todo])
            chars = "".join(words[k] for k in todo)
            other = self.span - 1
            points = np.frombuffer(chars.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
            seen, back = np.unique(points, return_inverse=True)
            sym = np.array([self.symbol.get(chr(c), other) for c in seen], dtype=np.int64)[back]
            word = np.repeat(np.arange(len(todo)), lens)
            start = np.arange(len(chars))  # where a symbol begins, for byte fallback
            done_sym, done_word, done_at = [], [], []
            # rank[i] and made[i] belong to symbols i and i + 1; only pairs beside a merge change
            rank, made = np.full(len(sym), _NONE), np.zeros(len(sym), dtype=np.int64)
            fresh = np.flatnonzero(word[:-1] == word[1:])
            rank[fresh], made[fresh] = self.pairs(sym[fresh], sym[fresh + 1])
            while len(sym):
                first = np.flatnonzero(np.append(True, word[1:] != word[:-1]))
                best = np.minimum.reduceat(rank, first)
                sizes = np.diff(np.append(first, len(sym)))
                live = best < _NONE
                keep = np.repeat(live, sizes)
                if not live.all():  # finished words leave the array
                    done_sym.append(sym[~keep])
                    done_word.append(word[~keep])
                    done_at.append(start[~keep])
                if not live.any():
                    break
                hit = np.flatnonzero(rank == np.repeat(np.where(live, best, -1), sizes))
                lead = hit[np.append(True, word[hit][1:] != word[hit][:-1])]
                sym[lead] = made[lead]
                keep[lead + 1] = False
                stale = np.zeros(len(sym), dtype=bool)
                stale[lead] = True
                stale[np.maximum(lead - 1, 0)] = True
                stale[np.maximum(lead - 2, 0)] = True
                sym, word, start, rank, made, stale = (x[keep] for x in (sym, word, start, rank, made, stale))
                at = np.flatnonzero(stale)
                rank[at] = _NONE
                at = at[at + 1 < len(sym)]
                at = at[word[at] == word[at + 1]]
                rank[at], made[at] = self.pairs(sym[at], sym[at + 1])
            sym, word, start = (np.concatenate(x) for x in (done_sym, done_word, done_at))
            order = np.argsort(start, kind="stable")
            sym, word, start = sym[order], word[order], start[order]
            ends = np.cumsum(np.bincount(word, minlength=len(todo))).tolist()
            plain = np.ones(len(todo), dtype=bool)
            plain[word[sym >= self.n]] = False
            ids, at = sym.tolist(), 0
            for k, end, simple in zip(todo, ends, plain.tolist()):
                if simple:
                    out[k] = ids[at:end]
                else:
                    out[k] = [i for j in range(at, end) for i in ([ids[j]] if ids[j] < self.n else self._bytes(chars[start[j]]))]
                at = end
        return [x or [] for x in out]

    def _bytes(self, char: str) -> list[int]:
        return [self.byte_id.get(b, self.unk) for b in char.encode("utf-8", "surrogatepass")]

    def _by_heap(self, word: str) -> list[int]:
        """One long word: a heap of pairs by rank and place, n log n."""
        other = self.span - 1
        sym = [self.symbol.get(c, other) for c in word]
        n = len(sym)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, int, int]] = []

        def push(i: int, j: int) -> None:
            if i >= 0 and j < n and (p := self.pair.get(sym[i] * self.span + sym[j])):
                heapq.heappush(heap, (p[0], i, sym[i], sym[j]))

        for i in range(n - 1):
            push(i, i + 1)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = after[i] if sym[i] == a else n
            if j >= n or sym[j] != b:
                continue
            sym[i], sym[j] = self.pair[a * self.span + b][1], -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            push(before[i], i)
            push(i, after[i])
        ids: list[int] = []
        for i, s in enumerate(sym):
            if s >= 0:
                ids.extend([s] if s < self.n else self._bytes(word[i]))
        return ids

    def learn(self, words: set[str]) -> None:
        """Put words that the table lacks into it; when it is full, words not seen of late go."""
        if len(self.words) > TABLE_WORDS // 2:
            self.older, self.words = self.words, {}
        new = []
        for w in words.difference(self.words):
            if w in self.older:
                self.words[w] = self.older[w]
            else:
                new.append(w)
        for k in range(0, len(new), 50_000):
            part = new[k : k + 50_000]
            number = self.number
            for w, ids in zip(part, self.encode_words(part)):
                self.words[w] = (len(ids), " ".join([number[i] for i in ids]), self._plain(ids))

    def _plain(self, ids: list[int]) -> str:
        """Text of ids, marks as spaces, without dropping the dummy prefix."""
        try:  # pieces alone
            return "".join([self.shown[i] for i in ids])
        except KeyError:
            pass
        parts, run = [], bytearray()
        for i in ids:
            if i in self.byte_of:
                run.append(self.byte_of[i])
                continue
            if run:
                parts.append(_utf8(bytes(run)))
                run = bytearray()
            if self.kind[i] == "piece":
                parts.append(self.shown[i])
            elif i == self.unk:
                parts.append(" ⁇ ")
        if run:
            parts.append(_utf8(bytes(run)))
        return "".join(parts)

    def encode(self, text: str | None) -> list[int]:
        if not text:
            return [self.eos]
        words = _WORD.findall(MARK + text.replace(" ", MARK))
        return [i for ids in self.encode_words(words) for i in ids] + [self.eos]

    def decode(self, ids: list[int]) -> str:
        text = self._plain(ids)
        lead = next((i for i in ids if self.kind[i] != "mark"), None)  # the dummy prefix is a piece, never a byte
        return text[1:] if lead is not None and self.text[lead].startswith(MARK) else text

    def digest(self, texts: list[str | None]) -> tuple[list[int], list[str], list[str]]:
        """Number of ids, hash of the ids, hash of the decoded text, by text."""
        split = [_WORD.findall(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        self.learn(set().union(*split))
        get, count, ids_hash, text_hash = self.words.__getitem__, [], [], []
        end = str(self.eos)
        for ws in split:
            sizes, numbers, plain = zip(*map(get, ws)) if ws else ((), (), ())
            count.append(sum(sizes) + 1)
            ids_hash.append(hashlib.sha256(" ".join((*numbers, end)).encode()).hexdigest())
            text = "".join(plain)
            text_hash.append(hashlib.sha256((text[1:] if text[:1] == " " else text).encode("utf-8", "surrogatepass")).hexdigest())
        return count, ids_hash, text_hash


def _utf8(run: bytes) -> str:
    """Bytes as text; each byte that fits nowhere gives one replacement character."""
    out, at = [], 0
    while at < len(run):
        b = run[at]
        size = 1 if b < 0x80 else 2 if 0xC2 <= b < 0xE0 else 3 if 0xE0 <= b < 0xF0 else 4 if 0xF0 <= b < 0xF5 else 0
        try:
            out.append(run[at : at + size].decode() if size else "�")
            at += max(size, 1)
        except UnicodeDecodeError:
            out.append("�")
            at += 1
    return "".join(out)


def codec(model_file: str) -> PieceCodec:
    """The codec of a model, kept by a Python worker until another operator needs it."""
    codecs = kept("piece_codec")
    if model_file not in codecs:
        codecs[model_file] = PieceCodec(model_file)
    return codecs[model_file]


def text_groups(texts: list[str | None]) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``SLICE_CHARS`` characters, at least one row each."""
    first, size = 0, 0
    for row, t in enumerate(texts):
        n = len(t) if t else 0
        if row > first and size + n > SLICE_CHARS:
            yield first, row
            first, size = row, 0
        size += n
    if len(texts) > first:
        yield first, len(texts)


def encode_documents(docs: DataFrame, model_file: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``ids`` (end id last) and ``decoded`` of every text."""
    where = model_file or model_path()
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(where)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for a, b in text_groups(texts):
                ids = [c.encode(t) for t in texts[a:b]]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(ids, pa.list_(pa.int32())), pa.array([c.decode(x) for x in ids], pa.string())], ["id", "ids", "decoded"])

    out = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).mapInArrow(run, f"id {kind}, ids array<int>, decoded string")
    return out.withColumnRenamed("id", id_col)


def codec_digest(docs: DataFrame, model_file: str | None = None) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: encode and decode every whole text."""
    where = model_file or model_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(where)
        for batch in batches:
            texts = batch.column(1)
            for k in range(0, len(texts), 512):
                part = texts.slice(k, 512).to_pylist()
                for a, b in text_groups(part):
                    n, ids, text = c.digest(part[a:b])
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(k + a, b - a), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(text, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec_digest(table(spark, sf_dir, "documents"))
