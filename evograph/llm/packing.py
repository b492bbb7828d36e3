"""Best-fit packing by a configuration linear program over the length histogram.

Documents become token ids plus one end id; only longer ones are cut, into pieces of
``capacity``. Everything after that works on the histogram of piece lengths, which has
at most ``capacity`` entries however large the corpus is:

* a configuration (how many pieces of which length share a sequence) is a column of
  the linear program; multiplicative weights price the lengths, a knapsack dynamic
  program finds the best columns at those prices, several from one table, until every
  length is covered: ``Plan.lp_value`` is the program's value, ``Plan.lp_bound`` a dual bound;
* the fractional solution is rounded down to whole sequences. For what that leaves, columns
  are priced anew on the pieces still there, the longest first, and taken whole; only the last
  ``BEST_FIT_SHARE`` of the sequences are placed by best fit decreasing. All of it works on counts
  of lengths, not on pieces;
* a piece finds its place from its rank among the pieces of its length, so a common
  length is dealt over many tasks and no list of pieces is gathered anywhere.

Null text counts as empty (one end id). An empty table gives no rows. Repeated rows are
packed like others. Extra columns are ignored. Results on a fixed input differ between
runs only in which equal-length piece takes which of their places.
"""

from __future__ import annotations

import gc
import os
import re
import string
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evograph.llm.common import cut, kept, table, tidy
from evograph.llm.piece_codec import text_groups

CAPACITY = 4096
END_ID = 1
#: Least number of parts into which the pieces of one length are dealt when they are ranked, and their rows.
RANK_PARTS, RANK_ROWS = 256, 50_000
#: Rounds of multiplicative weights, and how fast prices follow coverage.
LP_ROUNDS, LP_RATE = 8, 8.0
#: Gap between the program's value and its bound at which rounds end, and their largest number.
LP_GAP, MOST_ROUNDS = 0.1, 32
#: Share of the sequences that best fit may place, and columns taken from one knapsack table.
BEST_FIT_SHARE, COLUMNS = 0.02, 256
TABLE_WORDS, TABLE_PARTS = 1_300_000, 600_000
#: White space as the tokenizer's ``\s`` has it; ``str.split`` also splits at 0x1C-0x1F.
_SPACE = re.compile("[\t-\r \x85\xa0  -     　]+")
_ODD = re.compile("[\x1c-\x1f]")
#: A word of Latin letters and then symbols is two units of the tokenizer.
_UNITS = re.compile("[A-Za-zª-įı-ſ]+")
_SYMBOLS = string.punctuation


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Recent:
    """A bounded table: when its newer half is full, entries not used of late go."""

    def __init__(self, size: int):
        self.half, self.new, self.old = size // 2, {}, {}

    def missing(self, words: set[str]) -> list[str]:
        """Words that have no entry; the others are in ``new`` afterwards."""
        if len(self.new) > self.half:
            self.old, self.new = self.new, {}
        new, old, out = self.new, self.old, []
        for w in words.difference(new):
            if w in old:
                new[w] = old[w]
            else:
                out.append(w)
        return out


class WordTokens:
    """Token ids of white-space words, as little-endian bytes, from bounded tables.

    The tokenizer drops white space and splits on it, so words are independent. Of a word
    that is letters and then symbols, both parts are units of the tokenizer, so equal
    lower-cased letters are encoded once; their ids are told apart by the word-end mark
    that the last id of each unit bears.
    """

    def __init__(self, path: str):
        # one thread: a task has one core, and idle threads of a pool burn the others' time
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.words, self.parts = Recent(TABLE_WORDS), Recent(TABLE_PARTS)
        vocab = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True

    def _one(self, words: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]

    def _letters(self, parts: list[str]) -> None:
        """Encode lower-case letter units many at a time."""
        groups = [parts[k : k + 256] for k in range(0, len(parts), 256)]
        for group, e in zip(groups, self.tokenizer.encode_batch_fast([" ".join(g) for g in groups], add_special_tokens=False)):
            ids = np.array(e.ids, dtype="<u4")
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) == len(group):
                data, at = ids.tobytes(), 0
                for w, end in zip(group, (4 * cuts).tolist()):
                    self.parts.new[w] = data[at:end]
                    at = end
            else:
                self.parts.new.update(zip(group, self._one(group)))

    def learn(self, words: set[str]) -> None:
        plain, tailed, odd = [], [], []
        for w in self.words.missing(words):
            core = w.rstrip(_SYMBOLS)
            if not (core.isalpha() if core.isascii() else _UNITS.fullmatch(core) and core.isalpha()):
                odd.append(w)
            elif core is w and w.islower():
                plain.append(w)
            else:
                tailed.append((w, core.lower(), w[len(core) :]))
        self._letters(self.parts.missing({*plain, *(a for _, a, _ in tailed)}))
        tails = list({b for _, _, b in tailed if b})
        tail = dict(zip(tails, self._one(tails)))
        known, parts = self.words.new, self.parts.new
        for w in plain:
            known[w] = parts[w]
        for w, core, end in tailed:
            known[w] = parts[core] + tail[end] if end else parts[core]
        known.update(zip(odd, self._one(odd)))

    @staticmethod
    def _folded(text: str) -> str:
        """Lower-cased where that is letter by letter, as the tokenizer does it too."""
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return text
        return text.lower()

    def ids(self, texts: list[str | None]) -> list[bytes]:
        texts = [self._folded(t) if t else t for t in texts]
        split = [(_SPACE.split(t) if _ODD.search(t) else t.split()) if t else [] for t in texts]
        out, todo, get = [b""] * len(split), [], self.words.new.get
        for k, ws in enumerate(split):
            try:
                out[k] = b"".join(map(get, ws))
            except TypeError:  # a word that the table lacks
                todo.append(k)
        if todo:
            self.learn(set().union(*[split[k] for k in todo]))
            get = self.words.new.__getitem__
            for k in todo:
                out[k] = b"".join(map(get, split[k]))
        return out


def _tokens(path: str) -> WordTokens:
    tokens = kept("packing")
    if path not in tokens:
        tokens[path] = WordTokens(path)
    return tokens[path]


def pieces(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32`` of every piece of every whole text."""
    where = tokenizer or tokenizer_path()
    end = np.array([end_id], dtype="<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _tokens(where)
        gc.disable()  # no cycles here, but many lists to look through
        for batch in batches:
            texts = batch.column(1)
            for k in range(0, len(texts), 512):
                part = texts.slice(k, 512).to_pylist()
                rows: list[int] = []
                cols: list[list[int]] = [[], [], [], []]
                for a, b in text_groups(part):
                    for row, ids in enumerate(t.ids(part[a:b]), k + a):
                        ids += end
                        for piece, at in enumerate(range(0, len(ids) // 4, capacity)):
                            chunk = ids[4 * at : 4 * (at + capacity)]
                            rows.append(row)
                            for col, v in zip(cols, (piece, at, len(chunk) // 4, zlib.crc32(chunk))):
                                col.append(v)
                kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), *(pa.array(c, kind) for c, kind in zip(cols, kinds))], ["doc_id", "piece", "start", "length", "ids_crc32"])
        gc.enable()
        tidy()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


@dataclass
class Plan:
    """``groups``: (sequences, ((length, copies), ...)) of like sequences; how many of them which step made."""

    groups: list[tuple[int, tuple[tuple[int, int], ...]]] = field(default_factory=list)
    lp_bound: float = 0.0
    lp_value: float = 0.0
    lp_sequences: int = 0
    priced_sequences: int = 0
    best_fit_sequences: int = 0

    @property
    def sequences(self) -> int:
        return sum(n for n, _ in self.groups)


def price_table(lengths: np.ndarray, prices: np.ndarray, capacity: int) -> np.ndarray:
    """Unbounded knapsack: the best value of lengths that fill each capacity exactly (-inf: none do)."""
    best = np.full(capacity + 1, -np.inf)
    best[0] = 0.0
    for c in range(int(lengths[0]), capacity + 1):
        k = np.searchsorted(lengths, c, side="right")
        best[c] = (best[c - lengths[:k]] + prices[:k]).max()
    return best


def _column(best: np.ndarray, lengths: np.ndarray, prices: np.ndarray, room: np.ndarray, first: int, capacity: int, slack: float, want: np.ndarray | None, full: bool = True) -> dict[int, int] | None:
    """A column through ``first``: at every step, of the near-best lengths that ``room`` has, the most wanted (or longest) one.

    If not ``full``, it may leave room where no lengths fill the rest.
    """
    items, c = {first: 1}, capacity - int(lengths[first])
    if not full and not np.isfinite(best[c]):
        c = int(best[: c + 1].argmax())
    while c > 0:
        k = int(np.searchsorted(lengths, c, side="right"))
        v = best[c - lengths[:k]] + prices[:k]
        near = np.isfinite(v) & (v >= best[c] * (1 - slack)) & (room[:k] > 0)
        for i, n in items.items():
            if i < k and room[i] < n + 1:
                near[i] = False
        at = np.flatnonzero(near)
        if not len(at):
            return None
        # the longest one where it ends the column or nothing is wanted more
        i = int(at[-1]) if want is None or lengths[at[-1]] == c else int(at[want[at].argmax()])
        items[i] = items.get(i, 0) + 1
        c -= int(lengths[i])
    return items


def _key(lengths: np.ndarray, items: dict[int, int]) -> tuple[tuple[int, int], ...]:
    return tuple(sorted((int(lengths[j]), n) for j, n in items.items()))


def solve_lp(lengths: np.ndarray, counts: np.ndarray, capacity: int, rounds: int = LP_ROUNDS) -> tuple[dict[tuple[tuple[int, int], ...], float], float]:
    """Columns of the configuration program that cover all counts, with their amounts, and a dual lower bound.

    Rounds are doubled, so steps are smaller, until the gap is ``LP_GAP`` or there are ``MOST_ROUNDS``.
    """
    while True:
        amount, bound = _solve(lengths, counts, capacity, rounds)
        if sum(amount.values()) <= (1 + LP_GAP) * bound or 2 * rounds > MOST_ROUNDS:
            return amount, bound
        rounds *= 2


def _solve(lengths: np.ndarray, counts: np.ndarray, capacity: int, rounds: int) -> tuple[dict[tuple[tuple[int, int], ...], float], float]:
    """One solution by multiplicative weights.

    In every round the weight of a length falls exponentially with its coverage, one knapsack
    table is made at lengths times weights, and every length that lags behind the round's share,
    least covered first, gets a near-best column through it, by as much as closes its gap.
    """
    cover = np.zeros(len(lengths))
    amount: dict[tuple[tuple[int, int], ...], float] = {}
    bound = float((lengths * counts).sum() / capacity)

    def add(items: dict[int, int], step: float) -> None:
        key = _key(lengths, items)
        amount[key] = amount.get(key, 0.0) + step
        for j, n in items.items():
            cover[j] += n * step / counts[j]

    for r in range(1, rounds + 1):
        target = r / rounds
        prices = lengths * np.exp(LP_RATE * np.clip((r - 1) / rounds - cover, -1, 1))
        best = price_table(lengths, prices, capacity)
        top = np.maximum(best, 0).max()
        bound = max(bound, float((prices * counts).sum() / top)) if top > 0 else bound
        most = min(1.0, target + 2 / rounds) if r < rounds else 1.0
        for i in np.argsort(cover, kind="stable").tolist():
            if cover[i] > target - 1e-9:
                continue
            room = np.where(cover < most - 1e-9, np.ceil(counts), 0)
            items = _column(best, lengths, prices, room, i, capacity, 0.3, target - cover, False) or _column(best, lengths, prices, room, i, capacity, 1.0, target - cover, False)
            if items:
                free = min(float((most - cover[j]) * counts[j] / n) for j, n in items.items())
                add(items, max(0.0, min(free, float((target - cover[i]) * counts[i] / items[i]))))
    for i in np.argsort(-lengths, kind="stable").tolist():
        if cover[i] < 1 - 1e-9:  # nothing left that fills these up: cover others twice, or leave room
            items = _column(best, lengths, prices, np.full(len(lengths), np.inf), i, capacity, 1e-3, 1 - cover, False) or {i: capacity // int(lengths[i])}
            add(items, float((1 - cover[i]) * counts[i] / items[i]))
    return {k: x for k, x in amount.items() if x > 0}, bound


def _fullest(lengths: np.ndarray, room: np.ndarray, first: int, capacity: int) -> dict[int, int]:
    """The column through ``first`` that pieces still there fill most, where none fills it: a bounded knapsack by lengths."""
    own = room.copy()
    own[first] -= 1
    free = capacity - int(lengths[first])
    near = np.flatnonzero((own > 0) & (lengths <= free))
    via = np.full(free + 1, -1, dtype=np.int64)  # the last length that reached a sum first
    reached = np.zeros(free + 1, dtype=bool)
    reached[0] = True
    for i in near[::-1].tolist():  # longest first
        for _ in range(int(min(own[i], free // lengths[i]))):
            step = int(lengths[i])
            new = np.flatnonzero(reached[:-step] & ~reached[step:]) + step if step <= free else near[:0]
            if not len(new):
                break
            reached[new], via[new] = True, i
        if reached[free]:
            break
    items, c = {first: 1}, int(np.flatnonzero(reached)[-1])
    while c > 0:
        i = int(via[c])
        items[i] = items.get(i, 0) + 1
        c -= int(lengths[i])
    return items


def priced_columns(left: dict[int, int], capacity: int, until: float) -> list[tuple[int, tuple[tuple[int, int], ...]]]:
    """Whole full columns out of the pieces ``left`` (which it lowers), until these need no more than ``until`` sequences.

    Prices are the lengths, the dual solution wherever sequences can be filled; longer
    pieces go first, as short ones still fill any gap later.
    """
    groups: list[tuple[int, tuple[tuple[int, int], ...]]] = []
    while True:
        lengths = np.array(sorted(k for k, n in left.items() if n), dtype=np.int64)
        room = np.array([left[k] for k in lengths.tolist()], dtype=np.float64)
        if (lengths * room).sum() <= until * capacity:
            return groups
        prices = lengths.astype(np.float64)
        best, found = price_table(lengths, prices, capacity), 0
        for i in range(len(lengths) - 1, -1, -1):
            while room[i] > 0 and found < COLUMNS and (items := _column(best, lengths, prices, room, i, capacity, 1e-9, None) or _fullest(lengths, room, i, capacity)):
                n = int(min(room[j] // k for j, k in items.items()))
                groups.append((n, _key(lengths, items)))
                for j, k in items.items():
                    room[j] -= n * k
                found += 1
        left.update(zip(lengths.tolist(), room.astype(np.int64).tolist()))
        if not found:
            return groups


def best_fit(left: dict[int, int], capacity: int) -> list[tuple[int, tuple[tuple[int, int], ...]]]:
    """Best fit decreasing on counts: like bins stay one group, split only when needed."""
    import bisect

    rooms: list[int] = []  # free room of open groups, ascending
    groups: dict[int, list[tuple[int, tuple]]] = {}

    def put(room: int, n: int, items: tuple) -> None:
        if room not in groups:
            bisect.insort(rooms, room)
            groups[room] = []
        groups[room].append((n, items))

    for length in sorted(left, reverse=True):
        n = left[length]
        while n:
            at = bisect.bisect_left(rooms, length)
            if at == len(rooms):  # new bins, each as full of this length as it goes
                per = capacity // length
                if n >= per:
                    put(capacity - per * length, n // per, ((length, per),))
                if n % per:
                    put(capacity - (n % per) * length, 1, ((length, n % per),))
                break
            room = rooms[at]
            have, items = groups[room].pop()
            if not groups[room]:
                del groups[room]
                rooms.pop(at)
            per = min(room // length, n)
            used = min(have, n // per)
            put(room - per * length, used, (*items, (length, per)))
            if have > used:
                put(room, have - used, items)
            n -= used * per
    return [g for room in groups.values() for g in room]


def make_plan(histogram: dict[int, int], capacity: int = CAPACITY, rounds: int = LP_ROUNDS) -> Plan:
    """Whole sequences for a length histogram: the rounded program, priced columns, best fit for the last ones."""
    plan = Plan()
    if not histogram:
        return plan
    lengths = np.array(sorted(histogram), dtype=np.int64)
    counts = np.array([histogram[int(x)] for x in lengths], dtype=np.float64)
    amount, plan.lp_bound = solve_lp(lengths, counts, capacity, rounds)
    plan.lp_value, left = sum(amount.values()), dict(histogram)
    if plan.lp_value > (1 + LP_GAP) * plan.lp_bound:
        amount = {}  # not solved to its gap: its columns waste what others need, so all are priced anew
    for items, x in sorted(amount.items(), key=lambda kv: (-sum(a * b for a, b in kv[0]), -kv[1], kv[0])):
        n = int(min([x + 1e-6, *(left[length] // k for length, k in items)]))
        if n > 0:
            plan.groups.append((n, items))
            plan.lp_sequences += n
            for length, k in items:
                left[length] -= n * k
    priced = priced_columns(left, capacity, BEST_FIT_SHARE * plan.lp_bound)
    rest = best_fit({k: v for k, v in left.items() if v}, capacity)
    plan.priced_sequences, plan.best_fit_sequences = sum(n for n, _ in priced), sum(n for n, _ in rest)
    plan.groups += priced + rest
    return plan


def _places(plan: Plan) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ranges of ranks by length: sort key, first rank, first sequence, copies, offset."""
    at: dict[int, int] = {}
    rows, seq = [], 0
    for n, items in plan.groups:
        offset = 0
        for length, k in items:
            lo = at.get(length, 0)
            rows.append(((length << 44) + lo, lo, seq, k, offset))
            at[length] = lo + n * k
            offset += k * length
        seq += n
    cols = np.array(sorted(rows), dtype=np.int64).reshape(-1, 5)
    return tuple(np.ascontiguousarray(cols[:, i]) for i in range(5))


def pack(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row per piece with its sequence and place in it."""
    part = cut(pieces(docs, tokenizer, capacity, end_id))
    histogram = {r["length"]: r["n"] for r in part.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    key, first, seq, copies, offset = _places(make_plan(histogram, capacity))
    parts = max(RANK_PARTS, max(histogram.values(), default=0) // RANK_ROWS)
    dealt = part.withColumn("deal", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(parts)).cast("int"))
    sizes = dealt.groupBy("length", "deal").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("deal").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("length", "deal", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = dealt.withColumn("local", F.row_number().over(Window.partitionBy("length", "deal").orderBy("doc_id", "piece")) - 1)
    ranked = ranked.join(starts, ["length", "deal"]).withColumn("rank", F.col("base") + F.col("local"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = (b.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (3, 5))
            at = np.searchsorted(key, (length << 44) + rank, side="right") - 1
            place = rank - first[at]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(seq[at] + place // copies[at]), pa.array(offset[at] + place % copies[at] * length)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def op7_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
