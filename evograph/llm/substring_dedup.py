"""Substring deduplication by recompression.

Words (maximal stretches of non-white-space) are the first symbols. A round names runs of one
symbol (in the rounds ``RUN_ROUNDS``), then pairs whose left symbol is in one half of a fixed
hash partition of the symbols and whose right symbol is in the other; neither has a longest
length, and rounds go on until no window has a symbol of its own left. A name is a hash of what
it stands for, so all tasks of all documents name alike without exchanging a dictionary.

What a round does depends on neighbours only, so in each round the symbols that are sure to be
the same in every occurrence of a window are known from the window alone: a leading or trailing
run may go on outside, and so may a pair begun by the last or ended by the first symbol. They
are left off, round by round, and the longest of the symbols that remain in the last round that
leaves any is the window's *top*. Equal windows have equal tops in equal places.

* *Reveal.* The tops of all windows are counted over the corpus. One found once is told to its
  text: its windows are found once. All others share their top with another place.
* *Verify.* These windows are counted by a 96-bit hash of their words; those found once are
  told to their text, too. The rest are repeated windows.

Equal texts are one text with a count; if that is over one all windows of it are repeated, and
they are told to the rest of the corpus once and not once for each copy. Both counts are combined before
they are shuffled, so a window or passage in a third of all documents is one row per task; no
group is gathered, nothing is joined on the hash of a window, and what comes back to a text is
bounded by its own length.

Nulls and empty texts have no words. A null id is an id of its own. Repeated rows (equal id
and text) repeat each other's windows and so lose every word of texts of ``window`` words or
more. Shorter texts lose nothing. A very long text is hashed in slices. Extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.llm.common import by_deal, deal_of, deals_present, mix, sequence_hashes, slices, table, tidy, words_of_group

WINDOW = 35
#: Rounds that name runs before pairs; later ones name pairs only, as a run step costs every window a symbol at both ends.
RUN_ROUNDS = (0, 2)
#: Words for which symbols are held at once.
STRETCH = 1 << 20
_U = np.uint64
_LEFT, _RIGHT, _RUN = _U(0xD6E8FEB86659FD93), _U(0xA0761D6478BD642F), _U(0xE7037ED1A0B428DB)


def name_runs(name: np.ndarray, start: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Names, first words (and the end) after runs are named, and the new place of every symbol."""
    d = doc[start[:-1]]
    head = np.append(True, (name[1:] != name[:-1]) | (d[1:] != d[:-1]))
    first = np.flatnonzero(head)
    times = np.diff(np.append(first, len(name)))
    new = name[first]
    runs = times > 1
    new[runs] = mix(new[runs] * _RUN + times[runs].astype(np.uint64))
    return new, np.append(start[first], start[-1]), np.cumsum(head) - 1


def name_pairs(name: np.ndarray, start: np.ndarray, doc: np.ndarray, number: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """As ``name_runs`` for pairs, with the half (true: right) of every old symbol."""
    d = doc[start[:-1]]
    half = (mix(name + _U((number + 1) * int(_LEFT) & (2**64 - 1))) & _U(1)).astype(bool)
    pair = ~half[:-1] & half[1:] & (d[1:] == d[:-1])
    keep = np.append(True, ~pair)
    new, at = name.copy(), np.flatnonzero(pair)
    new[at] = mix(name[at] * _LEFT + name[at + 1] * _RIGHT + _U(number))
    return new[keep], np.append(start[:-1][keep], start[-1]), np.cumsum(keep) - 1, half


def tops(h: np.ndarray, offsets: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of every window of every text of a group: its first word, and its top's name and place.

    A place is the top's first word (in the group), shifted by 16 bits, and its number of words.
    As a top follows from its window alone, a very long text is done in overlapping stretches.
    """
    parts = []
    for lo in range(0, max(len(h), 1), STRETCH):
        end = min(len(h), lo + STRETCH + window - 1)
        at, top, place = _tops(h[lo:end], np.clip(offsets, lo, end) - lo, window)
        parts.append((at + lo, top, place + (lo << 16)))
    return tuple(np.concatenate(x) for x in zip(*parts))


def _tops(h: np.ndarray, offsets: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = len(h)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    at = np.flatnonzero(np.arange(n) + window <= offsets[doc + 1]) if n else np.zeros(0, dtype=np.int64)
    top, place = np.zeros(len(at), dtype=np.uint64), np.zeros(len(at), dtype=np.int64)
    name, start, live = h, np.arange(n + 1), np.arange(len(at))
    first, last = at.copy(), at + window - 1  # the symbols of a window that are sure

    def settle(gone: np.ndarray) -> None:
        """Tops of windows that the round in hand leaves without a symbol."""
        a, b = first[gone], last[gone]
        size = np.diff(start)
        best = a.copy()
        for step in range(1, int((b - a).max()) + 1):
            j = np.minimum(a + step, b)
            better = (size[j] > size[best]) | ((size[j] == size[best]) & (name[j] < name[best]))
            best = np.where(better, j, best)
        top[live[gone]] = name[best]
        place[live[gone]] = start[best] << 16 | size[best]

    number = 0
    while len(live):
        for runs in (True, False):
            if runs:
                if number not in RUN_ROUNDS:
                    continue
                new, new_start, to = name_runs(name, start, doc)
                a, b = to[first] + 1, to[last] - 1
                gone = a > b
            else:
                new, new_start, to, half = name_pairs(name, start, doc, number)
                a, b = first + half[first], last - ~half[last]
                gone = a > b
                a, b = to[np.minimum(a, len(name) - 1)], to[np.maximum(b, 0)]
            if gone.any():
                settle(gone)
            live, first, last = live[~gone], a[~gone], b[~gone]
            name, start = new, new_start
            if not len(live):
                break
        number += 1
    return at, top, place


def _window_hashes(h: np.ndarray, at: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """64 and 32 bits of two hashes of each window."""
    one, two = (sequence_hashes(h, window, seed)[at] for seed in (1, 2))
    return one.view(np.int64), (two >> _U(32)).astype(np.uint32).view(np.int32)


def _prints() -> list[Column]:
    """96 bits that name a text; a null one is an empty one."""
    t = F.coalesce("text", F.lit(""))
    return [F.xxhash64(t).alias("p1"), F.hash(t).alias("p2")]


def distinct_texts(docs: DataFrame) -> DataFrame:
    """``p1, p2, z, n, deals``: every text once, compressed for the one shuffle it takes, and its number of rows."""
    df = docs.select(F.encode(F.coalesce("text", F.lit("")), "utf-8").alias("z"), *_prints(), deal_of("doc_id"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([pack(x) for x in b.column(0).to_pylist()], pa.binary()), *b.columns[1:]], b.schema.names)

    return df.mapInArrow(run, df.schema).groupBy("p1", "p2").agg(F.first("z").alias("z"), F.count("*").alias("n"), deals_present())


def _found_once(found: DataFrame, keys: list[str], name: str) -> DataFrame:
    """``p1, p2`` and by text the places whose key occurs once in the corpus."""
    n = found.groupBy(*keys).agg(F.sum("weight").alias("n"), F.min("p1").alias("p1"), F.min("p2").alias("p2"), F.min("place").alias("place"))
    return n.where("n = 1").groupBy("p1", "p2").agg(F.collect_list("place").alias(name))


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, bytes, tuple]]:
    """Groups of whole texts: the rows, which of them have copies, the joined text and its words."""
    unpack = zstandard.ZstdDecompressor().decompress
    for batch in batches:
        for k in range(0, batch.num_rows, 512):
            part = batch.slice(k, 512)
            for a, b, data, offsets in slices([unpack(x) for x in part.column("z").to_pylist()]):
                group = part.slice(a, b - a)
                yield group, group.column("n").to_numpy() > 1, data, (*words_of_group(data, offsets), offsets)
    tidy()


def _rows(group: pa.RecordBatch, copied: np.ndarray, offsets: np.ndarray, word: np.ndarray, columns: dict[str, np.ndarray]) -> pa.RecordBatch:
    """Rows of places in a group of texts; those of a text with copies weigh two."""
    d = np.searchsorted(offsets, word, side="right") - 1
    row = pa.array(d)
    return pa.RecordBatch.from_arrays([group.column("p1").take(row), group.column("p2").take(row), pa.array(copied[d].astype(np.int32) + 1), *map(pa.array, columns.values())], ["p1", "p2", "weight", *columns])


def top_rows(texts: DataFrame, window: int = WINDOW) -> DataFrame:
    """``p1, p2, weight, place, key`` of every top of every text, once by place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, copied, _, (_, _, h, offsets, _) in _groups(batches):
            _, key, place = tops(h, offsets, window)
            place, one = np.unique(place, return_index=True)  # a place has one name
            word = place >> 16
            own = offsets[np.searchsorted(offsets, word, side="right") - 1]
            yield _rows(group, copied, offsets, word, {"place": place - (own << 16), "key": key[one].view(np.int64)})

    return texts.mapInArrow(run, "p1 long, p2 int, weight int, place long, key long")


def _minus(place: np.ndarray, offsets: np.ndarray, once: list[list[int] | None], shift: int) -> np.ndarray:
    """Mask of the places that are not listed, by text and counted from its start, as found once."""
    gone = [np.asarray(x, dtype=np.int64) + (int(offsets[k]) << shift) for k, x in enumerate(once) if x]
    return ~np.isin(place, np.concatenate(gone)) if gone else np.ones(len(place), dtype=bool)


def _candidates(h: np.ndarray, offsets: np.ndarray, lone_tops: list, window: int) -> np.ndarray:
    """First words of the windows whose top is found elsewhere."""
    at, _, place = tops(h, offsets, window)
    return at[_minus(place, offsets, lone_tops, 16)]


def removal(texts: DataFrame, window: int = WINDOW) -> DataFrame:
    """``texts`` and two lists of places by text: tops, and windows of other tops, found once."""
    told = texts.join(_found_once(top_rows(texts, window), ["key"], "lone_tops"), ["p1", "p2"], "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, copied, _, (_, _, h, offsets, _) in _groups(batches):
            at = _candidates(h, offsets, group.column("lone_tops").to_pylist(), window)
            if len(at):
                h1, h2 = _window_hashes(h, at, window)
                own = offsets[np.searchsorted(offsets, at, side="right") - 1]
                yield _rows(group, copied, offsets, at, {"place": at - own, "h1": h1, "h2": h2})

    # all columns go in, used or not: the shuffled texts are then the same exchange for both uses
    rows = told.mapInArrow(run, "p1 long, p2 int, weight int, place long, h1 long, h2 int")
    return told.join(_found_once(rows, ["h1", "h2"], "lone_windows"), ["p1", "p2"], "left")


def _kept(group: pa.RecordBatch, copied: np.ndarray, h: np.ndarray, offsets: np.ndarray, window: int) -> np.ndarray:
    """Mask of the words that stay."""
    at = _candidates(h, offsets, group.column("lone_tops").to_pylist(), window)
    at = at[_minus(at, offsets, group.column("lone_windows").to_pylist(), 0)]
    flag = np.zeros(len(h) + 1, dtype=np.int64)
    flag[at] += 1
    np.add.at(flag, at + window, -1)
    whole = copied & (np.diff(offsets) >= window)
    return (np.cumsum(flag[:-1]) == 0) & ~np.repeat(whole, np.diff(offsets))


def _told_back(docs: DataFrame, others: list[str], texts: DataFrame, result: list[str]) -> DataFrame:
    """Documents with what is known of their text; copies come to it dealt over tasks."""
    rows = docs.select("doc_id", F.col("text").isNull().alias("empty"), *_prints(), deal_of("doc_id"), *[F.col(f"`{c}`").alias(f"o{i}") for i, c in enumerate(others)])
    return rows.join(by_deal(texts), ["p1", "p2", "deal"]).select("doc_id", "empty", *[f"o{i}" for i in range(len(others))], *result)


def dedup_digest(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``doc_id, n_words, n_removed, kept_sha256`` of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, copied, data, (s, e, h, offsets, _) in _groups(batches):
            keep = _kept(group, copied, h, offsets, window)
            n, gone, sha = [], [], []
            for k in range(group.num_rows):
                i, j = int(offsets[k]), int(offsets[k + 1])
                stays = np.flatnonzero(keep[i:j]) + i
                n.append(j - i)
                gone.append(j - i - len(stays))
                if len(stays) == j - i and j > i:
                    words = b" ".join(data[s[i] : e[j - 1]].split())
                else:
                    words = b" ".join([data[x:y] for x, y in zip(s[stays].tolist(), e[stays].tolist())])
                sha.append(hashlib.sha256(words).hexdigest())
            yield pa.RecordBatch.from_arrays([*(group.column(c) for c in ("p1", "p2", "deals")), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha)], ["p1", "p2", "deals", "n_words", "n_removed", "kept_sha256"])

    done = removal(distinct_texts(docs), window).mapInArrow(run, "p1 long, p2 int, deals long, n_words long, n_removed long, kept_sha256 string")
    return _told_back(docs, [], done, ["n_words", "n_removed", "kept_sha256"]).drop("empty")


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """The given documents with repeated words cut out of ``text``; layout between kept words stays.

    Texts that lose nothing are unchanged, and so are all other columns (``n_chars``, where
    it is there, follows the text).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, copied, data, (s, e, h, offsets, at) in _groups(batches):
            keep = _kept(group, copied, h, offsets, window)
            texts: list[str] = []
            for k in range(group.num_rows):
                i, j = int(offsets[k]), int(offsets[k + 1])
                edge = np.flatnonzero(np.diff(np.concatenate(([False], keep[i:j], [False])).astype(np.int8)))
                runs = [data[s[i + x] : e[i + y - 1]] for x, y in zip(edge[::2].tolist(), edge[1::2].tolist())]
                new = b"\n".join(runs) if not keep[i:j].all() else data[at[k] : at[k + 1] - 1]
                texts.append(new.decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([*(group.column(c) for c in ("p1", "p2", "deals")), pa.array(texts, pa.string())], ["p1", "p2", "deals", "new_text"])

    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    done = removal(distinct_texts(docs), window).mapInArrow(run, "p1 long, p2 int, deals long, new_text string")
    out = _told_back(docs, others, done, ["new_text"])
    text = F.when(~F.col("empty"), F.col("new_text"))
    back = {c: F.col(f"o{i}") for i, c in enumerate(others)} | {"doc_id": F.col("doc_id"), "text": text}
    if "n_chars" in back:
        back["n_chars"] = F.length(text).cast(docs.schema["n_chars"].dataType)
    return out.select(*[back[c].alias(c) for c in docs.columns])


def op1_recompression(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_digest(table(spark, sf_dir, "documents"))


OP1_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
p AS (SELECT doc_id, words, unnest(generate_series(1, len(words) - 34)) AS i FROM w WHERE len(words) >= 35),
k AS (SELECT doc_id, i, sha256(array_to_string(words[i:i + 34], ' ')) AS win FROM p),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY win) AS n FROM k) WHERE n > 1),
c AS (SELECT DISTINCT doc_id, unnest(generate_series(i, i + 34)) AS i FROM r),
g AS (SELECT doc_id, list(i) AS gone FROM c GROUP BY doc_id),
kept AS (SELECT w.doc_id, len(words) AS n_words, coalesce(len(gone), 0) AS n_removed,
    CASE WHEN gone IS NULL THEN words ELSE list_transform(list_sort(list_filter(generate_series(1, len(words)), lambda x: NOT list_contains(gone, x))), lambda x: words[x]) END AS words
  FROM w LEFT JOIN g ON w.doc_id = g.doc_id)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(n_removed AS BIGINT) AS n_removed, sha256(coalesce(array_to_string(words, ' '), '')) AS kept_sha256
FROM kept
"""
