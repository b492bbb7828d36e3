"""Near-duplicate documents by ProbMinHash, banding and verification.

A document is its five-word shingles (fewer words: one shingle of all of them), each weighted by
how often it occurs (``weighting="set"``: by one). Every shingle is a Poisson process whose rate
is its weight: arrivals come after hashed exponential gaps, each falls on a hashed slot of the
sketch, and a slot keeps its first arrival. A shingle stops once its next arrival is later than
every slot's, so long texts end early. Two sketches agree in a slot with the probability Jaccard
similarity of the weighted sets, and by that same similarity, computed exactly, candidates are
verified. Where no shingle repeats it is the Jaccard similarity of the sets.

Documents with equal weighted sets are one class at once. Sketches of class representatives are
cut into bands; representatives that share a band are candidates. A band is never expanded into
pairs: its members meet its leader (another one in every band), verified links are joined to
components, and only members of one band that are still in different components meet each
other: pair by pair in small bands, in blocks in crowded ones. A block belongs to the largest
band of its members, so a crowd that shares twenty bands is compared once and not twenty times.

What is the same for a whole band or class comes to its members by a join on the key and one of
``DEALS`` deals, so a band that a third of all documents share is many tasks' work.

Nulls and texts without a word link with nothing. Texts are sketched and verified each by itself,
also those of one id; then classes that share an id are one. Repeated rows are copies:
``keep_one`` keeps one row of each class of texts, and one of each repeated row. Columns other than ``doc_id, text`` play no part;
an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.llm.common import by_deal, components, cut, deal_of, deals_present, mix, sequence_hashes, slices, table, tidy, words_of_group

SHINGLE = 5
SIMILARITY = 0.8
#: At similarity 0.8 a pair shares no band with probability 4e-4 or less.
BANDS, ROWS = 20, 5
#: Bands of so many members at most meet pair by pair, others in blocks of about so many shingles.
FEW, BLOCK_SHINGLES = 16, 100_000
#: Slack for rounding where similarities are compared.
SLACK = 1e-12
_U = np.uint64
_SLOT, _SUM1, _SUM2 = _U(0x9E6C63D0876A9A63), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9)


def shingles(h: np.ndarray, offsets: np.ndarray, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, hash and count of every distinct shingle of a group, ordered by text and hash."""
    n = np.diff(offsets)
    starts = np.maximum(n - size + 1, 0)
    doc = np.repeat(np.arange(len(n)), starts)
    at = np.arange(len(doc)) - np.repeat(np.cumsum(starts) - starts, starts) + offsets[:-1][doc]
    parts = [(doc, sequence_hashes(h, size)[at])]
    for k in range(1, size):
        few = np.flatnonzero(n == k)
        if len(few):
            parts.append((few, sequence_hashes(h, k)[offsets[few]]))
    doc, s = np.concatenate([x for x, _ in parts]), np.concatenate([y for _, y in parts])
    order = np.lexsort((s, doc))
    s, doc = s[order], doc[order]
    first = np.flatnonzero(np.append(True, (s[1:] != s[:-1]) | (doc[1:] != doc[:-1]))) if len(s) else np.zeros(0, dtype=np.int64)
    return doc[first], s[first], np.diff(np.append(first, len(s)))


def sketch(doc: np.ndarray, s: np.ndarray, weight: np.ndarray, n: int, slots: int) -> np.ndarray:
    """ProbMinHash of ``n`` weighted sets: the shingle that first arrives in each slot (0: empty set)."""
    when = np.full(n * slots, np.inf)
    who = np.zeros(n * slots, dtype=np.uint64)
    t = np.zeros(len(s))
    rate, live = weight.astype(np.float64), np.arange(len(s))
    step = 0
    while len(live):
        step += 1
        r = mix(s[live] + _U(step * 0x5851F42D4C957F2D % 2**64))
        t[live] += -np.log((r >> _U(11)).astype(np.float64) * 2.0**-53 + 2.0**-54) / rate[live]
        latest = when.reshape(n, slots).max(axis=1)
        live = live[t[live] < latest[doc[live]]]  # a later arrival changes nothing, nor does any after it
        slot = doc[live] * slots + (mix(s[live] * _SLOT + _U(step)) % _U(slots)).astype(np.int64)
        better = t[live] < when[slot]
        b, k = live[better], slot[better]
        order = np.lexsort((t[b], k))
        b, k = b[order], k[order]
        lead = np.append(True, k[1:] != k[:-1]) if len(k) else np.zeros(0, dtype=bool)
        when[k[lead]], who[k[lead]] = t[b[lead]], s[b[lead]]
    return who.reshape(n, slots)


def text_print() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit(""))).alias("print")


def sketches(docs: DataFrame, weighting: str = "tf", bands: int = BANDS, rows: int = ROWS, size: int = SHINGLE) -> DataFrame:
    """``doc_id, print, n, p1, p2, bands``: print of the text, number of shingles, print of the weighted set, band keys; texts with words only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                for a, b, data, offsets in slices(part.column(1).to_pylist()):
                    _, _, h, words = words_of_group(data, offsets)
                    doc, s, count = shingles(h, words, size)
                    weight = count if weighting == "tf" else np.ones(len(s))
                    m = b - a
                    sig = sketch(doc, s, weight, m, bands * rows).reshape(m, bands, rows)
                    key = np.zeros((m, bands), dtype=np.uint64)
                    for r in range(rows):
                        key = mix(key * _SUM1 + sig[:, :, r])
                    n = np.bincount(doc, minlength=m)
                    tagged = s if weighting == "set" else mix(s + count.astype(np.uint64) * _SUM2)
                    prints = []
                    for mult in (_SUM1, _SUM2):
                        total = np.concatenate(([_U(0)], np.cumsum(mix(tagged * mult))))
                        ends = np.cumsum(n)
                        prints.append((total[ends] - total[ends - n]).view(np.int64))
                    ok = np.flatnonzero(n > 0)
                    flat = pa.ListArray.from_arrays(pa.array(np.arange(len(ok) + 1, dtype=np.int32) * bands), pa.array(key[ok].reshape(-1).view(np.int64)))
                    yield pa.RecordBatch.from_arrays([part.column(0).slice(a, m).take(pa.array(ok)), part.column(2).slice(a, m).take(pa.array(ok)), pa.array(n[ok]), pa.array(prints[0][ok]), pa.array(prints[1][ok]), flat], ["doc_id", "print", "n", "p1", "p2", "bands"])
        tidy()

    return docs.select("doc_id", "text", text_print()).mapInArrow(run, "doc_id long, print long, n long, p1 long, p2 long, bands array<long>")


def shingle_sets(docs: DataFrame, weighting: str = "tf", size: int = SHINGLE) -> DataFrame:
    """``doc_id, s``: the weighted shingle set of each text as bytes, see ``weighted_set``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                for a, b, data, offsets in slices(part.column(1).to_pylist()):
                    _, _, h, words = words_of_group(data, offsets)
                    doc, s, count = shingles(h, words, size)
                    ends = np.searchsorted(doc, np.arange(b - a + 1))
                    out = []
                    for i, j in zip(ends[:-1].tolist(), ends[1:].tolist()):
                        weights = count[i:j].astype("<u4") if weighting == "tf" and (count[i:j] > 1).any() else count[:0].astype("<u4")
                        out.append(s[i:j].tobytes() + weights.tobytes())
                    yield pa.RecordBatch.from_arrays([part.column(0).slice(a, b - a), pa.array(np.diff(ends).astype(np.int32)), pa.array(out, pa.binary())], ["doc_id", "k", "s"])
        tidy()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, k int, s binary")


def weighted_set(k: int, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingles, 64 bits each, and their weights (not stored where all are one)."""
    s = np.frombuffer(data, dtype="<u8", count=k)
    return s, np.frombuffer(data, dtype="<u4", offset=8 * k).astype(np.float64) if len(data) > 8 * k else np.ones(k)


def probability_jaccard(x: np.ndarray, wx: np.ndarray, y: np.ndarray, wy: np.ndarray) -> float:
    """Sum over common shingles d of 1 / sum over all e of max(wx[e] / wx[d], wy[e] / wy[d])."""
    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
    if not len(i):
        return 0.0
    a, b = wx[i], wy[j]
    # by falling ratio, the first sets the maximum before a shingle's place and the second after it
    order = np.argsort(-a / b, kind="stable")
    a, b = a[order], b[order]
    first, second = np.cumsum(a), np.cumsum(b)
    return float((1 / ((wx.sum() - first[-1] + first) / a + (wy.sum() - second) / b)).sum())


def verified(pairs: DataFrame, sets: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The pairs ``(a, b)`` whose probability Jaccard similarity is at least ``similarity``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [
                probability_jaccard(*weighted_set(kx.as_py(), x.as_py()), *weighted_set(ky.as_py(), y.as_py())) >= similarity - SLACK
                for kx, x, ky, y in zip(*batch.columns[2:])
            ]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("k").alias("ka"), F.col("s").alias("sa")), "a")
    met = left.join(sets.select(F.col("doc_id").alias("b"), F.col("k").alias("kb"), F.col("s").alias("sb")), "b")
    return met.select("a", "b", "ka", "sa", "kb", "sb").mapInArrow(run, "a long, b long")


def _links(reps: DataFrame, docs: DataFrame, similarity: float, weighting: str, size: int) -> DataFrame:
    """``id, root`` of the representatives (``rep, n, bands, doc_id, print``) that link with another one."""
    buckets = reps.select("rep", F.col("n").cast("int").alias("n"), F.posexplode("bands").alias("band", "key"))
    buckets = buckets.select("rep", "n", F.xxhash64("band", "key").alias("gid"), deal_of("rep"))
    # names are hashes, so the least of name xor band is another member in every band
    crowd = buckets.groupBy("gid").agg(F.count("*").alias("m"), F.min(F.col("rep").bitwiseXOR(F.col("gid"))).alias("lead"), deals_present()).where("m > 1")
    crowd = by_deal(crowd.select("gid", F.col("lead").bitwiseXOR(F.col("gid")).alias("leader"), "deals"))
    shared = cut(buckets.join(crowd, ["gid", "deal"]).select("rep", "n", "gid", "deal", "leader"))
    stars = shared.where("rep <> leader").select("rep", "leader").distinct()
    where = reps.join(shared.select("rep").distinct(), "rep", "left_semi").select("rep", "doc_id", "print")
    texts = docs.select("doc_id", "text", text_print()).join(where, ["doc_id", "print"]).select(F.col("rep").alias("doc_id"), "text")
    sets = cut(shingle_sets(texts, weighting, size).dropDuplicates(["doc_id"]))
    pair = F.least("rep", "leader").alias("a"), F.greatest("rep", "leader").alias("b")
    # one leader of each representative first: most groups are whole after it
    one = stars.groupBy("rep").agg(F.min("leader").alias("leader")).select(*pair).distinct()
    found = cut(verified(one, sets, similarity))
    root = components(found)
    rest = _apart(stars.select(*pair).distinct().join(one, ["a", "b"], "left_anti"), root)
    found = cut(found.unionByName(verified(rest, sets, similarity)))
    root = components(found)
    # members of one band still apart, other than with the leader
    here = shared.select("rep", "n", "gid", "deal").join(root.withColumnRenamed("id", "rep"), "rep", "left").withColumn("root", F.coalesce("root", "rep"))
    by_root = here.groupBy("gid", "root").agg(F.count("*").alias("m"), F.sum("n").alias("size"), deals_present())
    crowds = by_root.groupBy("gid").agg(F.count("*").alias("roots"), F.sum("m").alias("m"), F.sum("size").alias("size"), F.max_by("root", "m").alias("most"), F.bit_or("deals").alias("deals"))
    here = cut(here.join(by_deal(crowds.where("roots > 1").drop("roots")), ["gid", "deal"]))
    few = here.where(F.col("m") <= FEW)
    x, y = few.select("gid", F.col("rep").alias("a"), F.col("root").alias("ra")), few.select("gid", F.col("rep").alias("b"), F.col("root").alias("rb"))
    apart = x.join(y, "gid").where((F.col("a") < F.col("b")) & (F.col("ra") != F.col("rb"))).select("a", "b").distinct()
    apart = apart.join(stars.select(*pair), ["a", "b"], "left_anti")
    found = found.unionByName(verified(apart, sets, similarity)).unionByName(_block_links(here.where(F.col("m") > FEW), sets, similarity))
    return components(found)


def _block_links(here: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links of crowded bands: members outside the largest component against all members, in blocks.

    A representative is in one block, that of its largest band, of about ``BLOCK_SHINGLES``
    shingles. Blocks whose members share a band make one row, whatever the number of bands they
    share, and a row yields links enough to join what belongs together.
    """
    home = here.groupBy("rep", "root").agg(F.max(F.struct("m", "gid", "size")).alias("home"), F.max(F.col("root") != F.col("most")).alias("minor"))
    deal = F.pmod(F.xxhash64("rep", F.lit(1)), F.ceil(F.col("home.size") / BLOCK_SHINGLES))
    home = cut(home.select("rep", "root", "minor", F.xxhash64("home.gid", deal).alias("block")))
    inside = here.select("gid", "rep", (F.col("root") != F.col("most")).alias("apart")).join(home.select("rep", "block"), "rep")
    left = inside.where("apart").select("gid", F.col("block").alias("i")).distinct()
    tiles = left.join(inside.select("gid", F.col("block").alias("j")).distinct(), "gid").select("i", "j").distinct()
    rows = home.join(sets.withColumnRenamed("doc_id", "rep"), "rep")
    item = F.collect_list(F.struct("rep", "root", "k", "s"))
    met = tiles.join(rows.where("minor").groupBy(F.col("block").alias("i")).agg(item.alias("left")), "i")
    met = met.join(rows.groupBy(F.col("block").alias("j")).agg(item.alias("right")), "j")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for left, right in zip(batch.column(0), batch.column(1)):
                found = block_links(*(_members(x.values) for x in (left, right)), similarity)
                yield pa.RecordBatch.from_arrays([pa.array([min(p) for p in found], pa.int64()), pa.array([max(p) for p in found], pa.int64())], ["a", "b"])
        tidy()

    return met.select("left", "right").mapInArrow(run, "a long, b long")


def _members(v: pa.StructArray) -> tuple[list[int], list[int], list[tuple[np.ndarray, np.ndarray]]]:
    return v.field("rep").to_pylist(), v.field("root").to_pylist(), [weighted_set(k, s) for k, s in zip(v.field("k").to_pylist(), v.field("s").to_pylist())]


def block_links(left: tuple, right: tuple, similarity: float) -> list[tuple[int, int]]:
    """Links between two blocks that join all components that their members' links join.

    An inverted list of the right block gives, for one left member, the sum over common
    shingles of the lesser share of the weight, which bounds the similarity to every right one.
    """
    (ra, roots_a, sa), (rb, roots_b, sb) = left, right
    above = {r: r for r in (*roots_a, *roots_b)}

    def find(x: int) -> int:
        while above[x] != x:
            above[x] = above[above[x]]
            x = above[x]
        return x

    sizes = np.array([len(s) for s, _ in sb])
    flat = np.concatenate([s for s, _ in sb])
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], np.repeat(np.arange(len(sb)), sizes)[order]
    share = np.concatenate([w / w.sum() for _, w in sb])[order]
    out = []
    for rep, root, (s, w) in zip(ra, roots_a, sa):
        lo, hi = np.searchsorted(flat, s, "left"), np.searchsorted(flat, s, "right")
        n = hi - lo
        at = np.arange(int(n.sum())) + np.repeat(lo - (np.cumsum(n) - n), n)
        bound = np.bincount(owner[at], weights=np.minimum(share[at], np.repeat(w / w.sum(), n)), minlength=len(sb))
        near = np.flatnonzero(bound >= similarity - SLACK)
        for j in near[np.argsort(-bound[near], kind="stable")].tolist():
            p, q = find(root), find(roots_b[j])
            if p != q and probability_jaccard(s, w, *sb[j]) >= similarity - SLACK:
                above[max(p, q)] = min(p, q)
                out.append((rep, rb[j]))
    return out


def _apart(pairs: DataFrame, root: DataFrame) -> DataFrame:
    """The pairs whose ends are not in one component yet."""
    p = pairs.join(root.select(F.col("id").alias("a"), F.col("root").alias("ra")), "a", "left").join(root.select(F.col("id").alias("b"), F.col("root").alias("rb")), "b", "left")
    return p.where(F.coalesce("ra", "a") != F.coalesce("rb", "b")).select("a", "b")


def text_classes(docs: DataFrame, similarity: float = SIMILARITY, weighting: str = "tf", bands: int = BANDS, rows: int = ROWS, size: int = SHINGLE) -> DataFrame:
    """``doc_id, print, deal, root, first_id`` of every row with an id and a word: its class of texts and the smallest id in it."""
    known = docs.where(F.col("doc_id").isNotNull())
    marks = cut(sketches(known, weighting, bands, rows, size))
    marks = marks.select("*", deal_of("doc_id", "print"))
    same = marks.groupBy("p1", "p2", "n").agg(F.min(F.struct("doc_id", "print")).alias("one"), F.first("bands").alias("bands"), deals_present())
    # a name for the text, not its id: an id may have several texts
    same = cut(same.select(F.xxhash64("p1", "p2", "n").alias("rep"), "p1", "p2", "n", "bands", "deals", "one.doc_id", "one.print"))
    root = cut(_links(same.select("rep", "n", "bands", "doc_id", "print"), known, similarity, weighting, size).withColumnRenamed("id", "rep"))
    whole = root.select("rep", "root").unionByName(root.select(F.col("root").alias("rep"), "root").distinct())  # roots have no row of their own
    linked = cut(whole.join(same.select("rep", "doc_id", deal_of("rep")), "rep"))
    least = by_deal(linked.groupBy("root").agg(F.min("doc_id").alias("least"), deals_present()))
    named = same.select("rep", "p1", "p2", "n", "doc_id", "deals").join(linked.join(least, ["root", "deal"]).select("rep", "root", "least"), "rep", "left")
    named = by_deal(named.select("p1", "p2", "n", "deals", F.coalesce("root", "rep").alias("root"), F.coalesce("least", "doc_id").alias("first_id")))
    return cut(marks.select("doc_id", "print", "deal", "p1", "p2", "n").join(named, ["p1", "p2", "n", "deal"]).select("doc_id", "print", "deal", "root", "first_id"))


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, weighting: str = "tf", bands: int = BANDS, rows: int = ROWS, size: int = SHINGLE) -> DataFrame:
    """``doc_id, class_id, kept`` of every document: the smallest id of its class, and whether it is that."""
    member = text_classes(docs, similarity, weighting, bands, rows, size)
    found = member.groupBy("doc_id").agg(F.min("first_id").alias("class_id"), F.max("first_id").alias("other"))
    several = found.where("class_id <> other").select("doc_id", "class_id")
    links = cut(member.join(several, "doc_id").where("first_id <> class_id").select(F.col("first_id").alias("a"), F.col("class_id").alias("b")).distinct())
    if not links.isEmpty():  # ids with texts of several classes join these
        joined = components(links).select(F.col("id").alias("class_id"), "root")
        found = found.join(joined, "class_id", "left").withColumn("class_id", F.coalesce("root", "class_id"))
    out = docs.select("doc_id").distinct().join(found.select("doc_id", "class_id"), "doc_id", "left")
    cls = F.coalesce("class_id", "doc_id")
    return out.select("doc_id", cls.alias("class_id"), F.coalesce(F.col("doc_id") == cls, F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """One row of each class of texts and of each repeated row, all columns as given; rows without an id stay."""
    member = text_classes(docs, similarity)
    first = by_deal(member.groupBy("root").agg(F.min(F.struct("doc_id", "print")).alias("first"), deals_present()))
    gone = member.join(first, ["root", "deal"]).where(F.struct("doc_id", "print") != F.col("first"))
    gone = gone.select(F.col("doc_id").alias("gone_id"), F.col("print").alias("gone_print")).distinct()
    mark = "print"
    while mark in docs.columns:
        mark += "_"
    rows = docs.withColumn(mark, text_print())
    rest = rows.join(gone, (rows["doc_id"] == gone["gone_id"]) & (rows[mark] == gone["gone_print"]), "left_anti")
    again = docs.where(F.col("doc_id").isNotNull()).select("doc_id", text_print()).groupBy("doc_id", "print").agg(F.count("*").alias("n")).where("n > 1")
    again = cut(again.select(F.col("doc_id").alias("again_id"), F.col("print").alias("again_print")))
    if not again.isEmpty():
        same = (rest["doc_id"] == again["again_id"]) & (rest[mark] == again["again_print"])
        rest = rest.join(again, same, "left_anti").unionByName(rest.join(again, same, "left_semi").dropDuplicates(["doc_id", mark]))
    return rest.drop(mark)


def op6_prob_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
