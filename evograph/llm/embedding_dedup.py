"""Embedding near-deduplication by PCA-ordered tiled comparison.

Vectors are scaled to length one and turned onto the principal axes of a bounded sample, so
most of a product lies in the leading dimensions. Equal vectors are one class with a count.
Classes are ordered by a tree of median cuts along leading axes; consecutive leaves are a group
of about ``GROUP_ROWS`` vectors, and a group is cut into tiles in that order. Groups are dealt on a
square grid: a vector goes once to each pair of its group with another, so it is copied as often
as there are groups and not as there are tiles. In a pair of groups, a pair of tiles whose boxes
are further apart than the threshold allows is never made. In a pair of tiles products are
accumulated over blocks of leading dimensions; what the remaining ones can add is at most the
product of both suffix norms, and a pair stops when its sum and that bound cannot reach the
threshold. Pairs that survive all blocks are decided by the cosine of the original vectors in
double precision.

A tile pair yields the number of links of each row and a spanning forest of its links, never
the pairs themselves, so a group of thousands of near copies costs tile rows, not pairs.
Components join the forests in rounds, each cut by a checkpoint.

Vectors of one length are compared with each other. Null, zero or non-finite vectors link with nothing.
Rows with one id and different vectors are each compared; the id's row has the sum of their
links. Repeated rows (equal id and vector) count once. Labels and other columns play no part;
an empty table gives an empty result. The axes only order the work: any sample gives the same links.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.llm.common import components, cut, forest, table

THRESHOLD = 0.95
#: Rows from which axes and cuts are computed; results do not depend on it.
SAMPLE_ROWS = 4096
TILE_ROWS = 1024
#: Vectors of a group; a task holds two groups.
GROUP_ROWS = 16384
BLOCKS = (8, 16, 32)
#: Slack for rounding in the bounds; decisions are made without it.
SLACK = 1e-9


def _unit(m: np.ndarray) -> np.ndarray:
    return m / np.linalg.norm(m, axis=1, keepdims=True)


def axes(sample: np.ndarray) -> np.ndarray:
    """Principal axes, strongest first, as columns (a rotation, so products are kept)."""
    _, _, vt = np.linalg.svd(sample - 0.0, full_matrices=True)
    return vt.T


class Tree:
    """Median cuts of a sample along the leading axes; a leaf is a tile."""

    def __init__(self, points: np.ndarray, leaves: int):
        self.cuts: list[tuple[int, float]] = []
        depth = max(0, int(np.ceil(np.log2(max(leaves, 1)))))
        level = [points]
        self.levels: list[np.ndarray] = []
        self.dims: list[np.ndarray] = []
        for _ in range(depth):
            dims, cuts, below = [], [], []
            for p in level:
                d = int(np.argmax(p[:, : min(16, p.shape[1])].std(axis=0))) if len(p) > 1 else 0
                c = float(np.median(p[:, d])) if len(p) else 0.0
                dims.append(d)
                cuts.append(c)
                below += [p[p[:, d] <= c], p[p[:, d] > c]]
            self.dims.append(np.array(dims))
            self.levels.append(np.array(cuts))
            level = below

    def leaf(self, p: np.ndarray) -> np.ndarray:
        at = np.zeros(len(p), dtype=np.int64)
        rows = np.arange(len(p))
        for dims, cuts in zip(self.dims, self.levels):
            at = 2 * at + (p[rows, dims[at]] > cuts[at])
        return at


def links_of(a: np.ndarray, b: np.ndarray, ra: np.ndarray, rb: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Row pairs of two tiles with cosine >= threshold; ``a, b`` rotated, ``ra, rb`` original unit vectors."""
    def suffix(m: np.ndarray, at: int) -> np.ndarray:
        return np.sqrt((m[:, at:] ** 2).sum(axis=1))

    total = a[:, : BLOCKS[0]] @ b[:, : BLOCKS[0]].T
    at = BLOCKS[0]
    alive = total + np.multiply.outer(suffix(a, at), suffix(b, at)) >= threshold - SLACK
    i, j = np.nonzero(alive)
    s = total[i, j]
    for nxt in (*BLOCKS[1:], a.shape[1]):
        if not len(i) or at >= a.shape[1]:
            break
        nxt = min(nxt, a.shape[1])
        s = s + np.concatenate([np.einsum("ij,ij->i", a[i[k : k + 65536], at:nxt], b[j[k : k + 65536], at:nxt]) for k in range(0, len(i), 65536)])
        keep = s + suffix(a, nxt)[i] * suffix(b, nxt)[j] >= threshold - SLACK
        i, j, s, at = i[keep], j[keep], s[keep], nxt
    exact = np.concatenate([np.einsum("ij,ij->i", ra[i[k : k + 65536]], rb[j[k : k + 65536]]) for k in range(0, len(i), 65536)]) if len(i) else s
    keep = exact >= threshold
    return i[keep], j[keep]


def _classes(vectors: DataFrame, id_col: str, vec_col: str) -> tuple[DataFrame, DataFrame]:
    """Distinct usable vectors with a class id and count; members with their class id."""
    kind = "float" if vectors.schema[vec_col].dataType.simpleString() == "array<float>" else "double"  # no wider than given
    v = vectors.select(F.col(id_col).alias("vec_id"), F.col(vec_col).cast(f"array<{kind}>").alias("v"))
    good = F.coalesce(F.forall("v", lambda x: F.coalesce((x == x) & (F.abs(x) < F.lit(float("inf"))), F.lit(False))) & F.exists("v", lambda x: x != 0), F.lit(False))
    v = v.where(good & F.col("vec_id").isNotNull()).withColumn("v", F.transform("v", lambda x: F.when(x == 0, F.lit(0.0).cast(kind)).otherwise(x)))
    v = v.withColumn("print", F.sha2(F.array_join(F.transform("v", lambda x: x.cast("string")), ","), 256)).dropDuplicates(["vec_id", "print"])
    reps = v.groupBy("print").agg(F.min("vec_id").alias("lead"), F.count("*").alias("copies"), F.first("v").alias("v"))
    return reps.select(F.monotonically_increasing_id().alias("class"), "print", "lead", "copies", "v", F.size("v").alias("size")), v.select("vec_id", "print")


def _rows(column: pa.ChunkedArray, size: int) -> np.ndarray:
    return np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in column.chunks]).reshape(-1, size).astype(np.float64) if len(column) else np.zeros((0, size))


def group_links(a: tuple, b: tuple | None, rotation: np.ndarray, threshold: float, tile_rows: int) -> list[tuple[int, int, int, int]]:
    """``kind, a, b, n`` of two groups (classes, ids, copies, vectors), or within one: links by class (0), forest links of ids (1)."""
    radius = float(np.sqrt(max(0.0, 2 - 2 * threshold))) + 1e-7

    def tiles(group: tuple) -> list[tuple]:
        names, ids, copies, m = group
        unit = _unit(m)
        turned = unit @ rotation
        cuts = range(0, len(ids), tile_rows)
        return [(names[k : k + tile_rows], ids[k : k + tile_rows], copies[k : k + tile_rows], unit[k : k + tile_rows], t, t.min(axis=0), t.max(axis=0)) for k in cuts if len(t := turned[k : k + tile_rows])]

    left = tiles(a)
    right = left if b is None else tiles(b)
    out: list[tuple[int, int, int, int]] = []
    for i, (ka, la, ca, ua, ta, lo_a, hi_a) in enumerate(left):
        for j in range(i if b is None else 0, len(right)):
            kb, lb, cb, ub, tb, lo_b, hi_b = right[j]
            gap = np.maximum(0, np.maximum(lo_a - hi_b, lo_b - hi_a))
            if (gap**2).sum() > radius**2:
                continue
            same = b is None and i == j
            x, y = links_of(ta, tb, ua, ub, threshold)
            if same:
                x, y = x[x < y], y[x < y]
            if not len(x):
                continue
            ids = la if same else np.concatenate([la, lb])  # both tiles in one space for the forest
            na, nb = np.bincount(x, weights=cb[y], minlength=len(la)), np.bincount(y, weights=ca[x], minlength=len(lb))
            out += [(0, int(ka[q]), 0, int(na[q])) for q in np.flatnonzero(na)]
            out += [(0, int(kb[q]), 0, int(nb[q])) for q in np.flatnonzero(nb)]
            out += [(1, int(ids[p]), int(ids[q]), 0) for p, q in forest(x, y if same else y + len(la), len(ids))]
    return out


def class_links(reps: DataFrame, threshold: float, size: int, tile_rows: int = TILE_ROWS, group_rows: int = GROUP_ROWS) -> DataFrame:
    """``kind, a, b, n`` over classes of one length: links by class (kind 0) and forest links of their ids (kind 1)."""
    spark = reps.sparkSession
    mine = reps.where(F.col("size") == size)
    n = mine.count()
    sample = _unit(np.array([r["v"] for r in mine.select("v").orderBy(F.xxhash64("print")).limit(SAMPLE_ROWS).collect()], dtype=np.float64))
    rotation = axes(sample)
    # enough groups that all tasks have a pair of them, and none with more than its rows
    groups = min(n, max(-(-n // group_rows), int(np.ceil(np.sqrt(2 * spark.sparkContext.defaultParallelism)))))
    tree = Tree(sample @ rotation, groups * max(1, -(-n // (groups * tile_rows))))
    leaves = 2 ** len(tree.levels)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                m = _unit(_rows(pa.chunked_array([b.column(3)]), size))
                leaf = tree.leaf(m @ rotation)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(leaf), pa.array(leaf * groups // leaves)], [*b.schema.names, "leaf", "part"])

    kept = mine.select("class", "lead", "copies", "v")
    placed = cut(kept.mapInArrow(place, f"class long, lead long, copies long, v {kept.schema['v'].dataType.simpleString()}, leaf long, part long"))
    # a crowded part is several groups, dealt by id; all groups meet each other
    sizes = sorted((r["part"], r["n"]) for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect())  # at most `groups` rows
    many = [max(1, -(-k // (2 * group_rows))) for _, k in sizes]
    first = np.cumsum([0, *many]).tolist()
    look = spark.createDataFrame([(p, f, m) for (p, _), f, m in zip(sizes, first, many)], "part long, first long, many long")
    grouped = placed.join(look, "part").withColumn("g", F.col("first") + F.pmod(F.xxhash64("class"), F.col("many")))
    met = grouped.withColumn("h", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(first[-1] - 1).cast("long"))))
    met = met.select("class", "lead", "copies", "v", "leaf", "g", F.least("g", "h").alias("i"), F.greatest("g", "h").alias("j"))

    def compare(t: pa.Table) -> pa.Table:
        i, j = t["i"][0].as_py(), t["j"][0].as_py()
        t, sides = t.sort_by("leaf"), []
        for k in {i, j} if i == j else (i, j):
            side = t.filter(pa.compute.equal(t["g"], k))
            sides.append((side["class"].to_numpy(), side["lead"].to_numpy(), side["copies"].to_numpy(), _rows(side["v"], size)))
        found = group_links(sides[0], None if i == j else sides[1], rotation, threshold, tile_rows)
        kind, a, b, n_ = zip(*found) if found else ((), (), (), ())
        return pa.table([pa.array(kind, pa.int32()), *(pa.array(c, pa.int64()) for c in (a, b, n_))], ["kind", "a", "b", "n"])

    return met.groupBy("i", "j").applyInArrow(compare, "kind int, a long, b long, n long")


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, id_col: str = "vec_id", vec_col: str = "embedding", tile_rows: int = TILE_ROWS, group_rows: int = GROUP_ROWS) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` of every vector."""
    reps, members = _classes(vectors, id_col, vec_col)
    reps = cut(reps)
    everyone = vectors.select(F.col(id_col).alias("vec_id"))
    sizes = sorted(r["size"] for r in reps.select("size").distinct().collect())
    if not sizes:
        return everyone.distinct().select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    found = cut(reduce(DataFrame.unionByName, [class_links(reps, threshold, k, tile_rows, group_rows) for k in sizes]))
    names = members.join(reps.select("print", "class", "lead", "copies"), "print")
    linked = found.where("kind = 0").groupBy(F.col("a").alias("class")).agg(F.sum("n").alias("links"))
    inside = names.where("vec_id <> lead").select(F.col("vec_id").alias("a"), F.col("lead").alias("b"))
    root = components(found.where("kind = 1").select("a", "b").unionByName(inside))
    own = names.join(linked, "class", "left").groupBy("vec_id").agg(F.sum(F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"))
    out = everyone.distinct().join(own, "vec_id", "left").join(root.withColumnRenamed("id", "vec_id"), "vec_id", "left")
    comp = F.coalesce("root", "vec_id")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), comp.alias("component_id"), (F.col("vec_id") == comp).alias("kept"))


def op5_pca_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


OP5_SQL = r"""
WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE embedding IS NOT NULL),
ok AS (SELECT vec_id, v, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS len FROM v),
unit AS (SELECT vec_id, list_transform(v, lambda x: x / len) AS u FROM ok WHERE len > 0 AND isfinite(len)),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM unit a JOIN unit b ON a.vec_id <> b.vec_id AND list_inner_product(a.u, b.u) >= 0.95),
r AS (SELECT * FROM (WITH RECURSIVE t(a, root) AS (SELECT vec_id, vec_id FROM embeddings UNION SELECT l.b, t.root FROM t JOIN l ON l.a = t.a AND t.root < l.b) SELECT a, min(root) AS root FROM t GROUP BY a)),
n AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT e.vec_id, coalesce(n.n, 0) AS n_links, r.root AS component_id, e.vec_id = r.root AS kept
FROM embeddings e JOIN r ON r.a = e.vec_id LEFT JOIN n ON n.a = e.vec_id
"""
