"""What an event reads (its k-hop surroundings as of its position) and what it writes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evograph.windows.adaptive import touches


def _hop(reads: DataFrame, spans: DataFrame, direction: str, deletions: DataFrame) -> DataFrame:
    """Neighbours of read nodes alive at the reader's position; a deletion also sees what it deletes."""
    out = None
    for own, nbr, use in (("dst", "src", direction in ("in", "both")), ("src", "dst", direction in ("out", "both"))):
        if not use:
            continue
        s = spans.select(F.col(own).alias("node_id"), F.col(nbr).alias("nbr"), "from_pos", "to_pos")
        hit = reads.join(deletions, "pos", "left").join(s, "node_id").where((F.col("from_pos") <= F.col("pos")) & (F.col("to_pos") + F.coalesce("is_del", F.lit(0)) > F.col("pos")))
        hit = hit.select("pos", F.col("nbr").alias("node_id"))
        out = hit if out is None else out.unionByName(hit)
    return out


def affected_nodes(ev: DataFrame, spans: DataFrame, k: int = 1, direction: str = "in") -> DataFrame:
    """``pos, node_id``: endpoints and their ``k``-hop neighbours after the event's own change."""
    reads = touches(ev)
    deletions = ev.where(F.col("kind").isin("edge_del", "node_del")).select("pos", F.lit(1).alias("is_del"))
    for _ in range(k):
        reads = reads.unionByName(_hop(reads, spans, direction, deletions)).distinct()
    return reads


def affected_edges(reads: DataFrame, spans: DataFrame) -> DataFrame:
    """``pos, src, dst``: live edges between nodes that an event reads."""
    s = spans.select("src", "dst", "from_pos", "to_pos")
    one = reads.withColumnRenamed("node_id", "src").join(s, "src").where((F.col("from_pos") <= F.col("pos")) & (F.col("to_pos") > F.col("pos")))
    return one.select("pos", "src", "dst").join(reads.withColumnRenamed("node_id", "dst"), ["pos", "dst"]).select("pos", "src", "dst").distinct()


def subgraphs(reads: DataFrame, edges: DataFrame) -> DataFrame:
    """One row per event: sorted nodes and edges it reads."""
    v = reads.groupBy("pos").agg(F.array_sort(F.collect_set("node_id")).alias("nodes"))
    e = edges.groupBy("pos").agg(F.array_sort(F.collect_set(F.struct("src", "dst"))).alias("edges"))
    return v.join(e, "pos", "left")


def writes(ev: DataFrame, reads: DataFrame | None = None, diffuse: bool = False) -> DataFrame:
    """``pos, node_id``: endpoints, or with diffusion all nodes read."""
    return reads if diffuse and reads is not None else touches(ev)


def reach(spans: DataFrame, pos: int, seeds: DataFrame, k: int, direction: str = "both") -> DataFrame:
    """``node_id, hops``: nodes within ``k`` hops of ``seeds(node_id)`` after ``pos``."""
    g = spans.where((F.col("from_pos") <= pos) & (F.col("to_pos") > pos)).select("src", "dst")
    e = {"out": g, "in": g.select(F.col("dst").alias("src"), F.col("src").alias("dst")), "both": g.unionByName(g.select(F.col("dst").alias("src"), F.col("src").alias("dst")))}[direction]
    seen = seeds.select("node_id", F.lit(0).alias("hops"))
    for h in range(1, k + 1):
        step = seen.where(F.col("hops") == h - 1).join(e, F.col("node_id") == F.col("src")).select(F.col("dst").alias("node_id"), F.lit(h).alias("hops"))
        seen = seen.unionByName(step).groupBy("node_id").agg(F.min("hops").alias("hops"))
    return seen
