"""In and out adjacency arrays with an index from neighbour to offset, and what is read from them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evograph.session import ensure_checkpoints
from evograph.windows.adaptive import touches
from evograph.windows.fixed import members

from evograph.graph.spans import graph_at


def adjacency(spans: DataFrame, pos: int, side: str = "out") -> DataFrame:
    """``node_id, nbrs``: time-ordered array of (from_pos, nbr, weight) of the graph after ``pos``."""
    own, nbr = ("src", "dst") if side == "out" else ("dst", "src")
    live = spans.where((F.col("from_pos") <= pos) & (F.col("to_pos") > pos))
    return live.groupBy(F.col(own).alias("node_id")).agg(F.array_sort(F.collect_list(F.struct("from_pos", F.col(nbr).alias("nbr"), "weight"))).alias("nbrs"))


def edge_index(adj: DataFrame) -> DataFrame:
    """Add ``offset_of``: neighbour to its offset in the array."""
    return adj.withColumn("offset_of", F.map_from_arrays("nbrs.nbr", F.sequence(F.lit(0), F.size("nbrs") - 1)))


def edge_lookup(index: DataFrame, pairs: DataFrame) -> DataFrame:
    """``u, v, offset, weight`` of the asked pairs; absent edges have nulls."""
    got = pairs.join(index.withColumnRenamed("node_id", "u"), "u", "left")
    off = F.col("offset_of")[F.col("v")]
    return got.select("u", "v", off.alias("offset"), F.get("nbrs", off)["weight"].alias("weight"))


def degrees(spans: DataFrame, pos: int) -> DataFrame:
    """``node_id, in_degree, out_degree`` after ``pos``."""
    g = graph_at(spans, pos)
    both = g.select(F.col("src").alias("node_id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(g.select(F.col("dst").alias("node_id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    return both.groupBy("node_id").agg(F.sum("i").alias("in_degree"), F.sum("o").alias("out_degree"))


def triangles(spans: DataFrame, pos: int) -> DataFrame:
    """Number of triangles of the undirected simple graph after ``pos``; edges point to the larger id."""
    e = graph_at(spans, pos).select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).where("a <> b").distinct()
    two = e.join(e.select(F.col("a").alias("b"), F.col("b").alias("c")), "b")
    return two.join(e.select("a", F.col("b").alias("c")), ["a", "c"]).agg(F.count("*").alias("triangles"))


def connected_components(spans: DataFrame, pos: int, rounds: int = 64) -> DataFrame:
    """``node_id, component``: the smallest node that each node of the graph after ``pos`` is connected to.

    Every node takes the least component of its neighbours, and then that of the node it is
    named after, so long paths halve; lineage is cut by a reliable checkpoint in every round.
    """
    g = graph_at(spans, pos).select(F.col("src").alias("a"), F.col("dst").alias("b"))
    ensure_checkpoints(g.sparkSession)
    both = g.unionByName(g.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().checkpoint()
    now = both.select(F.col("a").alias("node_id")).distinct().withColumn("component", F.col("node_id"))
    for _ in range(rounds):
        near = both.join(now.select(F.col("node_id").alias("b"), "component"), "b").groupBy(F.col("a").alias("node_id")).agg(F.min("component").alias("near"))
        low = now.join(near, "node_id").select("node_id", F.col("component").alias("old"), F.least("component", "near").alias("low"))
        above = now.select(F.col("node_id").alias("low"), F.col("component").alias("higher"))
        new = low.join(above, "low").select("node_id", "old", F.least("low", "higher").alias("component")).checkpoint()
        now = new.select("node_id", "component")
        if new.where("old <> component").isEmpty():
            return now
    raise RuntimeError(f"components still change after {rounds} rounds")


def window_hubs(ev: DataFrame, win: DataFrame, share: float = 0.05) -> DataFrame:
    """``window_id, node_id, n``: nodes that take part in at least ``share`` of a window's events."""
    size = members(ev, win).groupBy("window_id").agg(F.count("*").alias("size"))
    n = members(ev, win).join(touches(ev), "pos").groupBy("window_id", "node_id").agg(F.count("*").alias("n"))
    return n.join(size, "window_id").where(F.col("n") >= F.col("size") * share).select("window_id", "node_id", "n")


def pair_scores(spans: DataFrame, pos: int) -> DataFrame:
    """``a, b, common, jaccard, preferential`` of pairs with a common out-neighbour (plain link-prediction scores)."""
    g = graph_at(spans, pos).select("src", "dst").distinct()
    deg = g.groupBy("src").agg(F.count("*").alias("d"))
    common = g.select(F.col("src").alias("a"), "dst").join(g.select(F.col("src").alias("b"), "dst"), "dst").where("a < b").groupBy("a", "b").agg(F.count("*").alias("common"))
    c = common.join(deg.select(F.col("src").alias("a"), F.col("d").alias("da")), "a").join(deg.select(F.col("src").alias("b"), F.col("d").alias("db")), "b")
    return c.select("a", "b", "common", F.round(F.col("common") / (F.col("da") + F.col("db") - F.col("common")), 6).alias("jaccard"), (F.col("da") * F.col("db")).alias("preferential"))
