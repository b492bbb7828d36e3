"""Graph state as of any position: edge and node lifetimes, features, elapsed time.

Topology is never mutated: every edge is a row ``[from_pos, to_pos)``, so the graph after any
event is a filter and the neighbours an event sees are an equi-join with an interval.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evograph.stream.positions import micros

#: ``to_pos`` of a lifetime that does not end in the stream.
OPEN = 2**62


def edge_spans(ev: DataFrame, policy: str = "refresh") -> DataFrame:
    """``src, dst, from_pos, to_pos, first_ts, last_ts, weight, n_adds`` of every edge lifetime.

    ``refresh``: adding a live edge again refreshes its time and weight. ``multi``: it opens
    another parallel edge. Deleting an absent edge does nothing; a deletion or the deletion of
    an endpoint closes every open lifetime.
    """
    e = ev.where(F.col("dst").isNotNull() & F.col("kind").isin("edge_add", "edge_del")).select("pos", "src", "dst", "ts", "kind", "weight")
    gone = ev.where(F.col("kind") == "node_del").select("pos", F.col("src").alias("node"))
    pairs = e.select("src", "dst").distinct()
    closes = gone.join(pairs, (gone["node"] == pairs["src"])).select("pos", "src", "dst").unionByName(gone.join(pairs, (gone["node"] == pairs["dst"])).select("pos", "src", "dst")).distinct()
    closes = closes.select("pos", "src", "dst", F.lit(None).cast("timestamp_ntz").alias("ts"), F.lit("edge_del").alias("kind"), F.lit(None).cast("double").alias("weight"))
    e = e.unionByName(closes)
    w = Window.partitionBy("src", "dst").orderBy("pos", "kind")
    dels = F.sum((F.col("kind") == "edge_del").cast("long")).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    later_del = F.min(F.when(F.col("kind") == "edge_del", F.col("pos"))).over(w.rowsBetween(1, Window.unboundedFollowing))
    e = e.withColumns({"life": dels, "to_pos": F.coalesce(later_del, F.lit(OPEN))}).where("kind = 'edge_add'")
    if policy == "multi":
        return e.select("src", "dst", F.col("pos").alias("from_pos"), "to_pos", F.col("ts").alias("first_ts"), F.col("ts").alias("last_ts"), "weight", F.lit(1).cast("long").alias("n_adds"))
    return e.groupBy("src", "dst", "life").agg(
        F.min("pos").alias("from_pos"), F.min("to_pos").alias("to_pos"), F.min_by("ts", "pos").alias("first_ts"),
        F.max_by("ts", "pos").alias("last_ts"), F.max_by("weight", "pos").alias("weight"), F.count("*").alias("n_adds"),
    ).drop("life")


def graph_at(spans: DataFrame, pos: int) -> DataFrame:
    """Edges alive after the event at ``pos``."""
    return spans.where((F.col("from_pos") <= pos) & (F.col("to_pos") > pos)).select("src", "dst", "weight")


def node_spans(ev: DataFrame) -> DataFrame:
    """``node_id, from_pos, to_pos``: lifetimes of nodes; any event that names an absent node adds it."""
    adds = ev.where("kind <> 'node_del'").select("pos", F.explode(F.array_distinct(F.filter(F.array("src", "dst"), lambda x: x.isNotNull()))).alias("node_id"), F.lit(0).alias("del"))
    t = adds.unionByName(ev.where("kind = 'node_del'").select("pos", F.col("src").alias("node_id"), F.lit(1).alias("del")))
    w = Window.partitionBy("node_id").orderBy("pos")
    t = t.withColumns({"life": F.sum("del").over(w), "next_del": F.coalesce(F.min(F.when(F.col("del") == 1, F.col("pos"))).over(w.rowsBetween(1, Window.unboundedFollowing)), F.lit(OPEN))})
    return t.where("del = 0").groupBy("node_id", "life").agg(F.min("pos").alias("from_pos"), F.min("next_del").alias("to_pos")).drop("life")


def features_at(ev: DataFrame, pos: int) -> DataFrame:
    """``src, dst, weight``: the latest feature (weight) of each node or edge as of ``pos``; a node's dst is null."""
    f = ev.where((F.col("pos") <= pos) & F.col("kind").isin("node_feat", "edge_feat", "edge_add"))
    return f.groupBy("src", "dst").agg(F.max_by("weight", "pos").alias("weight"), F.max("pos").alias("at_pos"))


def last_time(ev: DataFrame, pos: int | None = None) -> DataFrame:
    """``node_id, last_ts, n``: latest interaction of each node."""
    e = ev if pos is None else ev.where(F.col("pos") <= pos)
    return e.select(F.explode(F.array_distinct(F.filter(F.array("src", "dst"), lambda x: x.isNotNull()))).alias("node_id"), "ts").groupBy("node_id").agg(F.max("ts").alias("last_ts"), F.count("*").alias("n"))


def elapsed(ev: DataFrame) -> DataFrame:
    """``pos, dt_u, dt_v``: seconds since each endpoint's previous interaction, 0 on the first."""
    side = F.explode(F.array(F.struct(F.lit("u").alias("side"), F.col("src").alias("node_id")), F.struct(F.lit("v").alias("side"), F.col("dst").alias("node_id"))))
    t = ev.select("pos", micros(F.col("ts")).alias("us"), side.alias("x")).select("pos", "us", "x.side", "x.node_id").where("node_id IS NOT NULL")
    one = t.groupBy("node_id", "pos", "us").agg(F.max((F.col("side") == "u").cast("int")).alias("is_u"), F.max((F.col("side") == "v").cast("int")).alias("is_v"))
    dt = (F.col("us") - F.coalesce(F.lag("us").over(Window.partitionBy("node_id").orderBy("pos")), F.col("us"))) / 1e6
    one = one.withColumn("dt", dt)
    return one.groupBy("pos").agg(F.max(F.when(F.col("is_u") == 1, F.col("dt"))).alias("dt_u"), F.max(F.when(F.col("is_v") == 1, F.col("dt"))).alias("dt_v"))
