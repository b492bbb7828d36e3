"""Snapshot sequences of a stream, their differences, and what they hide."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evograph.graph.spans import OPEN
from evograph.stream.positions import micros


def interval_of(ts: Column, seconds: int) -> Column:
    """Number of the interval that a time falls in."""
    return F.floor(micros(ts) / (seconds * 1_000_000)).cast("long")


def boundaries(ev: DataFrame, seconds: int) -> DataFrame:
    """``snap_id, last_pos``: last event of every interval that has events."""
    return ev.groupBy(interval_of(F.col("ts"), seconds).alias("snap_id")).agg(F.max("pos").alias("last_pos"), F.count("*").alias("n_events"))


def _life_by_snapshot(ev: DataFrame, spans: DataFrame, seconds: int) -> DataFrame:
    """Spans with the snapshots from which and before which they are visible."""
    at = ev.select("pos", interval_of(F.col("ts"), seconds).alias("snap"))
    s = spans.join(at.select(F.col("pos").alias("from_pos"), F.col("snap").alias("from_snap")), "from_pos")
    return s.join(at.select(F.col("pos").alias("to_pos"), F.col("snap").alias("to_snap")), "to_pos", "left").select("src", "dst", "from_snap", F.coalesce("to_snap", F.lit(OPEN)).alias("to_snap"))


def snapshots(ev: DataFrame, spans: DataFrame, seconds: int) -> DataFrame:
    """``snap_id, n_nodes, n_edges``: size of the graph at the end of every interval."""
    life = _life_by_snapshot(ev, spans, seconds).where("from_snap < to_snap")
    b = boundaries(ev, seconds).select("snap_id")
    # a running sum of edges that appear and go; edges counted once even if lifetimes touch
    change = life.select(F.col("from_snap").alias("snap_id"), F.lit(1).alias("d")).unionByName(life.where(F.col("to_snap") < OPEN).select(F.col("to_snap").alias("snap_id"), F.lit(-1).alias("d")))
    per = change.groupBy("snap_id").agg(F.sum("d").alias("d"))
    run = Window.orderBy("snap_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)  # one row per interval
    return b.join(per, "snap_id", "full").groupBy("snap_id").agg(F.sum(F.coalesce("d", F.lit(0))).alias("d")).select("snap_id", F.sum("d").over(run).alias("n_edges"))


def deltas(ev: DataFrame, spans: DataFrame, seconds: int) -> DataFrame:
    """``snap_id, src, dst, change``: edges that appear (1) or go (-1) between consecutive snapshots."""
    life = _life_by_snapshot(ev, spans, seconds).where("from_snap < to_snap")
    up = life.select(F.col("from_snap").alias("snap_id"), "src", "dst", F.lit(1).alias("change"))
    down = life.where(F.col("to_snap") < OPEN).select(F.col("to_snap").alias("snap_id"), "src", "dst", F.lit(-1).alias("change"))
    return up.unionByName(down).groupBy("snap_id", "src", "dst").agg(F.sum("change").alias("change")).where("change <> 0")


def hidden_events(ev: DataFrame, spans: DataFrame, seconds: int) -> DataFrame:
    """``snap_id, n_events, n_net, hidden``: edge events of an interval beyond its net changes."""
    e = ev.where(F.col("kind").isin("edge_add", "edge_del")).groupBy(interval_of(F.col("ts"), seconds).alias("snap_id")).agg(F.count("*").alias("n_events"))
    d = deltas(ev, spans, seconds).groupBy("snap_id").agg(F.count("*").alias("n_net"))
    n = F.coalesce("n_net", F.lit(0))
    return e.join(d, "snap_id", "left").select("snap_id", "n_events", n.alias("n_net"), (F.col("n_events") - n).alias("hidden"))
