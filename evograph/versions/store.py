"""Versioned node vectors as a long table ``node_id, version, at_pos, z``."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def init(nodes: DataFrame, emb: DataFrame) -> DataFrame:
    """Version 0 of every node: the embedding at ``node_id mod count`` (the vectors are few; checked before they are sent)."""
    n, size = emb.agg(F.count("*"), F.sum(F.size("embedding"))).first()
    e = emb.select(F.col("vec_id").alias("slot"), F.col("embedding").alias("z"))
    e = F.broadcast(e) if size is not None and size * 4 < 64 << 20 else e
    z = nodes.select("node_id").distinct().withColumn("slot", F.pmod(F.col("node_id"), F.lit(n))).join(e, "slot")
    return z.select("node_id", F.lit(0).cast("int").alias("version"), F.lit(-1).cast("long").alias("at_pos"), "z")


def append(versions: DataFrame, updates: DataFrame) -> DataFrame:
    """Add ``updates(node_id, at_pos, z)``; versions go on from each node's latest, in order of position."""
    top = versions.groupBy("node_id").agg(F.max("version").alias("top"))
    nth = F.row_number().over(Window.partitionBy("node_id").orderBy("at_pos"))
    new = updates.withColumn("nth", nth).join(top, "node_id", "left")
    return versions.unionByName(new.select("node_id", (F.coalesce("top", F.lit(-1)) + F.col("nth")).cast("int").alias("version"), "at_pos", "z"))


def latest(versions: DataFrame) -> DataFrame:
    """The newest version of every node."""
    return versions.groupBy("node_id").agg(F.max_by(F.struct("version", "at_pos", "z"), "version").alias("v")).select("node_id", "v.*")


def get(versions: DataFrame, asked: DataFrame) -> DataFrame:
    """``asked(node_id, version)`` with its vector; an absent version has none."""
    return asked.join(versions, ["node_id", "version"], "left")


def as_of(versions: DataFrame, asked: DataFrame) -> DataFrame:
    """``asked(node_id, pos)`` with the version that a read at ``pos`` sees: the last written before it."""
    v = versions.select("node_id", F.col("at_pos").alias("pos"), F.lit(1).alias("is_read"), F.struct("version", "z").alias("v")).withColumn("is_read", F.lit(1))
    a = asked.select("node_id", "pos", F.lit(0).alias("is_read"), F.lit(None).cast(v.schema["v"].dataType).alias("v"))
    w = Window.partitionBy("node_id").orderBy("pos", "is_read").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(v).withColumn("v", F.last("v", ignorenulls=True).over(w)).where("is_read = 0").select("node_id", "pos", "v.version", "v.z")


def vacuum(versions: DataFrame, min_start_pos: int) -> DataFrame:
    """Drop versions that no read at ``min_start_pos`` or later can see."""
    nxt = F.lead("at_pos").over(Window.partitionBy("node_id").orderBy("version"))
    return versions.withColumn("nxt", nxt).where(F.col("nxt").isNull() | (F.col("nxt") >= min_start_pos)).drop("nxt")
