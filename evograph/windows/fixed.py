"""Disjoint batches, fixed sliding windows, and windows by time.

Windows are ranges ``[start_pos, end_pos)`` computed from the stream's length alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def batches(spark: SparkSession, n: int, size: int = 200) -> DataFrame:
    """Disjoint batches; the last may be shorter."""
    w = spark.range(0, -(-n // size)).select(F.col("id").alias("window_id"), (F.col("id") * size).alias("start_pos"))
    return w.withColumn("end_pos", F.least(F.col("start_pos") + size, F.lit(n)))


def fixed(spark: SparkSession, n: int, size: int = 200, stride: int | None = None, stride_ratio: float | None = None, tail: str = "stop", bounds: str = "half_open") -> DataFrame:
    """Windows of ``size`` every ``stride`` events.

    ``tail``: ``full`` gives whole windows only, ``stop`` ends with the first window that
    reaches the end, ``shrink`` goes on with ever shorter windows. ``bounds="listing"`` takes
    one event more per window, as an inclusive end does.
    """
    step = stride if stride is not None else max(1, int(stride_ratio * size)) if stride_ratio is not None else 40
    if tail == "full":
        count = 0 if n < size else (n - size) // step + 1
    elif tail == "stop":
        count = 0 if n == 0 else 1 if n <= size else -(-(n - size) // step) + 1
    elif tail == "shrink":
        count = -(-n // step)
    else:
        raise ValueError(f"unknown tail {tail!r}")
    more = 1 if bounds == "listing" else 0
    w = spark.range(0, count).select(F.col("id").alias("window_id"), (F.col("id") * step).alias("start_pos"))
    return w.withColumn("end_pos", F.least(F.col("start_pos") + size + more, F.lit(n)))


def by_time(ev: DataFrame, size: str, slide: str | None = None, gap: str | None = None, by: str | None = None) -> DataFrame:
    """Comparators: tumbling or sliding time windows, or sessions of a key, with their counts."""
    w = F.session_window("ts", gap) if gap else F.window("ts", size, slide or size)
    keys = [F.col(by)] if by else []
    return ev.groupBy(w.alias("w"), *keys).agg(F.count("*").alias("n")).select("w.start", "w.end", *([by] if by else []), "n")


def members(ev: DataFrame, win: DataFrame, width: int = 1024) -> DataFrame:
    """``window_id, pos``: events of each window, by an equi-join on position buckets."""
    w = win.withColumn("b", F.explode(F.sequence((F.col("start_pos") / width).cast("long"), ((F.col("end_pos") - 1) / width).cast("long"))))
    e = ev.select("pos", (F.col("pos") / width).cast("long").alias("b"))
    return w.join(e, "b").where((F.col("pos") >= F.col("start_pos")) & (F.col("pos") < F.col("end_pos"))).select("window_id", "pos")


def members_fixed(ev: DataFrame, size: int, stride: int, count: int) -> DataFrame:
    """Membership in fixed windows in closed form: no join at all."""
    first = F.greatest(F.lit(0), F.ceil((F.col("pos") - size + 1) / stride))
    last = F.least(F.lit(count - 1), F.floor(F.col("pos") / stride))
    return ev.where(first <= last).select(F.explode(F.sequence(first.cast("long"), last.cast("long"))).alias("window_id"), "pos")


def stats(win: DataFrame, low: int | None = None, high: int | None = None) -> DataFrame:
    """Count, least, mean and greatest size, and the shares of windows at both limits."""
    size = F.col("end_pos") - F.col("start_pos")
    share = lambda v: F.round(F.avg((size == v).cast("double")), 6) if v is not None else F.lit(None).cast("double")
    return win.agg(F.count("*").alias("n_windows"), F.min(size).alias("min_size"), F.round(F.avg(size), 6).alias("avg_size"), F.max(size).alias("max_size"), share(low).alias("at_low"), share(high).alias("at_high"))
