"""Dense positions in chronological order, without a single-task window."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows that one position bucket should hold.
BUCKET_ROWS = 2_000_000
MAX_BUCKETS = 65_536


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of a timestamp without time zone, in any session time zone."""
    seconds = F.unix_date(ts.cast("date")).cast("long") * 86400 + F.hour(ts) * 3600 + F.minute(ts) * 60
    return seconds * 1_000_000 + (F.extract(F.lit("SECOND"), ts) * 1_000_000).cast("long")


def _number(df: DataFrame, name: str) -> Column:
    kind = df.schema[name].dataType.typeName()
    return micros(F.col(name)) if kind.startswith("timestamp") else F.col(name).cast("long")


def assign_positions(df: DataFrame, order: list[str], shape: Callable[[DataFrame], DataFrame] = lambda d: d) -> DataFrame:
    """Add ``pos``: 0, 1, ... by ``order``, which must be a total order; its first column is a number or time.

    The range of the first column is cut into buckets; rows are counted by bucket, the
    counts (a bounded table) become offsets, and rows are numbered inside their bucket only.
    """
    key = _number(df, order[0])
    lo, hi, n = df.agg(F.min(key), F.max(key), F.count("*")).first()
    if not n:
        return shape(df.withColumn("pos", F.lit(None).cast("long")))
    buckets = min(MAX_BUCKETS, max(8, -(-n // BUCKET_ROWS)))
    width = max(1, -(-(hi - lo + 1) // buckets))
    d = df.withColumn("pos_bucket", ((key - F.lit(lo)) / F.lit(width)).cast("int"))
    sizes = d.groupBy("pos_bucket").agg(F.count("*").alias("bucket_rows"))
    before = Window.orderBy("pos_bucket").rowsBetween(Window.unboundedPreceding, -1)  # at most MAX_BUCKETS rows
    offsets = sizes.select("pos_bucket", F.coalesce(F.sum("bucket_rows").over(before), F.lit(0)).alias("pos_base"))
    local = F.row_number().over(Window.partitionBy("pos_bucket").orderBy(*order)) - 1
    out = d.withColumn("pos_local", local).join(F.broadcast(offsets), "pos_bucket")
    return shape(out.withColumn("pos", F.col("pos_base") + F.col("pos_local")).drop("pos_bucket", "pos_base", "pos_local"))


def split_initial(ev: DataFrame, frac: float) -> tuple[DataFrame, DataFrame]:
    """The first share of a stream as the initial graph's events, and the rest."""
    cut = int(frac * ev.count())
    return ev.where(F.col("pos") < cut), ev.where(F.col("pos") >= cut)


def classify(ev: DataFrame, mapping: dict[str, str], column: str = "kind") -> DataFrame:
    """Set ``kind_class`` from a mapping of kinds (or of another column)."""
    m = F.create_map(*[F.lit(x) for kv in mapping.items() for x in kv])
    return ev.withColumn("kind_class", m[F.col(column)])
