"""Joins that Spark plans badly or lacks: band, as-of and salted joins, as DataFrame rewrites."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def band(a: DataFrame, b: DataFrame, a_key: str, b_key: str, low: int, high: int) -> DataFrame:
    """Rows with ``a_key + low <= b_key <= a_key + high``, as an equi-join on buckets instead of a nested loop."""
    width = max(1, high - low + 1)
    left = a.withColumn("band_bucket", F.explode(F.sequence(F.floor((F.col(a_key) + low) / width), F.floor((F.col(a_key) + high) / width))))
    right = b.withColumn("band_bucket", F.floor(F.col(b_key) / width))
    near = (F.col(b_key) >= F.col(a_key) + low) & (F.col(b_key) <= F.col(a_key) + high)
    return left.join(right, "band_bucket").where(near).drop("band_bucket")


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str, direction: str = "backward", inclusive: bool = True) -> DataFrame:
    """``left`` with the ``value`` of the nearest ``right`` row of its key at or before (after) ``on``: one shuffle."""
    turn = 0 if inclusive else 2
    l_ = left.withColumns({"asof_value": F.lit(None).cast(right.schema[value].dataType), "asof_turn": F.lit(1)})
    r = right.select(by, on, F.col(value).alias("asof_value"), F.lit(turn if direction == "backward" else 2 - turn).alias("asof_turn"))
    both = l_.unionByName(r, allowMissingColumns=True)
    order = [F.col(on), F.col("asof_turn")] if direction == "backward" else [F.col(on).desc(), F.col("asof_turn").desc()]
    w = Window.partitionBy(by).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("asof_value", F.last("asof_value", ignorenulls=True).over(w)).where("asof_turn = 1").drop("asof_turn")


def salted(big: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Inner join in which a hot key of ``big`` is dealt over ``salts`` tasks and ``small`` is copied to each."""
    b = big.withColumn("salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    s = small.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return b.join(s, [key, "salt"]).drop("salt")
