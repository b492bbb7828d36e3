"""Sinks: the event log clustered by position, parameters and versions as Parquet rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_stream_log(ev: DataFrame, path: str, width: int = 1 << 20) -> None:
    """Partitioned by position bucket and sorted by position inside, so position filters prune files."""
    e = ev.withColumn("pos_bucket", F.floor(F.col("pos") / width))
    e.repartition("pos_bucket").sortWithinPartitions("pos").write.mode("overwrite").partitionBy("pos_bucket").parquet(path)


def read_stream_log(spark: SparkSession, path: str, start: int, end: int, width: int = 1 << 20) -> DataFrame:
    """Events of ``[start, end)``; only their buckets are read."""
    df = spark.read.parquet(path)
    return df.where(F.col("pos_bucket").between(start // width, max(start, end - 1) // width) & (F.col("pos") >= start) & (F.col("pos") < end)).drop("pos_bucket")


def save_params(spark: SparkSession, params: dict[str, np.ndarray], path: str, step: int) -> None:
    """Append parameters of a step as rows ``name, shape, data, step``."""
    rows = [(k, [int(x) for x in v.shape], [float(x) for x in v.reshape(-1)], step) for k, v in sorted(params.items())]
    spark.createDataFrame(rows, "name string, shape array<int>, data array<double>, step long").coalesce(1).write.mode("append").parquet(path)


def load_params(spark: SparkSession, path: str, step: int | None = None) -> dict[str, np.ndarray]:
    """Parameters of a step, by default the newest whole one."""
    df = spark.read.parquet(path)
    at = step if step is not None else df.agg(F.max("step")).first()[0]
    return {r["name"]: np.array(r["data"]).reshape(r["shape"]) for r in df.where(F.col("step") == at).collect()}
