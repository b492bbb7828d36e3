"""Reading tables: explicit schemas, pruned and filtered scans, other formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession

from evograph.schema import table_schema
from evograph.session import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table with its declared columns; nothing is inferred from values."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scan(spark: SparkSession, sf_dir: str, name: str, columns: list[str], predicate: Column | None = None) -> DataFrame:
    """A scan that reads some columns and lets the reader skip by the predicate."""
    df = table(spark, sf_dir, name)
    return (df if predicate is None else df.where(predicate)).select(*columns)


def read_any(spark: SparkSession, fmt: str, path: str, name: str | None = None) -> DataFrame:
    """csv, json, orc, parquet or text; with the schema of a given table if it is named."""
    reader = spark.read.format(fmt)
    if fmt == "csv":
        reader = reader.option("header", True).option("quote", '"').option("escape", '"')
    if name and fmt != "text":
        reader = reader.schema(table_schema(name))
    return reader.load(path)
