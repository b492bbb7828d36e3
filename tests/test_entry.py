"""The driver's contract, and every oracle at the smallest scale."""

from __future__ import annotations

import importlib.util

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from evograph.registry import ORACLES, QUERIES
from evograph.schema import TABLES

SLOW: set[str] = set()


def normal(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)]
    return sorted((tuple("~" if pd.isna(v) else repr(round(float(v), 5)) if isinstance(v, (int, float)) or hasattr(v, "dtype") and v.dtype.kind in "iuf" else str(v) for v in r) for r in df.itertuples(index=False)), key=str)


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return c


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0


def test_names():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and set(QUERIES) <= set(q)
    if importlib.util.find_spec("evograph.llm") is None:
        assert "pipeline" not in q


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sf, con, name):
    a, b = QUERIES[name](spark, sf).toPandas(), con.execute(ORACLES[name]).fetchdf()
    assert sorted(a.columns) == sorted(b.columns)
    assert normal(a) == normal(b)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - SLOW))
def test_runs(spark, sf, name):
    QUERIES[name](spark, sf).count()
