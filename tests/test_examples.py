"""Worked examples run on given tables, and no table is broadcast whatever its size."""

from __future__ import annotations

import pytest

from evograph.ops import relational
from evograph.queries import QUERIES


@pytest.mark.parametrize("name,col,least", [("q_w01_batch_vs_window", "windows", 5), ("q_w02_fixed_vs_adaptive", "end_pos", 1000), ("q_w19_pipeline", "makespan", 80)])
def test_follows_the_stream(spark, sf, name, col, least):
    assert max(r[col] for r in QUERIES[name](spark, sf).collect()) >= least


@pytest.mark.parametrize("name,rows", [("q_w03_reads", 200), ("q_w04_nine_events", 1000)])
def test_every_event_is_there(spark, sf, name, rows):
    assert QUERIES[name](spark, sf).count() == rows


def test_conflicts_are_of_the_feed(spark, sf):
    scan = QUERIES["q_w03_conflicts"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in scan


def test_large_table_is_not_broadcast(spark, sf, monkeypatch):
    plan = lambda: QUERIES["q_o18_order_stream_broadcast"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=broadcast" in plan()
    monkeypatch.setattr(relational, "BROADCAST_ROWS", 10)
    assert "strategy=broadcast" not in plan()
