"""Sources, sinks, joins and streaming details."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from evograph.joins.joins import asof, band, salted
from evograph.sources import sinks
from evograph.sources.edge_list import EdgeListSource
from evograph.sources.streams import interactions
from evograph.sources.tables import read_any, scan, table
from evograph.streaming import online


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_round_trip(spark, sf, tmp_path, fmt):
    df = table(spark, sf, "events").drop("ts")
    w = df.write.format(fmt)
    (w.option("header", True).option("escape", '"') if fmt == "csv" else w).save(str(tmp_path / "x"))
    got = read_any(spark, fmt, str(tmp_path / "x"))
    assert got.count() == df.count() and set(got.columns) == set(df.columns)


def test_pushdown(spark, sf):
    plan = scan(spark, sf, "events", ["event_id"], F.col("value") > 90)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(value,90" in plan and "props" not in plan.split("ReadSchema")[1]


def test_stream_log(spark, sf, tmp_path):
    ev = interactions(spark, sf)
    sinks.write_stream_log(ev, str(tmp_path / "log"), 256)
    got = sinks.read_stream_log(spark, str(tmp_path / "log"), 300, 700, 256)
    assert got.count() == 400 and got.agg(F.min("pos")).first()[0] == 300
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(pos_bucket" in plan


def test_params(spark, tmp_path):
    p = {"A": np.arange(6.0).reshape(2, 3), "b": np.ones((1, 2))}
    sinks.save_params(spark, p, str(tmp_path / "p"), 1)
    sinks.save_params(spark, {k: v + 1 for k, v in p.items()}, str(tmp_path / "p"), 2)
    assert np.array_equal(sinks.load_params(spark, str(tmp_path / "p"))["A"], p["A"] + 1)
    assert np.array_equal(sinks.load_params(spark, str(tmp_path / "p"), 1)["b"], p["b"])


def test_edge_list(spark, tmp_path):
    (tmp_path / "g.txt").write_text("# head\n1 2 0.5\n3 4\n" + "".join(f"{k} {k + 1} {k}\n" for k in range(50)))
    spark.dataSource.register(EdgeListSource)
    df = spark.read.format("edgelist").option("parts", 4).load(str(tmp_path / "g.txt"))
    assert df.count() == 52 and df.where("time IS NULL").count() == 1


def test_joins(spark):
    a = spark.createDataFrame([(1, 5), (1, 9), (2, 3)], "k long, t long")
    b = spark.createDataFrame([(1, 5, "x"), (1, 7, "y"), (2, 4, "z")], "k long, t long, v string")
    got = {(r["k"], r["t"]): r["asof_value"] for r in asof(a, b, "k", "t", "v").collect()}
    assert got == {(1, 5): "x", (1, 9): "y", (2, 3): None}
    got = {(r["k"], r["t"]): r["asof_value"] for r in asof(a, b, "k", "t", "v", inclusive=False).collect()}
    assert got == {(1, 5): None, (1, 9): "y", (2, 3): None}
    got = {(r["k"], r["t"]): r["asof_value"] for r in asof(a, b, "k", "t", "v", "forward").collect()}
    assert got == {(1, 5): "x", (1, 9): None, (2, 3): "z"}
    x, y = spark.range(30).withColumnRenamed("id", "p"), spark.range(30).withColumnRenamed("id", "q")
    assert band(x, y, "p", "q", -1, 2).count() == sum(1 for p in range(30) for q in range(30) if p - 1 <= q <= p + 2)
    assert "NestedLoop" not in band(x, y, "p", "q", -1, 2)._jdf.queryExecution().executedPlan().toString()
    assert salted(a, b.select("k", "v"), "k", 4).count() == a.join(b.select("k", "v"), "k").count()


def test_restart_gives_same_windows(spark, sf, tmp_path):
    """A query stopped between files and started again goes on where it was."""
    ev = table(spark, sf, "events")
    for k in range(3):
        ev.where(F.floor(F.col("event_id") % 1000 / 334) == k).coalesce(1).write.mode("append").parquet(str(tmp_path / f"in{k}"))
    one = tmp_path / "events.parquet"
    one.mkdir()
    got = []
    for k in range(3):
        for f in sorted((tmp_path / f"in{k}").glob("*.parquet")):
            f.rename(one / f"{k}-{f.name}")
        df = online.run_to_table(online.online_windows(online.interaction_stream(spark, str(tmp_path)), 20, 60), checkpoint=str(tmp_path / "cp"))
        got += [tuple(r) for r in df.collect()]
    whole = online.run_to_table(online.online_windows(online.interaction_stream(spark, sf), 20, 60))
    assert sorted(got) == sorted(tuple(r) for r in whole.collect())


def test_online_trainer(spark, sf):
    from evograph.train.models import MODELS

    t = online.OnlineTrainer(MODELS["point_process_latent"](dim=4), np.random.default_rng(0).normal(size=(50, 4)), 30, 60, 0.5, epochs=1)
    q = online.interaction_stream(spark, sf).where("event_id < 200").writeStream.foreachBatch(t.each_batch).trigger(availableNow=True).start()
    q.awaitTermination()
    assert len(t.log) >= 3 and all(np.isfinite(x["loss"]) for x in t.log)


def test_late_and_progress(spark, sf, tmp_path):
    log, late, good = online.ProgressLog(), [], []
    spark.streams.addListener(log)
    online.split_late(online.stream_events(spark, sf), 3600, lambda b, i: good.append(b.count()), lambda b, i: late.append(b.count()), str(tmp_path / "c")).awaitTermination()
    spark.streams.removeListener(log)
    assert sum(good) + sum(late) == 1000
