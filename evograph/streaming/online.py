"""Structured Streaming: sources, windows, joins, the stateful window former and online training."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from evograph.registry import query
from evograph.schema import table_schema
from evograph.session import ship, work_dir
from evograph.sources.streams import left, right
from evograph.stream.positions import micros
from evograph.train.engine import Events, fit
from evograph.workloads.methods import _adaptive_sql


def stream_events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """``events`` as a stream of files; ``ts`` becomes TIMESTAMP, which watermarks need."""
    ship(spark)
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    reader = spark.readStream.schema(table_schema("events")).option("maxFilesPerTrigger", per_trigger)
    if fs.getFileStatus(path).isDirectory():
        df = reader.parquet(f"{sf_dir}/events.parquet")
    else:
        df = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_table(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there and return the rows it gave; every batch goes to a shared folder."""
    spark = stream.sparkSession
    base = f"{work_dir(spark)}/stream-{uuid.uuid4().hex}"
    out = f"{base}/out"

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={batch_id}")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{base}/checkpoint").foreachBatch(keep).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out if mode == "complete" else f"{out}/batch=*")


WINDOW_STATE = "blob string"
WINDOWS = "key long, window_id long, start_pos long, end_pos long"


class WindowFormer:
    """Adaptive windows of one ordered stream, event by event.

    Holds the open start, each recent event's ``prev``, and last positions of nodes touched
    since the open start: at most ``high`` events and their nodes.
    """

    def __init__(self, low: int, high: int, ratio: float, state: dict | None = None):
        self.low, self.high, self.ratio = low, high, ratio
        s = state or {"start": 0, "next": 0, "wid": 0, "prev": [], "last": {}}
        self.start, self.next, self.wid, self.prev = s["start"], s["next"], s["wid"], s["prev"]
        self.last = {int(k): v for k, v in s["last"].items()}

    def dump(self) -> dict:
        return {"start": self.start, "next": self.next, "wid": self.wid, "prev": self.prev, "last": self.last}

    def add(self, src: int, dst: int | None) -> list[tuple[int, int, int]]:
        """Windows that this event closes: (id, start, end)."""
        pos, nodes = self.next, {src} if dst is None else {src, dst}
        self.prev.append(max((self.last.get(n, -1) for n in nodes), default=-1))
        for n in nodes:
            self.last[n] = pos
        self.next += 1
        out = []
        while (end := self._end()) is not None:
            out.append((self.wid, self.start, end))
            self.wid += 1
            step = max(1, int(self.ratio * (end - self.start) + 1e-9))
            self.prev = self.prev[step:]
            self.start += step
            self.last = {n: p for n, p in self.last.items() if p >= self.start}  # older touches cannot matter
        return out

    def _end(self) -> int | None:
        """End of the open window, if the events so far decide it."""
        for k in range(self.low, min(self.high, len(self.prev))):
            if self.prev[k] < self.start:
                return self.start + k
        return self.start + self.high if len(self.prev) >= self.high + 1 else None


def online_windows(stream: DataFrame, low: int = 100, high: int = 300, ratio: float = 0.2, key: str | None = None, order: str = "event_id") -> DataFrame:
    """Closed adaptive windows of a stream with ``src, dst`` and an order column, by key (one chain per key)."""

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        former = WindowFormer(low, high, ratio, json.loads(state.get[0]) if state.exists else None)
        rows = pd.concat(list(batches)).sort_values(order)
        out = []
        for src, dst in zip(rows["src"], rows["dst"]):
            out += [(int(k[0]), *w) for w in former.add(int(src), None if pd.isna(dst) else int(dst))]
        state.update((json.dumps(former.dump()),))
        yield pd.DataFrame(out, columns=["key", "window_id", "start_pos", "end_pos"])

    keyed = stream.withColumn("key", F.col(key).cast("long") if key else F.lit(0).cast("long")).select("key", "src", "dst", order)
    return keyed.groupBy("key").applyInPandasWithState(step, WINDOWS, WINDOW_STATE, "append", GroupStateTimeout.NoTimeout)


def interaction_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream_events(spark, sf_dir)
    return e.select("event_id", "ts", left(F.col("user_id")).alias("src"), right(F.get_json_object("props", "$.k").cast("long")).alias("dst"))


@query("q_m28_online_windows", _adaptive_sql("s1") + "SELECT 0 AS key, window_id, start_pos, end_pos FROM win WHERE end_pos < (SELECT m FROM m)")
def q_online_windows(s, d):
    return run_to_table(online_windows(interaction_stream(s, d)))


@query("q_o63_watermark_counts", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def q_watermark(s, d):
    e = stream_events(s, d).withWatermark("ts", "10 minutes")
    return run_to_table(e.groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@query("q_o64_stream_tumbling", "SELECT CAST(floor(epoch_us(ts) / 3600000000.0) AS BIGINT) * 3600000000 AS start_us, count(*) AS n FROM events GROUP BY 1")
def q_stream_tumbling(s, d):
    e = stream_events(s, d).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return run_to_table(e, "complete").select(micros(F.col("w.start").cast("timestamp_ntz")).alias("start_us"), "n")


@query("q_o64_stream_sliding", "SELECT (h - o) * 1800000000 AS start_us, count(*) AS n FROM (SELECT CAST(floor(epoch_us(ts) / 1800000000.0) AS BIGINT) AS h, unnest([0, 1]) AS o FROM events) GROUP BY 1")
def q_stream_sliding(s, d):
    e = stream_events(s, d).groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return run_to_table(e, "complete").select(micros(F.col("w.start").cast("timestamp_ntz")).alias("start_us"), "n")


@query("q_o64_stream_session")
def q_stream_session(s, d):
    """Sessions closed by the watermark; the last ones of the stream are still open."""
    e = stream_events(s, d).withWatermark("ts", "1 minute").groupBy(F.session_window("ts", "2 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_table(e, "append").select(micros(F.col("w.start").cast("timestamp_ntz")).alias("start_us"), "user_id", "n")


@query("q_o66_stream_dedup", "SELECT DISTINCT user_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")
def q_stream_dedup(s, d):
    """Repeated deliveries of a pair are dropped; the horizon outlasts the stream, so once per pair."""
    e = stream_events(s, d).select("ts", "user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).withWatermark("ts", "3650 days")
    return run_to_table(e.dropDuplicatesWithinWatermark(["user_id", "k"])).select("user_id", "k")


@query("q_o67_stream_stream_join", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def q_stream_join(s, d):
    e = stream_events(s, d)
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("tc")).withWatermark("tc", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("event_id").alias("purchase"), F.col("ts").alias("tp")).withWatermark("tp", "1 hour")
    j = c.join(p, (F.col("user_id") == F.col("u")) & (F.col("tp") > F.col("tc")) & (F.col("tp") <= F.col("tc") + F.expr("INTERVAL 1 HOUR")))
    return run_to_table(j.select("click", "purchase"))


@query("q_o67_stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def q_stream_static(s, d):
    c = s.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    e = stream_events(s, d).select("event_id", "user_id")
    return run_to_table(e.join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("q_o68_keyed_windows", "SELECT count(*) AS keys FROM (SELECT DISTINCT user_id FROM events)")
def q_keyed_windows(s, d):
    """One window former per user; every user with events has a state, small users close windows of two."""
    e = stream_events(s, d).select("event_id", "user_id", left(F.col("user_id")).alias("src"), right(F.get_json_object("props", "$.k").cast("long")).alias("dst"))
    return run_to_table(online_windows(e, 1, 2, 0.5, key="user_id")).agg(F.countDistinct("key").alias("keys"))


def split_late(stream: DataFrame, delay_seconds: int, on_time: Callable[[DataFrame, int], None], late: Callable[[DataFrame, int], None], checkpoint: str):
    """Start a query that sends events more than ``delay_seconds`` behind the newest seen to ``late``, others to ``on_time``."""
    newest: dict[str, float] = {"us": float("-inf")}

    def each(batch: DataFrame, batch_id: int) -> None:
        us = (F.unix_micros("ts")).alias("us")
        limit = newest["us"] - delay_seconds * 1e6
        on_time(batch.where(us >= F.lit(limit)), batch_id)
        late(batch.where(us < F.lit(limit)), batch_id)
        top = batch.agg(F.max(us)).first()[0]
        newest["us"] = max(newest["us"], top) if top is not None else newest["us"]

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class ProgressLog(StreamingQueryListener):
    """Collects rows, state rows and durations of every micro-batch."""

    def __init__(self) -> None:
        self.rows: list[dict] = []

    def onQueryStarted(self, event) -> None:
        pass

    def onQueryProgress(self, event) -> None:
        p = event.progress
        self.rows.append({"batch": p.batchId, "rows": p.numInputRows, "state": sum(o.numRowsTotal for o in p.stateOperators), "ms": (p.durationMs or {}).get("triggerExecution", 0)})

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass


class OnlineTrainer:
    """Training on a stream in micro-batches: windows are trained as they close, parameters go on.

    Pass ``each_batch`` to ``foreachBatch``. Events of one chain arrive in order of ``order``;
    the events of the open window and the graph are what it keeps.
    """

    def __init__(self, model, z0: np.ndarray, low: int = 100, high: int = 300, ratio: float = 0.2, epochs: int = 5, order: str = "event_id"):
        self.model, self.z0, self.epochs, self.order, self.ratio = model, z0, epochs, order, ratio
        self.former = WindowFormer(low, high, ratio)
        self.params = model.init()
        self.rows: list[tuple] = []
        self.log: list[dict] = []

    def each_batch(self, batch: DataFrame, batch_id: int) -> None:
        for r in batch.select(self.order, "src", "dst", F.unix_micros("ts").alias("us")).orderBy(self.order).toLocalIterator():
            self.rows.append((r["src"], r["dst"], r["us"] / 1e6))
            for wid, a, b in self.former.add(r["src"], r["dst"]):
                self._train(wid, a, b)

    def _train(self, wid: int, a: int, b: int) -> None:
        n = b
        part = self.rows[:n]
        ev = Events(np.arange(n), np.array([x[0] for x in part]), np.array([-1 if x[1] is None else x[1] for x in part]), np.array([x[2] for x in part]), ["edge_add"] * n, np.ones(n))
        got = fit(self.model, ev, [(a, b)], self.z0, epochs=self.epochs, params=self.params)
        self.params = got.params
        best = max((x["auc"] for x in got.log if x["auc"] is not None), default=None)
        self.log.append({"window_id": wid, "start": a, "end": b, "auc": best, "loss": got.log[-1]["loss"] if got.log else None})
