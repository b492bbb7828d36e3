"""The experiments, re-expressed on the given tables, and the worked examples.

Training experiments run whole streams in groups, one epoch per window in the registered
queries (``epochs`` is a parameter; ``bench.py --experiments`` runs more).
"""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.baselines.stores import DenseMatrixStore, OutOfBudget, RowListStore
from evograph.deps import conflicts
from evograph.graph import affected, snapshot, spans
from evograph.graph.local_store import DynamicGraph
from evograph.metrics import measures
from evograph.pipeline.overlap import makespan
from evograph.registry import cte, query
from evograph.schedule import waves
from evograph.sources import streams
from evograph.sources.tables import table
from evograph.train.models import MODELS
from evograph.train.spark_fit import fit_grid
from evograph.versions import store
from evograph.windows import adaptive, fixed
from evograph.workloads.methods import _DEP0, _LIFE, _READS, _SPANS, _adaptive_sql

EVENT = "pos long, src long, dst long, ts timestamp_ntz, kind string, kind_class string, weight double"


def tiny(spark: SparkSession, pairs: list[tuple[int, int]], kinds: list[str] | None = None) -> DataFrame:
    """A stream of inline events, one second apart."""
    rows = [(k, u, v, "edge_add" if kinds is None else kinds[k]) for k, (u, v) in enumerate(pairs)]
    df = spark.createDataFrame(rows, "pos long, src long, dst long, kind string")
    ts = F.lit("2000-01-01 00:00:00").cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("pos").cast("decimal(18,6)"))
    return df.select("pos", "src", "dst", ts.alias("ts"), "kind", F.lit("association").alias("kind_class"), F.lit(1.0).alias("weight"))


# fixed values: the worked examples' events
NINE_MIXED = [(1, 2), (2, 3), (3, 4), (11, 12), (4, 1), (12, 13), (13, 14), (14, 11), (11, 13)]
FIVE_INITIAL, FIVE = [(3, 1), (4, 2), (6, 5), (7, 8), (6, 7), (7, 9)], [(1, 2), (5, 8), (1, 2), (7, 8), (9, 10)]
NINE_CHAINED = [(1, 2), (3, 4), (5, 6), (2, 7), (4, 8), (7, 9), (8, 10), (10, 11), (6, 12)]


_COVER = cte("s1") + """, n AS (SELECT count(*) AS n FROM s1), win AS (SELECT 'batch' AS method, 2 AS epochs, i AS window_id, i * 200 AS a, least(i * 200 + 200, n) AS b FROM (SELECT unnest(generate_series(0, CAST(ceil(n / 200.0) AS BIGINT) - 1)) AS i, n FROM n)
UNION ALL SELECT 'sliding', 1, i, i * 40, least(i * 40 + 200, n) FROM (SELECT unnest(generate_series(0, CAST(ceil((n - 200) / 40.0) AS BIGINT))) AS i, n FROM n))
"""


@query("q_w01_batch_vs_window", _COVER + "SELECT w.method, windows, epochs, windows * epochs AS updates, together FROM (SELECT method, epochs, count(*) AS windows FROM win GROUP BY ALL) w JOIN (SELECT method, count(DISTINCT pos) AS together FROM win JOIN s1 ON pos >= a AND pos + 1 < b GROUP BY method) t ON t.method = w.method")
def w01(s, d):
    """Windows, updates, and neighbouring events that some window has together, by method."""
    ev = streams.interactions(s, d)
    n = ev.count()
    out = None
    for name, win, epochs in (("batch", fixed.batches(s, n, 200), 2), ("sliding", fixed.fixed(s, n, 200, 40), 1)):
        m = fixed.members(ev, win)
        hit = m.join(m.select("window_id", (F.col("pos") - 1).alias("pos")), ["window_id", "pos"]).agg(F.count_distinct("pos").alias("together"))
        x = win.agg(F.lit(name).alias("method"), F.count("*").alias("windows"), F.lit(epochs).alias("epochs"), (F.count("*") * epochs).alias("updates")).crossJoin(hit)
        out = x if out is None else out.unionByName(x)
    return out


@query("q_w02_fixed_vs_adaptive", _adaptive_sql("s1") + "SELECT 'adaptive' AS method, window_id, start_pos, end_pos FROM win UNION ALL SELECT 'fixed', i, i * 40, i * 40 + 200 FROM (SELECT unnest(generate_series(0, CAST(floor(((SELECT m FROM m) - 200) / 40.0) AS BIGINT))) AS i)")
def w02(s, d):
    ev = streams.interactions(s, d)
    a = adaptive.adaptive(ev).withColumn("method", F.lit("adaptive"))
    return a.unionByName(fixed.fixed(s, ev.count(), 200, 40, tail="full").withColumn("method", F.lit("fixed")))


_FIVE_SQL = cte("s6", more=_SPANS.format(s="s6") + _READS.format(s="s6"))


@query("q_w03_conflicts", _FIVE_SQL + "SELECT DISTINCT 'e' || (r.pos + 1) AS later, 'e' || (w.pos + 1) AS earlier FROM reads r JOIN t w ON w.node_id = r.node_id AND w.pos < r.pos AND w.pos // 5 = r.pos // 5")
def w03(s, d):
    """Conflicts inside every five events of the document feed."""
    ev = streams.doc_feed(s, d)
    name = lambda c: F.concat(F.lit("e"), (F.col(c) + 1).cast("string"))
    return conflicts.one_hop(ev, spans.edge_spans(ev), fixed.batches(s, ev.count(), 5), "direct").select(name("later_pos").alias("later"), name("earlier_pos").alias("earlier"))


@query("q_w03_reads", _FIVE_SQL + "SELECT 'e' || (pos + 1) AS event, string_agg(node_id::VARCHAR, ',' ORDER BY node_id) AS nodes FROM reads GROUP BY pos")
def w03_reads(s, d):
    """What every event of the document feed reads."""
    ev = streams.doc_feed(s, d)
    r = affected.affected_nodes(ev, spans.edge_spans(ev), 1, "in")
    return r.groupBy("pos").agg(F.array_join(F.array_sort(F.collect_list("node_id")), ",").alias("nodes")).select(F.concat(F.lit("e"), (F.col("pos") + 1).cast("string")).alias("event"), "nodes")


_NINE_SQL = _DEP0.replace("WITH ", "WITH RECURSIVE ", 1).replace("// 200", "// 9") + ", u AS (SELECT later_pos AS a, earlier_pos AS b FROM dep UNION SELECT earlier_pos, later_pos FROM dep), c(pos, root) AS (SELECT pos, pos FROM s1 UNION SELECT u.b, c.root FROM c JOIN u ON u.a = c.pos AND c.root < u.b), lv(pos, level) AS (SELECT pos, 1 FROM s1 UNION SELECT d.later_pos, lv.level + 1 FROM lv JOIN dep d ON d.earlier_pos = lv.pos) "


@query("q_w04_nine_events", _NINE_SQL + "SELECT c.pos + 1 AS event, c.chain, l.level FROM (SELECT pos, min(root) + 1 AS chain FROM c GROUP BY pos) c JOIN (SELECT pos, max(level) AS level FROM lv GROUP BY pos) l ON l.pos = c.pos")
def w04(s, d):
    """Chains and levels inside every nine events of the interaction stream."""
    ev = streams.interactions(s, d)
    t = affected.affected_nodes(ev, spans.edge_spans(ev), 0)
    win = fixed.batches(s, ev.count(), 9)
    dep = conflicts.reduced(t, t, win)
    return conflicts.chains(dep, ev, win).join(waves.waves(dep, ev, win), ["window_id", "pos"]).select((F.col("pos") + 1).alias("event"), (F.col("chain_id") + 1).alias("chain"), "level")


@query("q_w05_versions", "SELECT * FROM (VALUES (0, 0), (1, 1), (2, 2)) t(node_id, version)")
def w05(s, d):
    nodes = s.createDataFrame([(0,), (1,), (2,)], "node_id long")
    v = store.init(nodes, table(s, d, "embeddings"))
    up = s.createDataFrame([(2, 0, [1.0]), (1, 1, [2.0]), (2, 2, [3.0])], "node_id long, at_pos long, z array<float>")
    return store.latest(store.append(v, up)).select("node_id", "version")


METHODS = ("batch", "sliding", "adaptive")
_CHEAP = {"epochs": 1, "n_neg": 5}


def _grid(s: SparkSession, d: str, settings: list[dict]) -> DataFrame:
    ev = streams.community(s, d, bursts=True).withColumn("data", F.lit("community_bursts"))
    return fit_grid(ev, settings, table(s, d, "embeddings"))


def settings_of(models: list[str], methods: tuple[str, ...] = METHODS, dim: int = 8, **more) -> list[dict]:
    return [{"model": m, "method": k, "dim": dim, "fit": {**_CHEAP, **more}} for m in models for k in methods]


@query("q_w12_auc_by_method")
def w12(s, d):
    """Mean of best AUC of the point-process model by windowing method, over the whole planted stream."""
    log = _grid(s, d, settings_of(["point_process_attention"]))
    return log.groupBy("data", "model", "method", "window_id", "unit").agg(F.max("auc").alias("auc"), F.first("n_windows").alias("n_windows")).groupBy("data", "model", "method").agg(F.avg("auc").alias("auc"), F.first("n_windows").alias("n_windows"))


#: Streams of the model grids: whole at every scale.
GRID_STREAMS = {"s4": streams.dialogue, "s5": streams.site_links, "s6": streams.doc_feed}
GRID_MODELS = tuple(MODELS)
#: The sequential reference is the batch method, one event after the other.
GRID_METHODS = {"batch_ref": ("batch", "serial"), "batch": ("batch", "wave"), "sliding": ("sliding", "wave"), "adaptive": ("adaptive", "wave")}


def _streams(s: SparkSession, d: str, names: tuple[str, ...] = tuple(GRID_STREAMS)) -> DataFrame:
    parts = [GRID_STREAMS[n](s, d).withColumn("data", F.lit(n)) for n in names]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _trained(s: SparkSession, d: str, settings: list[dict], names: tuple[str, ...] = tuple(GRID_STREAMS)) -> DataFrame:
    """``data, model, setting, auc, seconds, n_windows``: mean of best AUC and seconds of training each setting on each stream."""
    log = fit_grid(_streams(s, d, names), settings, table(s, d, "embeddings"))
    best = log.groupBy("data", "model", "setting", "window_id", "unit").agg(F.max("auc").alias("auc"), F.first("seconds").alias("seconds"), F.first("n_windows").alias("n_windows"))
    return best.groupBy("data", "model", "setting").agg(F.avg("auc").alias("auc"), F.first("seconds").alias("seconds"), F.first("n_windows").alias("n_windows"))


def model_grid(s: SparkSession, d: str, epochs: int = 1, dim: int = 8) -> DataFrame:
    """Three models by four methods on three whole streams."""
    settings = [{"model": m, "method": how, "dim": dim, "name": name, "fit": {"epochs": epochs, "units": 1, "plan": plan}} for m in GRID_MODELS for name, (how, plan) in GRID_METHODS.items()]
    return _trained(s, d, settings).withColumnRenamed("setting", "method")


@query("q_w10_runtime_grid")
def w10(s, d):
    """Seconds by model, stream and method, and the speed-up over the sequential reference."""
    times = model_grid(s, d).persist()
    return times.select("data", "model", "method", "seconds").join(measures.speedup(times, "batch_ref"), ["data", "model", "method"])


@query("q_w12_auc_grid")
def w12_grid(s, d):
    """Mean of best AUC by model, stream and method, and the adaptive method's gain over batches in points."""
    got = model_grid(s, d).persist()
    return got.select("data", "model", "method", "auc", "n_windows").join(measures.gain(got), ["data", "model"])


@query("q_w13_ablation")
def w13(s, d):
    """The adaptive method event by event, with waves, and with the next window prepared meanwhile."""
    steps = {"base": {"plan": "serial"}, "+parallel": {"plan": "wave"}, "+pipeline": {"plan": "wave", "prefetch": True}}
    settings = [{"model": "point_process_attention", "method": "adaptive", "dim": 8, "name": k, "fit": {"epochs": 2, **x}} for k, x in steps.items()]
    times = _trained(s, d, settings).withColumnRenamed("setting", "method").persist()
    return times.select("data", "model", "method", "seconds").join(measures.speedup(times, "base"), ["data", "model", "method"])


@query("q_w07_execution_plans")
def w07(s, d):
    """Seconds and AUC of two models by execution plan; ``ignore`` drops all dependencies."""
    plans = ("serial", "wave", "chain", "queue", "ignore")
    settings = [{"model": m, "method": "batch", "dim": 8, "name": p, "windows": {"size": 200}, "fit": {"epochs": 1, "units": 1, "plan": p}} for m in ("point_process_attention", "recurrent_diffusion") for p in plans]
    times = _trained(s, d, settings).withColumnRenamed("setting", "method").persist()
    return times.select("data", "model", "method", "auc", "seconds").join(measures.speedup(times, "wave"), ["data", "model", "method"]).withColumnRenamed("method", "plan")


def _sweep(s: SparkSession, d: str, method: str, windows: dict[str, dict]) -> DataFrame:
    """The recurrent model on one stream, by window settings."""
    settings = [{"model": "recurrent_diffusion", "method": method, "dim": 8, "name": k, "windows": w, "fit": {"epochs": 1, **({"stride": w["stride"]} if "stride" in w else {})}} for k, w in windows.items()]
    return _trained(s, d, settings, ("s6",))


@query("q_w14_auc_by_stride_adaptive")
def w14_auc(s, d):
    return _sweep(s, d, "adaptive", {str(r): {"ratio": r} for r in (0.2, 0.5, 0.8)})


@query("q_w15_auc_by_stride_sliding")
def w15_auc(s, d):
    return _sweep(s, d, "sliding", {str(r): {"size": 200, "stride": int(200 * r)} for r in (0.2, 0.5, 0.8)})


@query("q_w16_auc_by_size")
def w16_auc(s, d):
    return _sweep(s, d, "sliding", {str(w): {"size": w, "stride": w // 5} for w in (100, 150, 200, 250, 300)})


@query("q_w17_auc_by_limits")
def w17_auc(s, d):
    return _sweep(s, d, "adaptive", {f"{low}-{high}": {"low": low, "high": high} for low, high in LIMITS})


LIMITS = ((50, 300), (100, 300), (150, 300), (100, 250), (100, 350))


def _stats_sql(low: int, high: int, more: str, ratio: float = 0.2) -> str:
    return _adaptive_sql("s1", low, high, ratio) + f"SELECT count(*) AS n_windows, min(end_pos - start_pos) AS min_size, round(avg(end_pos - start_pos), 6) AS avg_size, max(end_pos - start_pos) AS max_size, round(avg(CASE WHEN end_pos - start_pos = {low} THEN 1.0 ELSE 0.0 END), 6) AS at_low, round(avg(CASE WHEN end_pos - start_pos = {high} THEN 1.0 ELSE 0.0 END), 6) AS at_high, {more} FROM win"


@query("q_w14_stride_adaptive", " UNION ALL ".join(f"SELECT * FROM ({_stats_sql(100, 300, f'CAST({r} AS DOUBLE) AS ratio', r)})" for r in (0.2, 0.5, 0.8)))
def w14(s, d):
    """Windows by stride ratio of the adaptive method: the cost driver of the stride experiment."""
    ev = streams.interactions(s, d)
    out = None
    for r in (0.2, 0.5, 0.8):
        x = fixed.stats(adaptive.adaptive(ev, ratio=r), 100, 300).withColumn("ratio", F.lit(r))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_w15_stride_fixed", cte("s1") + "SELECT r AS ratio, CAST(ceil((n - 200) / (200 * r)) AS BIGINT) + 1 AS n_windows FROM (SELECT count(*) AS n FROM s1), (SELECT unnest([0.2, 0.5, 0.8]) AS r)")
def w15(s, d):
    n = streams.interactions(s, d).count()
    out = None
    for r in (0.2, 0.5, 0.8):
        x = fixed.fixed(s, n, 200, stride_ratio=r).agg(F.lit(r).alias("ratio"), F.count("*").alias("n_windows"))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_w16_window_size", cte("s1") + "SELECT w AS size, CAST(ceil((n - w) / (0.2 * w)) AS BIGINT) + 1 AS n_windows FROM (SELECT count(*) AS n FROM s1), (SELECT unnest([100, 150, 200, 250, 300]) AS w)")
def w16(s, d):
    n = streams.interactions(s, d).count()
    out = None
    for w in (100, 150, 200, 250, 300):
        x = fixed.fixed(s, n, w, stride_ratio=0.2).agg(F.lit(w).alias("size"), F.count("*").alias("n_windows"))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_w17_limits", " UNION ALL ".join(f"SELECT * FROM ({_stats_sql(low, high, f'{low} AS low, {high} AS high')})" for low, high in LIMITS))
def w17(s, d):
    ev = streams.interactions(s, d)
    out = None
    for low, high in LIMITS:
        x = fixed.stats(adaptive.adaptive(ev, low, high), low, high).withColumns({"low": F.lit(low), "high": F.lit(high)})
        out = x if out is None else out.unionByName(x)
    return out


def _dense(n_nodes: int, budget: int) -> str:
    try:
        DenseMatrixStore(n_nodes, 64, budget)
        return "fits"
    except OutOfBudget:
        return "out of memory"


@query("q_w11_dense_survival", cte("s1", "s2") + "SELECT 's1' AS stream, CASE WHEN 2 * (n * n * 8 + n * 512) > 64000000 THEN 'out of memory' ELSE 'fits' END AS dense FROM (SELECT count(*) AS n FROM (SELECT src FROM s1 UNION SELECT dst FROM s1)) UNION ALL SELECT 's2', CASE WHEN 2 * (n * n * 8 + n * 512) > 64000000 THEN 'out of memory' ELSE 'fits' END FROM (SELECT count(*) AS n FROM (SELECT src FROM s2 UNION SELECT dst FROM s2))")
def w11(s, d):
    rows = [(n, _dense(measures.stream_stats(streams.STREAMS[n](s, d), 0.1).first()["nodes"], 64_000_000)) for n in ("s1", "s2")]
    return s.createDataFrame(rows, "stream string, dense string")


STORES = {"indexed": lambda n: DynamicGraph(), "row_list": RowListStore, "dense": lambda n: DenseMatrixStore(n, 16)}


def _timed(kind: str, n: int, src: np.ndarray, dst: np.ndarray, a: int, b: int) -> float:
    """Seconds of the events from ``a`` to ``b`` on a store that holds all earlier ones."""
    st = STORES[kind](n)
    st.load(src[:a], dst[:a])
    pairs = list(zip(src[a:b].tolist(), dst[a:b].tolist()))
    began = time.perf_counter()
    for u, v in pairs:
        st.add_edge(u, v)
        st.neighbours(v)
    return time.perf_counter() - began


@query("q_w18_storage_query_time")
def w18(s, d):
    """Seconds of adding an event's edge and reading its neighbours, by store, over a whole stream (ids made dense)."""
    ev = streams.interactions(s, d).orderBy("pos").select("src", "dst").toPandas()
    ids, at = np.unique(np.concatenate((ev["src"], ev["dst"])), return_inverse=True)
    shared = s.sparkContext.broadcast((len(ids), at[: len(ev)], at[len(ev) :]))
    cuts = [len(ev) * k // STRETCHES for k in range(STRETCHES + 1)]
    todo = [(kind, a, b) for kind in STORES for a, b in zip(cuts, cuts[1:])]  # a store's stretches add up to the whole stream

    def run(parts):
        for pdf in parts:
            got = [_timed(k, *shared.value, a, b) for k, a, b in pdf.itertuples(index=False)]
            yield pd.DataFrame({"store": pdf["store"], "events": pdf["b"] - pdf["a"], "seconds": got})

    each = s.createDataFrame(s.sparkContext.parallelize(todo, len(todo)), "store string, a long, b long").mapInPandas(run, "store string, events long, seconds double")
    return each.groupBy("store").agg(F.sum("events").alias("events"), F.sum("seconds").alias("seconds"))


#: Tasks of each store; what precedes a stretch is loaded and not timed.
STRETCHES = 24


@query("q_w19_pipeline", cte("s1") + "SELECT overlap, 20.0 + ((SELECT count(DISTINCT pos // 200) FROM s1) - 1) * (20.0 - saved) AS makespan FROM (VALUES ('none', 0.0), ('WD', 1.0), ('WD+DA', 4.0), ('WD+DA+ES', 5.0)) t(overlap, saved)")
def w19(s, d):
    """Ablation of overlapped stages on the stream's batches, each of equal stage times (1, 3, 1 and 15 units)."""
    ev = streams.interactions(s, d)
    n = fixed.members(ev, fixed.batches(s, ev.count(), 200)).select("window_id").distinct().count()
    t = [{"WD": 1.0, "DA": 3.0, "ES": 1.0, "PT": 15.0}] * n
    sets = {"none": set(), "WD": {"WD"}, "WD+DA": {"WD", "DA"}, "WD+DA+ES": {"WD", "DA", "ES"}}
    return s.createDataFrame([(k, float(makespan(t, v))) for k, v in sets.items()], "overlap string, makespan double")


@query("q_w21_event_classes", cte("s1m") + "SELECT kind_class, kind, count(*) AS n, round(count(*) / (SELECT count(*) FROM s1m), 6) AS share FROM s1m GROUP BY kind_class, kind")
def w21(s, d):
    ev = streams.interactions(s, d, mixed=True)
    n = ev.count()
    return ev.groupBy("kind_class", "kind").agg(F.count("*").alias("n")).withColumn("share", F.round(F.col("n") / n, 6))


_HIDDEN = "SELECT '{name}' AS every, CAST(sum(e.n) AS BIGINT) AS events, CAST(sum(e.n - coalesce(x.n, 0)) AS BIGINT) AS hidden FROM (SELECT CAST(floor(epoch_us(ts) / {us}.0) AS BIGINT) AS snap_id, count(*) AS n FROM s1m WHERE kind IN ('edge_add', 'edge_del') GROUP BY 1) e LEFT JOIN (SELECT snap_id, count(*) AS n FROM delta GROUP BY 1) x ON x.snap_id = e.snap_id"


def _hidden_sql(name: str, seconds: int) -> str:
    return cte("s1m", more=_LIFE.format(s="s1m").replace("86400000000", f"{seconds * 1_000_000}")) + _HIDDEN.format(name=name, us=seconds * 1_000_000)


@query("q_w22_snapshot_loss", f"SELECT * FROM ({_hidden_sql('day', 86_400)}) UNION ALL SELECT * FROM ({_hidden_sql('week', 7 * 86_400)})")
def w22(s, d):
    ev = streams.interactions(s, d, mixed=True)
    sp = spans.edge_spans(ev)
    out = None
    for name, sec in (("day", 86_400), ("week", 7 * 86_400)):
        x = snapshot.hidden_events(ev, sp, sec).agg(F.lit(name).alias("every"), F.sum("n_events").alias("events"), F.sum("hidden").alias("hidden"))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_w08_stage_times")
def w08(s, d):
    """Seconds of window determination, dependency analysis and scheduling, and the analysis' share."""
    ev = streams.interactions(s, d).persist()
    sp = spans.edge_spans(ev).persist()
    held = [ev, sp]
    ev.count(), sp.count()
    rows, sec, win, dep = [], [], None, None
    for stage in ("WD", "DA", "ES"):  # each stage reads what the one before it made, and makes all of its own
        began = time.perf_counter()
        if stage == "WD":
            made = win = adaptive.adaptive(ev).persist()
        elif stage == "DA":
            made = dep = conflicts.reduced_one_hop(ev, sp, win).persist()
        else:
            made = waves.waves(dep, ev, win).persist()
        rows.append(made.count())
        sec.append(time.perf_counter() - began)
        held.append(made)
    n_windows, n_deps = rows[0], rows[1]
    for x in held:
        x.unpersist()
    times = s.createDataFrame([("s1", k, x) for k, x in zip(("WD", "DA", "ES"), sec)], "data string, stage string, seconds double")
    share = measures.stage_share(times, "DA").withColumnRenamed("share", "analysis_share")
    return times.join(share, "data").withColumns({"n_windows": F.lit(n_windows), "n_deps": F.lit(n_deps)})
