"""Queries of the stream, window, dependency, version and measure methods, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.deps import conflicts
from evograph.graph import adjacency as adj
from evograph.graph import affected, snapshot, spans, stretches
from evograph.metrics import measures
from evograph.registry import cte, query
from evograph.schedule import waves
from evograph.sources import streams
from evograph.sources.tables import table
from evograph.stream import positions
from evograph.versions import store
from evograph.windows import adaptive, fixed

DAY = 86_400
_EV = "pos, src, dst, epoch_us(ts) AS ts_us, kind, kind_class, weight"


def _show(ev: DataFrame) -> DataFrame:
    return ev.select("pos", "src", "dst", positions.micros(F.col("ts")).alias("ts_us"), "kind", "kind_class", "weight")


def s1(spark: SparkSession, d: str) -> DataFrame:
    return streams.interactions(spark, d)


def s1m(spark: SparkSession, d: str) -> DataFrame:
    return streams.interactions(spark, d, mixed=True)


for _name, _make in {"s1": s1, "s1m": s1m, "s2": streams.purchases, "s3": streams.supply, "s4": streams.dialogue, "s6": streams.doc_feed}.items():
    query(f"q_m01_stream_{_name}", cte(_name) + f"SELECT {_EV} FROM {_name}")(lambda s, d, f=_make: _show(f(s, d)))
query("q_m01_stream_s5", cte("links", "s5") + f"SELECT {_EV} FROM s5")(lambda s, d: _show(streams.site_links(s, d)))


@query("q_m02_positions", cte("s2") + "SELECT pos, src, dst FROM s2")
def q_positions(s, d):
    return streams.purchases(s, d).select("pos", "src", "dst")


@query("q_m03_split", cte("s1") + "SELECT CASE WHEN pos < floor(0.1 * (SELECT count(*) FROM s1)) THEN 'initial' ELSE 'stream' END AS part, count(*) AS n, min(pos) AS first_pos FROM s1 GROUP BY 1")
def q_split(s, d):
    a, b = positions.split_initial(s1(s, d), 0.1)
    return a.withColumn("part", F.lit("initial")).unionByName(b.withColumn("part", F.lit("stream"))).groupBy("part").agg(F.count("*").alias("n"), F.min("pos").alias("first_pos"))


@query("q_m04_classify", cte("s1m") + "SELECT kind, CASE kind WHEN 'edge_add' THEN 'association' ELSE 'communication' END AS kind_class, count(*) AS n FROM s1m GROUP BY 1, 2")
def q_classify(s, d):
    m = {"edge_add": "association", "edge_del": "communication", "node_add": "communication"}
    return positions.classify(s1m(s, d), m).groupBy("kind", "kind_class").agg(F.count("*").alias("n"))


_SPANS = """e AS (SELECT pos, src, dst, ts, kind, weight FROM {s} WHERE dst IS NOT NULL AND kind IN ('edge_add', 'edge_del')),
l AS (SELECT *, sum(CASE WHEN kind = 'edge_del' THEN 1 ELSE 0 END) OVER (PARTITION BY src, dst ORDER BY pos) AS life,
  min(CASE WHEN kind = 'edge_del' THEN pos END) OVER (PARTITION BY src, dst ORDER BY pos ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS nd FROM e),
spans AS (SELECT src, dst, min(pos) AS from_pos, coalesce(min(nd), 4611686018427387904) AS to_pos, arg_max(weight, pos) AS weight, count(*) AS n_adds FROM l WHERE kind = 'edge_add' GROUP BY src, dst, life)"""


@query("q_m05_edge_spans", cte("s1m", more=_SPANS.format(s="s1m")) + "SELECT src, dst, from_pos, to_pos, weight, n_adds FROM spans")
def q_spans(s, d):
    return spans.edge_spans(s1m(s, d)).select("src", "dst", "from_pos", "to_pos", "weight", "n_adds")


@query("q_m05_edge_spans_multi", cte("s1m", more=_SPANS.format(s="s1m")) + "SELECT src, dst, pos AS from_pos, coalesce(nd, 4611686018427387904) AS to_pos, weight FROM l WHERE kind = 'edge_add'")
def q_spans_multi(s, d):
    return spans.edge_spans(s1m(s, d), "multi").select("src", "dst", "from_pos", "to_pos", "weight")


@query("q_m06_graph_at", cte("s1m", more=_SPANS.format(s="s1m")) + "SELECT src, dst, weight FROM spans WHERE from_pos <= 499 AND to_pos > 499")
def q_graph_at(s, d):
    return spans.graph_at(spans.edge_spans(s1m(s, d)), 499)


@query("q_m07_node_spans", cte("s1m") + "SELECT node_id, min(pos) AS from_pos, 4611686018427387904 AS to_pos FROM (SELECT pos, src AS node_id FROM s1m UNION ALL SELECT pos, dst FROM s1m WHERE dst IS NOT NULL) GROUP BY node_id")
def q_node_spans(s, d):
    return spans.node_spans(s1m(s, d)).select("node_id", "from_pos", "to_pos")


@query("q_m08_features_at", cte("s1m") + "SELECT src, dst, arg_max(weight, pos) AS weight, max(pos) AS at_pos FROM s1m WHERE pos <= 600 AND kind = 'edge_add' GROUP BY src, dst")
def q_features(s, d):
    return spans.features_at(s1m(s, d), 600)


_LIFE = _SPANS + """,
at_ AS (SELECT pos, CAST(floor(epoch_us(ts) / 86400000000.0) AS BIGINT) AS snap FROM {s}),
life AS (SELECT src, dst, a.snap AS from_snap, coalesce(b.snap, 4611686018427387904) AS to_snap FROM spans JOIN at_ a ON a.pos = from_pos LEFT JOIN at_ b ON b.pos = to_pos),
net AS (SELECT from_snap AS snap_id, src, dst, 1 AS change FROM life WHERE from_snap < to_snap UNION ALL SELECT to_snap, src, dst, -1 FROM life WHERE from_snap < to_snap AND to_snap < 4611686018427387904),
delta AS (SELECT snap_id, src, dst, sum(change) AS change FROM net GROUP BY ALL HAVING sum(change) <> 0)"""


@query("q_m09_snapshots", cte("s1m", more=_LIFE.format(s="s1m")) + "SELECT b.snap_id, CAST(sum(coalesce(n.d, 0)) OVER (ORDER BY b.snap_id) AS BIGINT) AS n_edges FROM (SELECT DISTINCT snap AS snap_id FROM at_) b LEFT JOIN (SELECT snap_id, sum(change) AS d FROM net GROUP BY 1) n ON n.snap_id = b.snap_id")
def q_snapshots(s, d):
    ev = s1m(s, d)
    return snapshot.snapshots(ev, spans.edge_spans(ev), DAY)


@query("q_m10_deltas", cte("s1m", more=_LIFE.format(s="s1m")) + "SELECT snap_id, src, dst, CAST(change AS BIGINT) AS change FROM delta")
def q_deltas(s, d):
    ev = s1m(s, d)
    return snapshot.deltas(ev, spans.edge_spans(ev), DAY)


@query("q_m11_hidden_events", cte("s1m", more=_LIFE.format(s="s1m")) + "SELECT e.snap_id, e.n AS n_events, coalesce(x.n, 0) AS n_net, e.n - coalesce(x.n, 0) AS hidden FROM (SELECT CAST(floor(epoch_us(ts) / 86400000000.0) AS BIGINT) AS snap_id, count(*) AS n FROM s1m WHERE kind IN ('edge_add', 'edge_del') GROUP BY 1) e LEFT JOIN (SELECT snap_id, count(*) AS n FROM delta GROUP BY 1) x ON x.snap_id = e.snap_id")
def q_hidden(s, d):
    ev = s1m(s, d)
    return snapshot.hidden_events(ev, spans.edge_spans(ev), DAY)


@query("q_m12_adjacency", cte("s1m", more=_SPANS.format(s="s1m")) + "SELECT dst AS node_id, string_agg(src::VARCHAR || ':' || from_pos::VARCHAR, ',' ORDER BY from_pos) AS nbrs FROM spans WHERE from_pos <= 800 AND to_pos > 800 GROUP BY dst")
def q_adjacency(s, d):
    a = adj.adjacency(spans.edge_spans(s1m(s, d)), 800, "in")
    return a.select("node_id", F.array_join(F.transform("nbrs", lambda x: F.concat_ws(":", x["nbr"].cast("string"), x["from_pos"].cast("string"))), ",").alias("nbrs"))


@query("q_m13_edge_index", cte("s1m", more=_SPANS.format(s="s1m")) + """, o AS (SELECT src, dst, weight, row_number() OVER (PARTITION BY src ORDER BY from_pos) - 1 AS off FROM spans WHERE from_pos <= 800 AND to_pos > 800)
SELECT p.u, p.v, o.off AS "offset", o.weight FROM (SELECT DISTINCT src AS u, dst AS v FROM s1m WHERE dst IS NOT NULL AND src IN (SELECT src FROM o)) p LEFT JOIN o ON o.src = p.u AND o.dst = p.v""")
def q_edge_index(s, d):
    ev = s1m(s, d)
    idx = adj.edge_index(adj.adjacency(spans.edge_spans(ev), 800, "out"))
    pairs = ev.where("dst IS NOT NULL").select(F.col("src").alias("u"), F.col("dst").alias("v")).distinct().join(idx.select(F.col("node_id").alias("u")), "u", "left_semi")
    return adj.edge_lookup(idx, pairs)


_TOUCH = """, t AS (SELECT pos, src AS node_id FROM {s} UNION SELECT pos, dst FROM {s} WHERE dst IS NOT NULL)"""
_READS = _TOUCH + """, reads AS (SELECT pos, node_id FROM t UNION SELECT t.pos, p.src FROM t JOIN spans p ON p.dst = t.node_id LEFT JOIN (SELECT pos FROM {s} WHERE kind = 'edge_del') x ON x.pos = t.pos WHERE p.from_pos <= t.pos AND p.to_pos + CASE WHEN x.pos IS NULL THEN 0 ELSE 1 END > t.pos)"""


@query("q_m15_affected_nodes", cte("s1m", more=_SPANS.format(s="s1m") + _READS.format(s="s1m")) + "SELECT pos, node_id FROM reads")
def q_reads(s, d):
    ev = s1m(s, d)
    return stretches.nodes(ev, spans.edge_spans(ev), 1, "in")


@query("q_m15_affected_nodes_k0", cte("s1m") + _TOUCH.format(s="s1m") + " SELECT pos, node_id FROM t")
def q_reads0(s, d):
    ev = s1m(s, d)
    return affected.affected_nodes(ev, spans.edge_spans(ev), 0)


@query("q_m15_affected_nodes_k2", cte("s1m", more=_SPANS.format(s="s1m") + _READS.format(s="s1m") + """, r2 AS (SELECT pos, node_id FROM reads UNION SELECT r.pos, p.src FROM reads r JOIN spans p ON p.dst = r.node_id LEFT JOIN (SELECT pos FROM s1m WHERE kind = 'edge_del') x ON x.pos = r.pos WHERE p.from_pos <= r.pos AND p.to_pos + CASE WHEN x.pos IS NULL THEN 0 ELSE 1 END > r.pos)""") + "SELECT pos, count(*) AS n, sum(node_id) AS s FROM r2 GROUP BY pos")
def q_reads2(s, d):
    ev = s1m(s, d)
    return stretches.totals(ev, spans.edge_spans(ev), 2, "in")


@query("q_m16_affected_edges", cte("s1m", more=_SPANS.format(s="s1m") + _READS.format(s="s1m")) + "SELECT DISTINCT a.pos, p.src, p.dst FROM reads a JOIN spans p ON p.src = a.node_id AND p.from_pos <= a.pos AND p.to_pos > a.pos JOIN reads b ON b.pos = a.pos AND b.node_id = p.dst")
def q_edges(s, d):
    ev = s1m(s, d)
    return stretches.edges(ev, spans.edge_spans(ev), 1, "in")


@query("q_m17_subgraph", cte("s1m", more=_SPANS.format(s="s1m") + _READS.format(s="s1m")) + """, ed AS (SELECT DISTINCT a.pos, p.src, p.dst FROM reads a JOIN spans p ON p.src = a.node_id AND p.from_pos <= a.pos AND p.to_pos > a.pos JOIN reads b ON b.pos = a.pos AND b.node_id = p.dst)
SELECT v.pos, v.nodes, e.edges FROM (SELECT pos, string_agg(node_id::VARCHAR, ',' ORDER BY node_id) AS nodes FROM reads GROUP BY pos) v LEFT JOIN (SELECT pos, string_agg(src::VARCHAR || '>' || dst::VARCHAR, ',' ORDER BY src, dst) AS edges FROM ed GROUP BY pos) e ON e.pos = v.pos""")
def q_subgraph(s, d):
    ev = s1m(s, d)
    text = lambda c, f: F.array_join(F.transform(c, f), ",")
    return stretches.subgraphs(ev, spans.edge_spans(ev), 1, "in").select("pos", text("nodes", lambda x: x.cast("string")).alias("nodes"), text("edges", lambda x: F.concat(x["src"].cast("string"), F.lit(">"), x["dst"].cast("string"))).alias("edges"))


@query("q_m18_last_time", cte("s1m") + _TOUCH.format(s="s1m") + " SELECT node_id, epoch_us(max(ts)) AS last_us, count(*) AS n FROM t JOIN s1m USING (pos) GROUP BY node_id")
def q_last_time(s, d):
    return spans.last_time(s1m(s, d)).select("node_id", positions.micros(F.col("last_ts")).alias("last_us"), "n")


@query("q_m19_elapsed", cte("s1m") + _TOUCH.format(s="s1m") + """, g AS (SELECT t.pos, node_id, (epoch_us(ts) - coalesce(lag(epoch_us(ts)) OVER (PARTITION BY node_id ORDER BY t.pos), epoch_us(ts))) / 1000000.0 AS dt FROM t JOIN s1m ON s1m.pos = t.pos)
SELECT e.pos, round(a.dt, 3) AS dt_u, round(b.dt, 3) AS dt_v FROM s1m e JOIN g a ON a.pos = e.pos AND a.node_id = e.src LEFT JOIN g b ON b.pos = e.pos AND b.node_id = e.dst""")
def q_elapsed(s, d):
    return spans.elapsed(s1m(s, d)).select("pos", F.round("dt_u", 3).alias("dt_u"), F.round("dt_v", 3).alias("dt_v"))


@query("q_m20_writes", cte("s1m") + _TOUCH.format(s="s1m") + " SELECT pos, node_id FROM t")
def q_writes(s, d):
    return affected.writes(s1m(s, d))


def _range_sql(size: int, stride: int, stop: str, more: str = "") -> str:
    return cte("s1") + f"SELECT i AS window_id, i * {stride} AS start_pos, least(i * {stride} + {size}{more}, n) AS end_pos FROM (SELECT unnest(generate_series(0, {stop} - 1)) AS i, n FROM (SELECT count(*) AS n FROM s1))"


@query("q_m21_batches", _range_sql(200, 200, "CAST(ceil(n / 200.0) AS BIGINT)"))
def q_batches(s, d):
    return fixed.batches(s, s1(s, d).count(), 200)


@query("q_m22_fixed_full", _range_sql(200, 40, "CAST(floor((n - 200) / 40.0) AS BIGINT) + 1"))
def q_fixed_full(s, d):
    return fixed.fixed(s, s1(s, d).count(), 200, 40, tail="full")


@query("q_m22_fixed_stop", _range_sql(200, 40, "CAST(ceil((n - 200) / 40.0) AS BIGINT) + 1"))
def q_fixed_stop(s, d):
    return fixed.fixed(s, s1(s, d).count(), 200, 40)


@query("q_m22_fixed_shrink", _range_sql(200, 40, "CAST(ceil(n / 40.0) AS BIGINT)"))
def q_fixed_shrink(s, d):
    return fixed.fixed(s, s1(s, d).count(), 200, 40, tail="shrink")


@query("q_m22_fixed_listing", _range_sql(200, 40, "CAST(ceil((n - 200) / 40.0) AS BIGINT) + 1", " + 1"))
def q_fixed_listing(s, d):
    return fixed.fixed(s, s1(s, d).count(), 200, 40, bounds="listing")


@query("q_m23_stride_ratio", "\nUNION ALL ".join(["SELECT 0.2 AS ratio, count(*) AS n FROM (" + _range_sql(200, 40, "CAST(ceil((n - 200) / 40.0) AS BIGINT) + 1") + ")", "SELECT 0.5, count(*) FROM (" + _range_sql(200, 100, "CAST(ceil((n - 200) / 100.0) AS BIGINT) + 1") + ")", "SELECT 0.8, count(*) FROM (" + _range_sql(200, 160, "CAST(ceil((n - 200) / 160.0) AS BIGINT) + 1") + ")"]))
def q_ratio(s, d):
    n = s1(s, d).count()
    out = None
    for r in (0.2, 0.5, 0.8):
        x = fixed.fixed(s, n, 200, stride_ratio=r).agg(F.lit(r).alias("ratio"), F.count("*").alias("n"))
        out = x if out is None else out.unionByName(x)
    return out


def _len_sql(stream: str, low: int, high: int) -> str:
    return f"""t AS (SELECT pos, src AS node_id FROM {stream} UNION SELECT pos, dst FROM {stream} WHERE dst IS NOT NULL),
p AS (SELECT pos, max(prev) AS prev FROM (SELECT pos, coalesce(lag(pos) OVER (PARTITION BY node_id ORDER BY pos), -1) AS prev FROM t) GROUP BY pos),
m AS (SELECT count(*) AS m FROM {stream}),
len AS (SELECT i.pos AS start_pos, coalesce(min(CASE WHEN j.prev < i.pos THEN j.pos END), least(i.pos + {high}, max(m.m))) - i.pos AS size FROM p i CROSS JOIN m LEFT JOIN p j ON j.pos >= i.pos + {low} AND j.pos < i.pos + {high} GROUP BY i.pos)"""


def _chain_sql(ratio: float) -> str:
    return f"""w(k, start_pos, size) AS (SELECT 0, start_pos, size FROM len WHERE start_pos = 0 UNION ALL SELECT k + 1, len.start_pos, len.size FROM w JOIN len ON len.start_pos = w.start_pos + greatest(1, CAST(floor({ratio} * w.size + 1e-9) AS BIGINT)) WHERE w.start_pos + w.size < (SELECT m FROM m)),
win AS (SELECT k AS window_id, start_pos, start_pos + size AS end_pos FROM w)"""


def _adaptive_sql(stream: str, low: int = 100, high: int = 300, ratio: float = 0.2) -> str:
    return cte(stream, more=_len_sql(stream, low, high) + ",\n" + _chain_sql(ratio), recursive=True)


@query("q_m24_adaptive_length", cte("s1", more=_len_sql("s1", 100, 300)) + "SELECT start_pos, size FROM len")
def q_length(s, d):
    return adaptive.adaptive_length(s1(s, d), 100, 300)


@query("q_m25_adaptive_windows", _adaptive_sql("s1") + "SELECT window_id, start_pos, end_pos FROM win")
def q_adaptive(s, d):
    return adaptive.adaptive(s1(s, d))


@query("q_m25_adaptive_windows_s3", _adaptive_sql("s3") + "SELECT window_id, start_pos, end_pos FROM win")
def q_adaptive_s3(s, d):
    return adaptive.adaptive(streams.supply(s, d))


@query("q_m26_adaptive_subgraph", cte("s1m", more=_SPANS.format(s="s1m") + _READS.format(s="s1m") + ", " + _len_sql("s1m", 100, 300).replace("t AS (SELECT pos, src AS node_id FROM s1m UNION SELECT pos, dst FROM s1m WHERE dst IS NOT NULL)", "t2 AS (SELECT * FROM reads)").replace("FROM t)", "FROM t2)") + ",\n" + _chain_sql(0.2), recursive=True) + "SELECT window_id, start_pos, end_pos FROM win")
def q_adaptive_subgraph(s, d):
    ev = s1m(s, d)
    prev = stretches.previous_read(ev, spans.edge_spans(ev), 1, "in", 300).persist()  # two numbers an event, read twice
    return adaptive.adaptive(ev, prev=prev)


@query("q_m27_adaptive_fixed_stride", cte("s1", more=_len_sql("s1", 100, 300)) + ", k AS (SELECT i * 40 AS start_pos FROM (SELECT unnest(generate_series(0, (SELECT m FROM m) // 40)) AS i)), s AS (SELECT k.start_pos, size, k.start_pos + size >= (SELECT m FROM m) AS done FROM k JOIN len ON len.start_pos = k.start_pos) SELECT start_pos // 40 AS window_id, start_pos, start_pos + size AS end_pos FROM s WHERE start_pos <= (SELECT min(start_pos) FROM s WHERE done)")
def q_fixed_stride(s, d):
    return adaptive.adaptive(s1(s, d), stride=40)


@query("q_m29_members", _adaptive_sql("s1") + "SELECT window_id, count(*) AS n, sum(pos) AS s FROM win JOIN s1 ON pos >= start_pos AND pos < end_pos GROUP BY window_id")
def q_members(s, d):
    ev = s1(s, d)
    return fixed.members(ev, adaptive.adaptive(ev)).groupBy("window_id").agg(F.count("*").alias("n"), F.sum("pos").alias("s"))


@query("q_m29_members_closed_form", cte("s1") + ", win AS (SELECT i AS window_id, i * 40 AS a FROM (SELECT unnest(generate_series(0, CAST(ceil(((SELECT count(*) FROM s1) - 200) / 40.0) AS BIGINT))) AS i)) SELECT pos, count(*) AS n, min(window_id) AS first_window FROM s1 JOIN win ON pos >= a AND pos < a + 200 GROUP BY pos")
def q_members_closed(s, d):
    ev = s1(s, d)
    count = fixed.fixed(s, ev.count(), 200, 40).count()
    return fixed.members_fixed(ev, 200, 40, count).groupBy("pos").agg(F.count("*").alias("n"), F.min("window_id").alias("first_window"))


@query("q_m30_locality_coverage", cte("s1") + """, t AS (SELECT pos, src AS node_id FROM s1 UNION SELECT pos, dst FROM s1),
pr AS (SELECT DISTINCT a.pos AS i, b.pos AS j FROM t a JOIN t b ON a.node_id = b.node_id AND b.pos > a.pos AND b.pos <= a.pos + 5),
win AS (SELECT i AS w, i * 40 AS a FROM (SELECT unnest(generate_series(0, CAST(ceil(((SELECT count(*) FROM s1) - 200) / 40.0) AS BIGINT))) AS i)),
b AS (SELECT 'batch' AS method, count(*) AS pairs, sum(CASE WHEN i // 200 = j // 200 THEN 1 ELSE 0 END) AS covered FROM pr),
f AS (SELECT 'sliding' AS method, count(*) AS pairs, sum(CASE WHEN EXISTS (SELECT 1 FROM win WHERE a <= i AND j < a + 200) THEN 1 ELSE 0 END) AS covered FROM pr)
SELECT method, pairs, CAST(covered AS BIGINT) AS covered, round(covered / pairs, 6) AS share FROM (SELECT * FROM b UNION ALL SELECT * FROM f)""")
def q_coverage(s, d):
    ev = s1(s, d)
    n = ev.count()
    out = None
    for name, win in (("batch", fixed.batches(s, n)), ("sliding", fixed.fixed(s, n, 200, 40))):
        x = adaptive.locality_coverage(ev, win, 5).withColumn("method", F.lit(name))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_m31_window_stats", _adaptive_sql("s1") + "SELECT count(*) AS n_windows, min(end_pos - start_pos) AS min_size, round(avg(end_pos - start_pos), 6) AS avg_size, max(end_pos - start_pos) AS max_size, round(avg(CASE WHEN end_pos - start_pos = 100 THEN 1.0 ELSE 0.0 END), 6) AS at_low, round(avg(CASE WHEN end_pos - start_pos = 300 THEN 1.0 ELSE 0.0 END), 6) AS at_high FROM win")
def q_window_stats(s, d):
    return fixed.stats(adaptive.adaptive(s1(s, d)), 100, 300)


@query("q_m32_locality_profile", cte("s2") + ", t AS (SELECT pos, src AS node_id FROM s2 UNION SELECT pos, dst FROM s2) SELECT gap, round(count(DISTINCT b.pos) / (any_value(n) - gap), 6) AS share FROM (SELECT unnest([1, 2, 3, 4, 5]) AS gap), (SELECT count(*) AS n FROM s2), t a JOIN t b ON a.node_id = b.node_id WHERE b.pos = a.pos + gap GROUP BY gap")
def q_profile(s, d):
    return adaptive.locality_profile(streams.purchases(s, d), 5)


@query("q_m33_tumbling", "SELECT CAST(floor(epoch_us(ts) / 3600000000.0) AS BIGINT) * 3600000000 AS start_us, count(*) AS n FROM events GROUP BY 1")
def q_tumbling(s, d):
    return fixed.by_time(table(s, d, "events"), "1 hour").select(positions.micros(F.col("start")).alias("start_us"), "n")


@query("q_m33_sliding", "SELECT (h - o) * 1800000000 AS start_us, count(*) AS n FROM (SELECT CAST(floor(epoch_us(ts) / 1800000000.0) AS BIGINT) AS h, unnest([0, 1]) AS o FROM events) GROUP BY 1")
def q_sliding_time(s, d):
    return fixed.by_time(table(s, d, "events"), "1 hour", "30 minutes").select(positions.micros(F.col("start")).alias("start_us"), "n")


@query("q_m33_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), r AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS sid FROM g) SELECT epoch_us(min(ts)) AS start_us, user_id, count(*) AS n FROM r GROUP BY user_id, sid")
def q_session(s, d):
    return fixed.by_time(table(s, d, "events"), "", gap="2 hours", by="user_id").select(positions.micros(F.col("start")).alias("start_us"), "user_id", "n")


# dependencies over disjoint batches of 200: reads k = 0 and k = 1
def _parts(s, d, k=0, diffuse=False):
    ev = s1(s, d)
    reads = affected.affected_nodes(ev, spans.edge_spans(ev), k, "in")
    return ev, reads, affected.writes(ev, reads, diffuse), fixed.batches(s, ev.count(), 200)


def _one_hop(s, d, what):
    ev = s1(s, d)
    win = fixed.batches(s, ev.count(), 200)
    return ev, win, conflicts.one_hop(ev, spans.edge_spans(ev), win, what)


_DEP0 = cte("s1") + ", t AS (SELECT pos, src AS node_id FROM s1 UNION SELECT pos, dst FROM s1), dep AS (SELECT DISTINCT r.pos // 200 AS window_id, r.pos AS later_pos, w.pos AS earlier_pos FROM t r JOIN t w ON r.node_id = w.node_id AND w.pos < r.pos AND w.pos // 200 = r.pos // 200)"
_DEP1 = cte("s1", more=_SPANS.format(s="s1") + _READS.format(s="s1")) + ", dep AS (SELECT DISTINCT r.pos // 200 AS window_id, r.pos AS later_pos, w.pos AS earlier_pos FROM reads r JOIN t w ON r.node_id = w.node_id AND w.pos < r.pos AND w.pos // 200 = r.pos // 200)"
_SUMS = "SELECT window_id, count(*) AS n, sum(later_pos) AS s_later, sum(earlier_pos) AS s_earlier FROM {} GROUP BY window_id"


def _sums(df: DataFrame) -> DataFrame:
    return df.groupBy("window_id").agg(F.count("*").alias("n"), F.sum("later_pos").alias("s_later"), F.sum("earlier_pos").alias("s_earlier"))


@query("q_m34_direct", _DEP0 + "SELECT * FROM dep")
def q_direct(s, d):
    _, r, w, win = _parts(s, d)
    return conflicts.direct(r, w, win)


@query("q_m34_direct_k1", _DEP1 + _SUMS.format("dep"))
def q_direct1(s, d):
    return _sums(_one_hop(s, d, "direct")[2])


@query("q_m35_reduced", _DEP1 + ", red AS (SELECT DISTINCT window_id, later_pos, e AS earlier_pos FROM (SELECT r.pos // 200 AS window_id, r.pos AS later_pos, r.node_id, max(w.pos) AS e FROM reads r JOIN t w ON w.node_id = r.node_id AND w.pos < r.pos AND w.pos // 200 = r.pos // 200 GROUP BY ALL)) SELECT * FROM red")
def q_reduced(s, d):
    return _one_hop(s, d, "reduced")[2]


_CLOSE = _DEP0.replace("WITH ", "WITH RECURSIVE ", 1) + ", clo(window_id, later_pos, earlier_pos) AS (SELECT * FROM dep UNION SELECT c.window_id, c.later_pos, d.earlier_pos FROM clo c JOIN dep d ON d.window_id = c.window_id AND d.later_pos = c.earlier_pos)"


@query("q_m36_closure", _CLOSE + _SUMS.format("clo"))
def q_closure(s, d):
    _, r, w, win = _parts(s, d)
    return _sums(conflicts.closure(conflicts.reduced(r, w, win)))


@query("q_m37_with_root", _DEP0 + "SELECT * FROM dep UNION ALL SELECT pos // 200, pos, -1 FROM s1 WHERE pos NOT IN (SELECT later_pos FROM dep)")
def q_root(s, d):
    ev, r, w, win = _parts(s, d)
    return conflicts.with_root(conflicts.direct(r, w, win), ev, win)


@query("q_m38_chains", _DEP0.replace("WITH ", "WITH RECURSIVE ", 1) + ", u AS (SELECT later_pos AS a, earlier_pos AS b FROM dep UNION SELECT earlier_pos, later_pos FROM dep), c(pos, root) AS (SELECT pos, pos FROM s1 UNION SELECT u.b, c.root FROM c JOIN u ON u.a = c.pos AND c.root < u.b) SELECT pos // 200 AS window_id, pos, min(root) AS chain_id FROM c GROUP BY pos")
def q_chains(s, d):
    ev, r, w, win = _parts(s, d)
    return conflicts.chains(conflicts.reduced(r, w, win), ev, win)


_LEVEL = _DEP0.replace("WITH ", "WITH RECURSIVE ", 1) + ", lv(pos, level) AS (SELECT pos, 1 FROM s1 UNION SELECT d.later_pos, lv.level + 1 FROM lv JOIN dep d ON d.earlier_pos = lv.pos), waves AS (SELECT pos // 200 AS window_id, pos, max(level) AS level FROM lv GROUP BY pos)"


@query("q_m39_waves", _LEVEL + "SELECT window_id, pos, level FROM waves")
def q_waves(s, d):
    ev, r, w, win = _parts(s, d)
    return waves.waves(conflicts.reduced(r, w, win), ev, win)


@query("q_m40_queue")
def q_queue(s, d):
    ev, win, dep = _one_hop(s, d, "reduced")
    return waves.list_schedule(dep, ev, win, 4)


@query("q_m41_chain_plan", _DEP0.replace("WITH ", "WITH RECURSIVE ", 1) + ", u AS (SELECT later_pos AS a, earlier_pos AS b FROM dep UNION SELECT earlier_pos, later_pos FROM dep), c(pos, root) AS (SELECT pos, pos FROM s1 UNION SELECT u.b, c.root FROM c JOIN u ON u.a = c.pos AND c.root < u.b), ch AS (SELECT pos, min(root) AS chain_id FROM c GROUP BY pos) SELECT chain_id // 200 AS window_id, chain_id, count(*) AS n, min(pos) AS first_pos, max(pos) AS last_pos FROM ch GROUP BY chain_id")
def q_chain_plan(s, d):
    ev, r, w, win = _parts(s, d)
    return waves.chain_plan(conflicts.chains(conflicts.reduced(r, w, win), ev, win))


@query("q_m42_anti", _DEP1.replace("dep AS (SELECT DISTINCT r.pos // 200 AS window_id, r.pos AS later_pos, w.pos AS earlier_pos FROM reads r JOIN t w ON r.node_id = w.node_id AND w.pos < r.pos", "dep AS (SELECT DISTINCT r.pos // 200 AS window_id, w.pos AS later_pos, r.pos AS earlier_pos FROM reads r JOIN t w ON r.node_id = w.node_id AND w.pos > r.pos") + _SUMS.format("dep"))
def q_anti(s, d):
    return _sums(_one_hop(s, d, "anti")[2])


@query("q_m42_uncovered")
def q_uncovered(s, d):
    return _one_hop(s, d, "uncovered")[2]


@query("q_m43_concurrent", _CLOSE + "SELECT a.window_id, n * (n - 1) // 2 AS n_pairs, coalesce(o, 0) AS n_ordered, n * (n - 1) // 2 - coalesce(o, 0) AS n_free FROM (SELECT pos // 200 AS window_id, count(*) AS n FROM s1 GROUP BY 1) a LEFT JOIN (SELECT window_id, count(*) AS o FROM clo GROUP BY 1) b ON a.window_id = b.window_id")
def q_concurrent(s, d):
    ev, r, w, win = _parts(s, d)
    return waves.concurrent_pairs(conflicts.closure(conflicts.reduced(r, w, win)), ev, win)


@query("q_m44_stream_index", _adaptive_sql("s1") + ", ix AS (SELECT DISTINCT pos AS later_pos, e AS earlier_pos FROM (SELECT pos, lag(pos) OVER (PARTITION BY node_id ORDER BY pos) AS e FROM t) WHERE e IS NOT NULL) SELECT window_id, count(*) AS n, sum(later_pos) AS s_later, sum(earlier_pos) AS s_earlier FROM win JOIN ix ON later_pos >= start_pos AND later_pos < end_pos AND earlier_pos >= start_pos GROUP BY window_id")
def q_stream_index(s, d):
    ev, r, w, _ = _parts(s, d)
    return _sums(conflicts.for_window(conflicts.stream_index(r, w), adaptive.adaptive(ev)))


# versions: every event writes the position as a one-element vector of each endpoint
def _versions(s, d):
    ev = s1(s, d)
    t = adaptive.touches(ev)
    v0 = store.init(t, table(s, d, "embeddings"))
    return t, v0, store.append(v0, t.select("node_id", F.col("pos").alias("at_pos"), F.array(F.col("pos").cast("float")).alias("z")))


_VER = cte("s1") + ", t AS (SELECT pos, src AS node_id FROM s1 UNION SELECT pos, dst FROM s1), ver AS (SELECT DISTINCT node_id, 0 AS version, -1 AS at_pos FROM t UNION ALL SELECT node_id, row_number() OVER (PARTITION BY node_id ORDER BY pos), pos FROM t)"


@query("q_m62_versions", _VER + "SELECT node_id, version, at_pos FROM ver")
def q_versions(s, d):
    return _versions(s, d)[2].select("node_id", "version", "at_pos")


@query("q_m63_latest", _VER + "SELECT node_id, max(version) AS version, max(at_pos) AS at_pos FROM ver GROUP BY node_id")
def q_latest(s, d):
    return store.latest(_versions(s, d)[2]).select("node_id", "version", "at_pos")


@query("q_m63_get", _VER + "SELECT node_id, 3 AS version, max(CASE WHEN version = 3 THEN at_pos END) AS at_pos FROM ver GROUP BY node_id")
def q_get(s, d):
    t, _, v = _versions(s, d)
    return store.get(v, t.select("node_id").distinct().withColumn("version", F.lit(3))).select("node_id", "version", "at_pos")


@query("q_m63_as_of", _VER + "SELECT node_id, 500 AS pos, max(version) AS version FROM ver WHERE at_pos < 500 GROUP BY node_id")
def q_as_of(s, d):
    t, _, v = _versions(s, d)
    return store.as_of(v, t.select("node_id").distinct().withColumn("pos", F.lit(500).cast("long"))).select("node_id", "pos", "version")


@query("q_m64_vacuum", _VER + "SELECT node_id, version, at_pos FROM (SELECT *, lead(at_pos) OVER (PARTITION BY node_id ORDER BY version) AS nxt FROM ver) WHERE nxt IS NULL OR nxt >= 800")
def q_vacuum(s, d):
    return store.vacuum(_versions(s, d)[2], 800).select("node_id", "version", "at_pos")


@query("q_m65_init", _VER + "SELECT v.node_id, round(CAST(embedding[1] AS DOUBLE), 5) AS z0, label FROM (SELECT DISTINCT node_id FROM ver) v JOIN embeddings e ON e.vec_id = v.node_id % (SELECT count(*) FROM embeddings)")
def q_init(s, d):
    _, v0, _ = _versions(s, d)
    emb = table(s, d, "embeddings")
    n = emb.count()
    return v0.withColumn("vec_id", F.pmod("node_id", F.lit(n))).join(emb.select("vec_id", "label"), "vec_id").select("node_id", F.round(F.get("z", F.lit(0)).cast("double"), 5).alias("z0"), "label")


# measures
@query("q_a09_parallelism", _LEVEL + "SELECT window_id, count(*) AS n, max(level) AS levels, round(count(*) / max(level), 6) AS parallelism, max(width) AS widest FROM (SELECT *, count(*) OVER (PARTITION BY window_id, level) AS width FROM waves) GROUP BY window_id")
def q_parallelism(s, d):
    return measures.parallelism(q_waves(s, d))


@query("q_a10_density", _DEP1 + "SELECT a.window_id, n * (n - 1) // 2 AS possible, coalesce(c, 0) AS pairs, round(coalesce(c, 0) / (n * (n - 1) // 2), 6) AS density FROM (SELECT pos // 200 AS window_id, count(*) AS n FROM s1 GROUP BY 1) a LEFT JOIN (SELECT window_id, count(*) AS c FROM dep GROUP BY 1) b ON a.window_id = b.window_id")
def q_density(s, d):
    ev, win, dep = _one_hop(s, d, "direct")
    return measures.dep_density(dep, ev, win)


@query("q_a11_iterations", _adaptive_sql("s1") + ", tr AS (SELECT window_id, start_pos, end_pos - greatest(1, CAST(floor(0.2 * (end_pos - start_pos) + 1e-9) AS BIGINT)) AS train_end FROM win) SELECT pos, 20 * count(window_id) AS iterations FROM s1 LEFT JOIN tr ON pos >= start_pos AND pos < train_end GROUP BY pos")
def q_iterations(s, d):
    ev = s1(s, d)
    return measures.iterations_per_event(ev, measures.tail_fraction(adaptive.adaptive(ev), 0.2).select("window_id", "start_pos", F.col("train_end").alias("end_pos")), 20)


@query("q_a13_stream_stats", "\nUNION ALL\n".join(f"SELECT * FROM ({cte(n)} SELECT '{n}' AS stream, (SELECT count(*) FROM (SELECT src FROM {n} UNION SELECT dst FROM {n})) AS nodes, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM {n} WHERE pos < floor(0.1 * (SELECT count(*) FROM {n})))) AS initial_edges, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM {n})) AS final_edges, count(*) AS events FROM {n})" for n in ("s1", "s2", "s3")))
def q_stream_stats(s, d):
    out = None
    for n, make in streams.STREAMS.items():
        x = measures.stream_stats(make(s, d), 0.1).withColumn("stream", F.lit(n))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_a17_staleness", _adaptive_sql("s1") + "SELECT pos, min(end_pos) - pos AS staleness FROM s1 JOIN win ON pos >= start_pos AND pos < end_pos GROUP BY pos")
def q_staleness(s, d):
    ev = s1(s, d)
    return measures.staleness(ev, adaptive.adaptive(ev))


# protocols
@query("q_m68_batch_units", cte("s1") + "SELECT b AS batch_id, u AS unit, b * 200 + 200 + u * 40 AS start_pos, b * 200 + 240 + u * 40 AS end_pos FROM (SELECT unnest(generate_series(0, (SELECT count(*) FROM s1) // 200 - 1)) AS b), (SELECT unnest([0, 1, 2, 3, 4]) AS u) WHERE b * 200 + 240 + u * 40 <= (SELECT count(*) FROM s1)")
def q_batch_units(s, d):
    return measures.batch_units(s, s1(s, d).count(), 200, 5)


@query("q_m69_next_stride", cte("s1") + "SELECT i AS window_id, i * 40 + 200 AS start_pos, i * 40 + 240 AS end_pos FROM (SELECT unnest(generate_series(0, CAST(floor(((SELECT count(*) FROM s1) - 240) / 40.0) AS BIGINT))) AS i)")
def q_next_stride(s, d):
    n = s1(s, d).count()
    return measures.next_stride(fixed.fixed(s, n, 200, 40), 40, n)


@query("q_m70_tail_fraction", _adaptive_sql("s1") + "SELECT window_id, start_pos, end_pos - greatest(1, CAST(floor(0.2 * (end_pos - start_pos) + 1e-9) AS BIGINT)) AS train_end, end_pos FROM win")
def q_tail(s, d):
    return measures.tail_fraction(adaptive.adaptive(s1(s, d)), 0.2)


@query("q_m71_holdout", cte("s1") + "SELECT CASE WHEN pos < floor(0.8 * (SELECT count(*) FROM s1)) THEN 'train' ELSE 'test' END AS part, count(*) AS n, max(pos) AS last_pos FROM s1 GROUP BY 1")
def q_holdout(s, d):
    return measures.holdout(s1(s, d), 0.8).groupBy("part").agg(F.count("*").alias("n"), F.max("pos").alias("last_pos"))


@query("q_m73_leaks", _adaptive_sql("s1") + "SELECT * FROM (VALUES ('held_out', 0)) t(training, leaked) UNION ALL SELECT 'whole_window', CAST(sum(greatest(1, CAST(floor((end_pos - start_pos) * 0.2 + 1e-9) AS BIGINT))) AS BIGINT) FROM win")
def q_leaks(s, d):
    """Test events of adaptive windows that training sees: none if the tail is held out, all of it if not."""
    ev = s1(s, d)
    t = measures.tail_fraction(adaptive.adaptive(ev), 0.2)
    test = t.select("window_id", F.col("train_end").alias("start_pos"), "end_pos")
    out = None
    for name, end in (("held_out", "train_end"), ("whole_window", "end_pos")):
        x = measures.leaks(ev, t.select("window_id", "start_pos", F.col(end).alias("end_pos")), test).agg(F.lit(name).alias("training"), F.count("*").alias("leaked"))
        out = x if out is None else out.unionByName(x)
    return out
