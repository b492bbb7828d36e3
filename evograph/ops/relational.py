"""Relational operators a user of the methods needs, re-expressed on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evograph.graph import adjacency, affected, spans
from evograph.joins.joins import asof, band, salted
from evograph.registry import cte, query
from evograph.schema import TABLES
from evograph.sources import streams
from evograph.sources.tables import scan, table
from evograph.stream.positions import micros
from evograph.windows.adaptive import touches
from evograph.windows.fixed import batches


#: A table of more rows is not broadcast on demand: the driver and every executor would hold all of it.
BROADCAST_ROWS = 1_000_000


def _s1(s: SparkSession, d: str) -> DataFrame:
    return streams.interactions(s, d)


def _s1m(s: SparkSession, d: str) -> DataFrame:
    return streams.interactions(s, d, mixed=True)


@query("q_o01_scan_counts", "\nUNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n FROM {t}" for t in TABLES))
def scan_counts(s, d):
    out = None
    for t in TABLES:
        x = table(s, d, t).agg(F.lit(t).alias("table_name"), F.count("*").alias("n"))
        out = x if out is None else out.unionByName(x)
    return out


@query("q_o02_pruned_scan", "SELECT event_id, user_id FROM events WHERE value > 90")
def pruned_scan(s, d):
    return scan(s, d, "events", ["event_id", "user_id"], F.col("value") > 90)


@query("q_o09_json_edges", "SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")
def json_edges(s, d):
    return table(s, d, "events").select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"))


@query("q_o09_html_links", cte("links") + "SELECT page_id, CAST(ord AS BIGINT) AS ord, href FROM links")
def html_links(s, d):
    return streams.page_links(s, d).select("page_id", F.col("ord").cast("long").alias("ord"), "href")


@query("q_o10_sql_degree", cte("s1") + "SELECT src AS node_id, count(DISTINCT dst) AS degree FROM s1 GROUP BY src")
def sql_degree(s, d):
    return s.sql("SELECT src AS node_id, count(DISTINCT dst) AS degree FROM {ev} GROUP BY src", ev=_s1(s, d))


@query("q_o11_event_tuple", cte("s1m") + "SELECT pos, src, dst, kind FROM s1m")
def event_tuple(s, d):
    return _s1m(s, d).select("pos", "src", "dst", "kind")


@query("q_o12_null_logic", cte("s1m") + "SELECT kind, count(*) FILTER (WHERE dst IS NULL) AS n_null_dst, count(*) FILTER (WHERE dst <> 1 OR dst IS NULL) AS n_any, count(*) FILTER (WHERE NOT (dst > 50)) AS n_not FROM s1m GROUP BY kind")
def null_logic(s, d):
    return _s1m(s, d).groupBy("kind").agg(F.count_if(F.col("dst").isNull()).alias("n_null_dst"), F.count_if((F.col("dst") != 1) | F.col("dst").isNull()).alias("n_any"), F.count_if(~(F.col("dst") > 50)).alias("n_not"))


@query("q_o13_predicates", cte("s1m") + "SELECT pos FROM s1m WHERE pos BETWEEN 100 AND 900 AND kind IN ('edge_add', 'edge_del') AND kind_class LIKE 'comm%' AND regexp_matches(kind, 'add$') AND dst IS NOT NULL")
def predicates(s, d):
    return _s1m(s, d).where(F.col("pos").between(100, 900) & F.col("kind").isin("edge_add", "edge_del") & F.col("kind_class").like("comm%") & F.col("kind").rlike("add$") & F.col("dst").isNotNull()).select("pos")


@query("q_o14_case_kind", cte("s1m") + "SELECT CASE WHEN kind LIKE 'edge%' THEN 'edge' ELSE 'node' END AS what, coalesce(nullif(dst, 1), -1) % 10 AS bucket, count(*) AS n, max(greatest(src, coalesce(dst, 0))) AS hi, min(least(src, coalesce(dst, src))) AS lo FROM s1m GROUP BY 1, 2")
def case_kind(s, d):
    return _s1m(s, d).groupBy(F.when(F.col("kind").like("edge%"), "edge").otherwise("node").alias("what"), (F.coalesce(F.nullif("dst", F.lit(1)), F.lit(-1)) % 10).alias("bucket")).agg(F.count("*").alias("n"), F.max(F.greatest("src", F.coalesce("dst", F.lit(0)))).alias("hi"), F.min(F.least("src", F.coalesce("dst", "src"))).alias("lo"))


@query("q_o15_seen_before", cte("s1") + "SELECT pos, EXISTS (SELECT 1 FROM s1 b WHERE b.src = a.src AND b.dst = a.dst AND b.pos < a.pos) AS is_repeat, weight > (SELECT avg(weight) FROM s1) AS above FROM s1 a")
def seen_before(s, d):
    # the correlated test becomes a window by pair: one shuffle, no join
    ev = _s1(s, d)
    mean = ev.agg(F.avg("weight").alias("mean"))
    return ev.withColumn("is_repeat", F.row_number().over(Window.partitionBy("src", "dst").orderBy("pos")) > 1).join(F.broadcast(mean)).select("pos", "is_repeat", (F.col("weight") > F.col("mean")).alias("above"))


@query("q_o16_distinct_pairs", cte("s1") + "SELECT DISTINCT src, dst FROM s1")
def distinct_pairs(s, d):
    return _s1(s, d).dropDuplicates(["src", "dst"]).select("src", "dst")


@query("q_o17_hash_sample", cte("s1") + "SELECT pos FROM s1 WHERE (pos * 48271 + 11) % 2147483647 % 10 = 0")
def hash_sample(s, d):
    return _s1(s, d).where((F.col("pos") * 48271 + 11) % 2147483647 % 10 == 0).select("pos")


@query("q_o17_stratified_hash", cte("s1m") + "SELECT kind, count(*) AS n FROM s1m WHERE (pos * 48271 + 11) % 2147483647 % 100 < CASE kind WHEN 'edge_add' THEN 10 WHEN 'edge_del' THEN 50 ELSE 100 END GROUP BY kind")
def stratified_hash(s, d):
    """A share of each kind by an arithmetic hash: the same rows whatever the partitions."""
    share = F.when(F.col("kind") == "edge_add", 10).when(F.col("kind") == "edge_del", 50).otherwise(100)
    return _s1m(s, d).where((F.col("pos") * 48271 + 11) % 2147483647 % 100 < share).groupBy("kind").agg(F.count("*").alias("n"))


@query("q_o17_stratified_sample")
def stratified_sample(s, d):
    return _s1m(s, d).sampleBy("kind", {"edge_add": 0.1, "edge_del": 0.5, "node_add": 1.0}, seed=7).groupBy("kind").agg(F.count("*").alias("n"))


for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"q_o18_order_stream_{_hint}", "SELECT l_orderkey, o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
    def order_stream(s, d, hint=_hint):
        o = table(s, d, "orders").select("o_orderkey", "o_custkey")
        if hint != "broadcast" or o.count() <= BROADCAST_ROWS:  # the count comes from the files' footers
            o = o.hint(hint)
        return table(s, d, "lineitem").select("l_orderkey").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey", "o_custkey").agg(F.count("*").alias("n"))


@query("q_o19_delta_outer", cte("s1m") + ", a AS (SELECT DISTINCT src, dst FROM s1m WHERE dst IS NOT NULL AND pos < 500), b AS (SELECT DISTINCT src, dst FROM s1m WHERE dst IS NOT NULL AND pos >= 500) SELECT coalesce(a.src, b.src) AS src, coalesce(a.dst, b.dst) AS dst, CASE WHEN a.src IS NULL THEN 'new' WHEN b.src IS NULL THEN 'gone' ELSE 'both' END AS change FROM a FULL JOIN b ON a.src = b.src AND a.dst = b.dst")
def delta_outer(s, d):
    ev = _s1m(s, d).where("dst IS NOT NULL")
    a = ev.where("pos < 500").select("src", "dst").distinct().withColumn("a", F.lit(True))
    b = ev.where("pos >= 500").select("src", "dst").distinct().withColumn("b", F.lit(True))
    return a.join(b, ["src", "dst"], "full").select("src", "dst", F.when(F.col("a").isNull(), "new").when(F.col("b").isNull(), "gone").otherwise("both").alias("change"))


@query("q_o20_new_nodes", cte("s1") + "SELECT DISTINCT dst AS node_id FROM s1 WHERE pos >= 200 AND dst NOT IN (SELECT dst FROM s1 WHERE pos < 200)")
def new_nodes(s, d):
    ev = _s1(s, d).select("pos", F.col("dst").alias("node_id"))
    return ev.where("pos >= 200").select("node_id").distinct().join(ev.where("pos < 200").select("node_id"), "node_id", "left_anti")


@query("q_o20_known_edges", cte("s1") + "SELECT DISTINCT src, dst FROM s1 a WHERE pos >= 200 AND EXISTS (SELECT 1 FROM s1 b WHERE b.pos < 200 AND a.src = b.src AND a.dst = b.dst)")
def known_edges(s, d):
    ev = _s1(s, d)
    return ev.where("pos >= 200").select("src", "dst").distinct().join(ev.where("pos < 200").select("src", "dst"), ["src", "dst"], "left_semi")


@query("q_o21_all_pairs_conflict", cte("s1") + "SELECT b.pos AS later_pos, a.pos AS earlier_pos FROM s1 a, s1 b WHERE a.pos < 500 AND b.pos < 500 AND a.pos < b.pos AND (a.src = b.src OR a.dst = b.dst)")
def all_pairs_conflict(s, d):
    """The all-pairs baseline itself, on one window of 500 events: what the equi-join replaces."""
    w = _s1(s, d).where("pos < 500").select("pos", F.array("src", "dst").alias("nodes"))
    a, b = w.select(F.col("pos").alias("earlier_pos"), F.col("nodes").alias("na")), w.select(F.col("pos").alias("later_pos"), F.col("nodes").alias("nb"))
    return b.crossJoin(a).where((F.col("earlier_pos") < F.col("later_pos")) & F.arrays_overlap("na", "nb")).select("later_pos", "earlier_pos")


@query("q_o22_band_pairs", cte("s1") + "SELECT a.pos, b.pos AS next_pos FROM s1 a JOIN s1 b ON b.pos BETWEEN a.pos + 3 AND a.pos + 9 AND a.dst = b.dst")
def band_pairs(s, d):
    ev = _s1(s, d)
    return band(ev.select("pos", "dst"), ev.select(F.col("pos").alias("next_pos"), F.col("dst").alias("next_dst")), "pos", "next_pos", 3, 9).where("dst = next_dst").select("pos", "next_pos")


@query("q_o23_alive_edges", cte("s1m", more="""e AS (SELECT pos, src, dst, kind FROM s1m WHERE dst IS NOT NULL AND kind IN ('edge_add', 'edge_del')), l AS (SELECT *, sum(CASE WHEN kind = 'edge_del' THEN 1 ELSE 0 END) OVER (PARTITION BY src, dst ORDER BY pos) AS life, min(CASE WHEN kind = 'edge_del' THEN pos END) OVER (PARTITION BY src, dst ORDER BY pos ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS nd FROM e), sp AS (SELECT src, dst, min(pos) AS a, coalesce(min(nd), 4611686018427387904) AS b FROM l WHERE kind = 'edge_add' GROUP BY src, dst, life)""") + "SELECT p AS pos, count(sp.src) AS n_edges FROM (SELECT unnest([0, 99, 499, 999]) AS p) LEFT JOIN sp ON a <= p AND b > p GROUP BY p")
def alive_edges(s, d):
    sp = spans.edge_spans(_s1m(s, d))
    asked = s.createDataFrame([(p,) for p in (0, 99, 499, 999)], "pos long")
    return F.broadcast(asked).join(sp, (F.col("from_pos") <= F.col("pos")) & (F.col("to_pos") > F.col("pos"))).groupBy("pos").agg(F.count("*").alias("n_edges")).join(asked, "pos", "right").select("pos", F.coalesce("n_edges", F.lit(0)).alias("n_edges"))


@query("q_o24_asof_last_event", "SELECT p.event_id, c.value AS prev_value FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND c.ts <= p.ts")
def asof_last_event(s, d):
    e = table(s, d, "events")
    return asof(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'click'").select("user_id", "ts", "value"), "user_id", "ts", "value").select("event_id", F.col("asof_value").alias("prev_value"))


@query("q_o24_asof_forward", "SELECT p.event_id, c.value AS next_value FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND c.ts >= p.ts")
def asof_forward(s, d):
    e = table(s, d, "events")
    return asof(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'click'").select("user_id", "ts", "value"), "user_id", "ts", "value", "forward").select("event_id", F.col("asof_value").alias("next_value"))


@query("q_o25_click_to_purchase", "SELECT c.user_id, c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def click_to_purchase(s, d):
    e = table(s, d, "events")
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("tc"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("tp"))
    return c.join(p, "user_id").where((F.col("tp") > F.col("tc")) & (F.col("tp") <= F.col("tc") + F.expr("INTERVAL 1 HOUR"))).select("user_id", "click", "purchase")


@query("q_o26_two_paths", cte("s1") + "SELECT count(*) AS n, sum(a.src) AS s FROM s1 a JOIN s1 b ON a.dst = b.dst AND a.src < b.src WHERE a.pos < 2000 AND b.pos < 2000")
def two_paths(s, d):
    e = _s1(s, d).where("pos < 2000")
    return e.alias("a").join(e.alias("b"), (F.col("a.dst") == F.col("b.dst")) & (F.col("a.src") < F.col("b.src"))).agg(F.count("*").alias("n"), F.sum("a.src").alias("s"))


@query("q_o27_last_three", "SELECT user_id, event_id, rk FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC) AS rk FROM events) WHERE rk <= 3")
def last_three(s, d):
    e = table(s, d, "events")
    return e.withColumn("rk", F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("ts")))).where("rk <= 3").select("user_id", "event_id", "rk")


@query("q_o27_lateral", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def lateral(s, d):
    c, o = table(s, d, "customer").select("c_custkey"), table(s, d, "orders")
    return c.lateralJoin(o.where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_totalprice") > 200000)).select("o_orderkey"))


@query("q_o28_touch_pairs", cte("s1") + ", t AS (SELECT pos, src AS n FROM s1 UNION SELECT pos, dst FROM s1) SELECT DISTINCT b.pos AS later_pos, a.pos AS earlier_pos FROM t a JOIN t b ON a.n = b.n AND a.pos < b.pos AND a.pos // 200 = b.pos // 200")
def touch_pairs(s, d):
    t = touches(_s1(s, d)).withColumn("w", F.floor(F.col("pos") / 200))
    return t.select("w", "node_id", F.col("pos").alias("earlier_pos")).join(t.select("w", "node_id", F.col("pos").alias("later_pos")), ["w", "node_id"]).where("earlier_pos < later_pos").select("later_pos", "earlier_pos").distinct()


@query("q_o29_star_revenue", "SELECT r_name, p_brand, round(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) / 100.0, 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def star_revenue(s, d):
    li = table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice")
    o, c = table(s, d, "orders").select("o_orderkey", "o_custkey"), table(s, d, "customer").select("c_custkey", "c_nationkey")
    n, r = table(s, d, "nation").select("n_nationkey", "n_regionkey"), table(s, d, "region")
    p = table(s, d, "part").select("p_partkey", "p_brand")
    c = c.join(F.broadcast(n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name")
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("r_name", "p_brand").agg(F.round(F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")) / 100.0, 2).alias("revenue"))


@query("q_o30_null_safe_match", cte("s1m") + ", n AS (SELECT DISTINCT dst FROM s1m WHERE pos < 300) SELECT count(*) AS n FROM s1m a JOIN n ON a.dst IS NOT DISTINCT FROM n.dst")
def null_safe_match(s, d):
    ev = _s1m(s, d).select("pos", "dst")
    n = ev.where("pos < 300").select(F.col("dst").alias("d")).distinct()
    return ev.join(n, ev["dst"].eqNullSafe(n["d"])).agg(F.count("*").alias("n"))


@query("q_o31_salted_degree_join", cte("s1") + ", g AS (SELECT dst, count(*) AS degree FROM s1 GROUP BY dst) SELECT pos, g.dst AS node_id, degree FROM s1 JOIN g ON g.dst = s1.dst")
def salted_degree_join(s, d):
    ev = _s1(s, d).select("pos", F.col("dst").alias("node_id"))
    return salted(ev, ev.groupBy("node_id").agg(F.count("*").alias("degree")), "node_id")


@query("q_o32_degree_stats", cte("s1") + "SELECT src AS node_id, count(*) AS n, round(sum(weight), 4) AS total, round(avg(weight), 4) AS mean, min(weight) AS lo, max(weight) AS hi FROM s1 GROUP BY src")
def degree_stats(s, d):
    return _s1(s, d).groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("n"), F.round(F.sum("weight"), 4).alias("total"), F.round(F.avg("weight"), 4).alias("mean"), F.min("weight").alias("lo"), F.max("weight").alias("hi"))


@query("q_o33_sorted_neighbours", cte("s1") + "SELECT src AS node_id, string_agg(DISTINCT dst::VARCHAR, ',' ORDER BY dst::VARCHAR) AS nbrs FROM s1 GROUP BY src")
def sorted_neighbours(s, d):
    return _s1(s, d).groupBy(F.col("src").alias("node_id")).agg(F.array_join(F.array_sort(F.collect_set(F.col("dst").cast("string"))), ",").alias("nbrs"))


@query("q_o34_distinct_nodes", cte("s1m") + "SELECT kind, count(DISTINCT src) AS srcs, count(DISTINCT dst) AS dsts, count(DISTINCT src * 100000 + coalesce(dst, 0)) AS pairs FROM s1m GROUP BY kind")
def distinct_nodes(s, d):
    return _s1m(s, d).groupBy("kind").agg(F.countDistinct("src").alias("srcs"), F.countDistinct("dst").alias("dsts"), F.countDistinct(F.col("src") * 100000 + F.coalesce("dst", F.lit(0))).alias("pairs"))


_CUBE = "SELECT kind, kind_class, CAST(day AS BIGINT) AS day, count(*) AS n, CAST({g} AS BIGINT) AS g FROM (SELECT kind, kind_class, epoch_us(ts) // 86400000000 AS day FROM s1m) GROUP BY {by}"


@query("q_o35_cube_kind_day", cte("s1m") + _CUBE.format(g="grouping(kind) * 4 + grouping(kind_class) * 2 + grouping(day)", by="CUBE (kind, kind_class, day)"))
def cube_kind_day(s, d):
    ev = _s1m(s, d).select("kind", "kind_class", F.floor(micros(F.col("ts")) / 86_400_000_000).alias("day"))
    return ev.cube("kind", "kind_class", "day").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("q_o35_rollup", cte("s1m") + _CUBE.format(g="grouping(kind) * 4 + grouping(kind_class) * 2 + grouping(day)", by="ROLLUP (kind, kind_class, day)"))
def rollup_kind_day(s, d):
    ev = _s1m(s, d).select("kind", "kind_class", F.floor(micros(F.col("ts")) / 86_400_000_000).alias("day"))
    return ev.rollup("kind", "kind_class", "day").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("q_o35_grouping_sets", cte("s1m") + "SELECT kind, kind_class, count(*) AS n FROM s1m GROUP BY GROUPING SETS ((kind), (kind_class), ())")
def grouping_sets(s, d):
    return s.sql("SELECT kind, kind_class, count(*) AS n FROM {ev} GROUP BY GROUPING SETS ((kind), (kind_class), ())", ev=_s1m(s, d))


@query("q_o36_filtered_counts", cte("s1m") + "SELECT src, count(*) FILTER (WHERE kind = 'edge_add') AS adds, count(*) FILTER (WHERE kind = 'edge_del') AS dels, sum(weight) FILTER (WHERE kind = 'nothing') AS none FROM s1m GROUP BY src")
def filtered_counts(s, d):
    return s.sql("SELECT src, count(*) FILTER (WHERE kind = 'edge_add') AS adds, count(*) FILTER (WHERE kind = 'edge_del') AS dels, sum(weight) FILTER (WHERE kind = 'nothing') AS none FROM {ev} GROUP BY src", ev=_s1m(s, d))


@query("q_o37_latest_by_node", cte("s1m") + "SELECT src, arg_max(weight, pos) AS latest, arg_min(weight, pos) AS earliest, arg_max(kind, pos) AS kind FROM s1m GROUP BY src")
def latest_by_node(s, d):
    return _s1m(s, d).groupBy("src").agg(F.max_by("weight", "pos").alias("latest"), F.min_by("weight", "pos").alias("earliest"), F.max_by("kind", "pos").alias("kind"))


@query("q_o38_value_moments", "SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 6) AS vp, round(corr(value, user_id), 6) AS r, round(covar_samp(value, user_id), 6) AS c, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS med FROM events GROUP BY event_type")
def value_moments(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.var_pop("value"), 6).alias("vp"), F.round(F.corr("value", F.col("user_id").cast("double")), 6).alias("r"), F.round(F.covar_samp("value", F.col("user_id").cast("double")), 6).alias("c"), F.round(F.percentile("value", F.lit(0.25)), 6).alias("q1"), F.round(F.median("value"), 6).alias("med"))


@query("q_o39_bool_bits", cte("s1m") + "SELECT src, bool_and(weight > 1) AS all_big, bool_or(weight > 99) AS any_big, bit_xor(coalesce(dst, 0)) AS x, bit_or(coalesce(dst, 0)) AS o, bit_and(coalesce(dst, 0)) AS a, count(DISTINCT dst) AS distinct_dst FROM s1m GROUP BY src")
def bool_bits(s, d):
    n = F.coalesce("dst", F.lit(0))
    ev = _s1m(s, d)
    bits = ev.groupBy("src", F.bitmap_bucket_number("dst").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("dst")).alias("m")).groupBy("src").agg(F.coalesce(F.sum(F.bitmap_count("m")), F.lit(0)).alias("distinct_dst"))
    return ev.groupBy("src").agg(F.bool_and(F.col("weight") > 1).alias("all_big"), F.bool_or(F.col("weight") > 99).alias("any_big"), F.bit_xor(n).alias("x"), F.bit_or(n).alias("o"), F.bit_and(n).alias("a")).join(bits, "src")


@query("q_o40_approx_nodes")
def approx_nodes(s, d):
    return _s1(s, d).groupBy("kind").agg(F.approx_count_distinct("src", 0.02).alias("srcs"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("dsts"), F.percentile_approx("weight", 0.5, 1000).alias("median"), F.countDistinct("src").alias("exact_srcs"), F.countDistinct("dst").alias("exact_dsts"))


@query("q_o40_sketch_bounds", cte("s1") + "SELECT count(DISTINCT src) AS srcs, count(DISTINCT dst) AS dsts, true AS hll, true AS theta, true AS overlap, true AS kll, true AS top FROM s1")
def sketch_bounds(s, d):
    """Exact counts, and whether each sketch is within its error: distinct, set overlap, median, most frequent."""
    ev = _s1(s, d)
    theta = F.expr("theta_sketch_agg(src)")
    a = ev.agg(
        F.countDistinct("src").alias("srcs"), F.countDistinct("dst").alias("dsts"),
        F.hll_sketch_estimate(F.hll_sketch_agg("src")).alias("hll"), F.expr("theta_sketch_estimate(theta_sketch_agg(src))").alias("theta"),
        F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(weight), 0.5D)").alias("kll"), F.expr("percentile(weight, array(0.45, 0.55))").alias("middle"),
        F.expr("approx_top_k(dst, 1)[0].count").alias("top"),
    )
    halves = ev.agg(theta.alias("all")).crossJoin(ev.where("pos % 2 = 0").agg(theta.alias("even")))
    both = halves.select(F.expr("theta_sketch_estimate(theta_intersection(all, even))").alias("both")).crossJoin(ev.where("pos % 2 = 0").agg(F.countDistinct("src").alias("exact")))
    most = ev.groupBy("dst").count().agg(F.max("count").alias("most"))
    near = lambda x, y, e: F.abs(x - y) <= e * y + 1
    return a.crossJoin(both).crossJoin(most).select(
        "srcs", "dsts", near(F.col("hll"), F.col("srcs"), 0.06).alias("hll"), near(F.col("theta"), F.col("srcs"), 0.06).alias("theta"), near(F.col("both"), F.col("exact"), 0.1).alias("overlap"),
        F.col("kll").between(F.col("middle")[0], F.col("middle")[1]).alias("kll"), near(F.col("top"), F.col("most"), 0.05).alias("top"),
    )


@query("q_o41_kind_pivot", cte("s1m") + "SELECT kind_class, count(*) FILTER (WHERE kind = 'edge_add') AS edge_add, count(*) FILTER (WHERE kind = 'edge_del') AS edge_del, count(*) FILTER (WHERE kind = 'node_add') AS node_add FROM s1m GROUP BY kind_class")
def kind_pivot(s, d):
    return _s1m(s, d).groupBy("kind_class").pivot("kind", ["edge_add", "edge_del", "node_add"]).agg(F.count(F.lit(1))).na.fill(0)


@query("q_o41_unpivot", cte("s1m") + "SELECT pos, 'src' AS side, src AS node_id FROM s1m UNION ALL SELECT pos, 'dst', dst FROM s1m WHERE dst IS NOT NULL")
def unpivot(s, d):
    return _s1m(s, d).unpivot(["pos"], ["src", "dst"], "side", "node_id").where("node_id IS NOT NULL")


@query("q_o42_vector_mean", "SELECT label, dim - 1 AS dim, round(avg(CAST(v AS DOUBLE)), 5) AS mean, round(max(CAST(v AS DOUBLE)), 5) AS hi FROM (SELECT label, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS dim FROM embeddings) GROUP BY label, dim")
def vector_mean(s, d):
    e = table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("dim", "v"))
    return e.groupBy("label", "dim").agg(F.round(F.avg(F.col("v").cast("double")), 5).alias("mean"), F.round(F.max(F.col("v").cast("double")), 5).alias("hi"))


@query("q_o43_chain_text", cte("s1") + "SELECT src, string_agg(pos::VARCHAR, '>' ORDER BY pos) AS chain FROM s1 GROUP BY src")
def chain_text(s, d):
    return _s1(s, d).groupBy("src").agg(F.expr("listagg(CAST(pos AS STRING), '>') WITHIN GROUP (ORDER BY pos)").alias("chain"))


@query("q_o44_size_histogram", "SELECT CAST(floor(value / 10) AS BIGINT) + 1 AS bin, count(*) AS n FROM events WHERE value >= 0 AND value < 100 GROUP BY 1")
def size_histogram(s, d):
    return table(s, d, "events").where("value >= 0 AND value < 100").groupBy(F.expr("width_bucket(value, 0, 100, 10)").alias("bin")).agg(F.count("*").alias("n"))


@query("q_o45_rank_family", "SELECT event_id, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER (PARTITION BY user_id ORDER BY k, event_id) AS q FROM (SELECT *, CAST(props->>'$.k' AS BIGINT) AS k FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY k)")
def rank_family(s, d):
    e = table(s, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    w = Window.partitionBy("user_id").orderBy("k")
    return e.select("event_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(Window.partitionBy("user_id").orderBy("k", "event_id")).alias("q"))


@query("q_o46_lag_lead", cte("s1m") + "SELECT pos, lag(dst, 1) OVER w AS p, lead(dst, 2) OVER w AS n, last_value(dst IGNORE NULLS) OVER (PARTITION BY src ORDER BY pos) AS l, first_value(kind) OVER w AS f, nth_value(kind, 2) OVER (PARTITION BY src ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM s1m WINDOW w AS (PARTITION BY src ORDER BY pos)")
def lag_lead(s, d):
    w = Window.partitionBy("src").orderBy("pos")
    run = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return _s1m(s, d).select("pos", F.lag("dst", 1).over(w).alias("p"), F.lead("dst", 2).over(w).alias("n"), F.last("dst", ignorenulls=True).over(run).alias("l"), F.first("kind").over(w).alias("f"), F.nth_value("kind", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"))


@query("q_o47_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last_three, count(*) OVER (PARTITION BY user_id) AS all_rows FROM events")
def frames(s, d):
    e = table(s, d, "events").withColumn("us", micros(F.col("ts")))
    w = Window.partitionBy("user_id").orderBy("us")
    return e.select("event_id", F.count("*").over(w.rangeBetween(-3_600_000_000, 0)).alias("last_hour"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("last_three"), F.count("*").over(Window.partitionBy("user_id")).alias("all_rows"))


@query("q_o48_running_edges", cte("s1") + "SELECT pos, count(*) OVER (PARTITION BY src ORDER BY pos) AS running, round(avg(weight) OVER (PARTITION BY src ORDER BY pos ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 5) AS smooth FROM s1")
def running_edges(s, d):
    w = Window.partitionBy("src").orderBy("pos")
    return _s1(s, d).select("pos", F.count("*").over(w).alias("running"), F.round(F.avg("weight").over(w.rowsBetween(-4, 0)), 5).alias("smooth"))


@query("q_o49_islands", cte("s2") + ", g AS (SELECT src, pos, pos - row_number() OVER (PARTITION BY src ORDER BY pos) AS island FROM s2) SELECT src, min(pos) AS first_pos, count(*) AS n FROM g GROUP BY src, island")
def islands(s, d):
    w = Window.partitionBy("src").orderBy("pos")
    return streams.purchases(s, d).select("src", "pos", (F.col("pos") - F.row_number().over(w)).alias("island")).groupBy("src", "island").agg(F.min("pos").alias("first_pos"), F.count("*").alias("n")).drop("island")


@query("q_o50_chronological", cte("s1m") + "SELECT row_number() OVER (ORDER BY dst DESC NULLS LAST, pos) AS rk, pos FROM s1m ORDER BY rk LIMIT 1000")
def chronological(s, d):
    top = _s1m(s, d).orderBy(F.desc_nulls_last("dst"), "pos").limit(1000)
    return top.select(F.row_number().over(Window.orderBy(F.desc_nulls_last("dst"), "pos")).alias("rk"), "pos")  # a top-k report of 1000 rows


@query("q_o51_top_hubs", cte("s1") + "SELECT dst AS node_id, count(*) AS n FROM s1 GROUP BY dst ORDER BY n DESC, node_id LIMIT 10 OFFSET 5")
def top_hubs(s, d):
    return _s1(s, d).groupBy(F.col("dst").alias("node_id")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "node_id").offset(5).limit(10)


@query("q_o52_sorted_parts", cte("s1") + "SELECT src, count(*) AS n, max(pos) AS last_pos FROM s1 GROUP BY src")
def sorted_parts(s, d):
    p = _s1(s, d).repartition("src").sortWithinPartitions("src", "pos")
    return p.groupBy("src").agg(F.count("*").alias("n"), F.max("pos").alias("last_pos"))


@query("q_o53_set_ops", cte("s1") + ", a AS (SELECT src, dst FROM s1 WHERE pos < 500), b AS (SELECT src, dst FROM s1 WHERE pos >= 500) SELECT 'intersect' AS op, count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b) UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)")
def set_ops(s, d):
    e = _s1(s, d)
    a, b = e.where("pos < 500").select("src", "dst"), e.where("pos >= 500").select("src", "dst")
    out = None
    for name, x in (("intersect", a.intersect(b)), ("except", a.subtract(b)), ("except_all", a.exceptAll(b)), ("intersect_all", a.intersectAll(b)), ("union", a.union(b).distinct())):
        y = x.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = y if out is None else out.unionByName(y)
    return out


@query("q_o54_recursive_levels", cte("s1") + ", dep AS (SELECT DISTINCT b.pos AS later, a.pos AS earlier FROM s1 a JOIN s1 b ON a.pos < b.pos AND (a.src = b.src OR a.dst = b.dst) WHERE a.pos < 200 AND b.pos < 200), lv AS (SELECT * FROM (WITH RECURSIVE l(pos, level) AS (SELECT pos, 1 FROM s1 WHERE pos < 200 UNION SELECT later, level + 1 FROM l JOIN dep ON earlier = pos) SELECT * FROM l)) SELECT pos, max(level) AS level FROM lv GROUP BY pos")
def recursive_levels(s, d):
    """Levels of the first window by a recursive query (the operator under test; windows of any stream use groups)."""
    e = _s1(s, d).where("pos < 200")
    return s.sql("""WITH RECURSIVE e AS (SELECT pos, src, dst FROM {e}), dep AS (SELECT DISTINCT b.pos AS later, a.pos AS earlier FROM e a JOIN e b ON a.src = b.src AND a.pos < b.pos UNION SELECT b.pos, a.pos FROM e a JOIN e b ON a.dst = b.dst AND a.pos < b.pos),
      red AS (SELECT later, earlier FROM dep), l(pos, level, step) AS (SELECT pos, 1, 1 FROM e UNION ALL SELECT DISTINCT later, level + 1, step + 1 FROM l JOIN red ON earlier = pos WHERE level = step AND step < 60) SELECT pos, max(level) AS level FROM l GROUP BY pos""", e=e)


# graph helpers
@query("q_g01_degrees", cte("s1") + ", g AS (SELECT DISTINCT src, dst FROM s1 WHERE pos <= 900) SELECT node_id, sum(i) AS in_degree, sum(o) AS out_degree FROM (SELECT src AS node_id, 0 AS i, 1 AS o FROM g UNION ALL SELECT dst, 1, 0 FROM g) GROUP BY node_id")
def g_degrees(s, d):
    return adjacency.degrees(spans.edge_spans(_s1(s, d)), 900)


_FOLD = cte("s1", more="f AS (SELECT (src // 2) % 40 AS src, (dst // 2 + 3) % 40 AS dst FROM s1 WHERE pos <= 300), e AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM f WHERE src <> dst)")


def _folded(s: SparkSession, d: str) -> DataFrame:
    """A one-sided graph: users and items share forty names, so that triangles exist."""
    half = lambda c, more: F.floor(F.col(c) / 2 + more).cast("long") % 40
    return _s1(s, d).withColumns({"src": half("src", 0), "dst": half("dst", 3)})


@query("q_g02_triangles", _FOLD + "SELECT count(*) AS triangles FROM e x JOIN e y ON y.a = x.b JOIN e z ON z.a = x.a AND z.b = y.b")
def g_triangles(s, d):
    return adjacency.triangles(spans.edge_spans(_folded(s, d)), 300)


@query("q_g03_components", cte("s1", more="e AS (SELECT DISTINCT src AS a, dst AS b FROM s1 WHERE pos <= 40 UNION SELECT dst, src FROM s1 WHERE pos <= 40), c(n, root) AS (SELECT a, a FROM e UNION SELECT e.b, c.root FROM c JOIN e ON e.a = c.n AND c.root < e.b)", recursive=True) + "SELECT n AS node_id, min(root) AS component FROM c GROUP BY n")
def g_components(s, d):
    """Components of an early snapshot, when the graph still has several."""
    return adjacency.connected_components(spans.edge_spans(_s1(s, d)), 40)


@query("q_g04_reach", cte("s1") + ", g AS (SELECT DISTINCT src, dst FROM s1 WHERE pos <= 300), b AS (SELECT src AS a, dst AS b FROM g UNION SELECT dst, src FROM g), r0 AS (SELECT 1 AS n, 0 AS h), r1 AS (SELECT b AS n, 1 AS h FROM b WHERE a = 1), r2 AS (SELECT b.b AS n, 2 AS h FROM r1 JOIN b ON b.a = r1.n) SELECT n AS node_id, min(h) AS hops FROM (SELECT * FROM r0 UNION ALL SELECT * FROM r1 UNION ALL SELECT * FROM r2) GROUP BY n")
def g_reach(s, d):
    return affected.reach(spans.edge_spans(_s1(s, d)), 300, s.createDataFrame([(1,)], "node_id long"), 2)


@query("q_g05_pair_scores", cte("s1") + ", g AS (SELECT DISTINCT src, dst FROM s1 WHERE pos <= 2000), dg AS (SELECT src, count(*) AS k FROM g GROUP BY src) SELECT x.a, x.b, common, round(common / (da.k + db.k - common), 6) AS jaccard, da.k * db.k AS preferential FROM (SELECT p.src AS a, q.src AS b, count(*) AS common FROM g p JOIN g q ON p.dst = q.dst AND p.src < q.src GROUP BY ALL) x JOIN dg da ON da.src = a JOIN dg db ON db.src = b")
def g_pair_scores(s, d):
    return adjacency.pair_scores(spans.edge_spans(_s1(s, d)), 2000)


@query("q_g06_window_hubs", cte("s1") + ", t AS (SELECT pos, src AS node_id FROM s1 UNION SELECT pos, dst FROM s1) SELECT pos // 200 AS window_id, node_id, count(*) AS n FROM t JOIN (SELECT pos // 200 AS w, count(*) AS size FROM s1 GROUP BY 1) z ON z.w = pos // 200 GROUP BY pos // 200, node_id HAVING count(*) >= 0.02 * any_value(size)")
def g_window_hubs(s, d):
    """Nodes that take part in two hundredths or more of a batch."""
    ev = _s1(s, d)
    return adjacency.window_hubs(ev, batches(s, ev.count(), 200), 0.02)
