"""Scalar function groups, vectors as arrays, samples, losses and layers as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evograph.graph import spans
from evograph.metrics import measures
from evograph.registry import cte, query
from evograph.sources import streams
from evograph.sources.tables import table
from evograph.stream.positions import assign_positions, micros


@query("q_o55_fn_string", "SELECT page_id, lower(substr(url, 1, 8)) AS head, length(url) AS n, lpad(CAST(page_id AS VARCHAR), 6, '0') AS id, regexp_extract(url, '://([^/?#]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape, concat_ws('|', 'p', CAST(page_id AS VARCHAR)) AS tag, levenshtein(substr(url, 1, 10), 'https://ab') AS dist, trim('  x ') AS t, string_split(url, '/')[3] AS part FROM pages")
def fn_string(s, d):
    return table(s, d, "pages").select("page_id", F.lower(F.substring("url", 1, 8)).alias("head"), F.length("url").alias("n"), F.lpad(F.col("page_id").cast("string"), 6, "0").alias("id"), F.regexp_extract("url", "://([^/?#]+)", 1).alias("host"), F.regexp_replace("url", "[0-9]+", "#").alias("shape"), F.concat_ws("|", F.lit("p"), F.col("page_id").cast("string")).alias("tag"), F.levenshtein(F.substring("url", 1, 10), F.lit("https://ab")).alias("dist"), F.trim(F.lit("  x ")).alias("t"), F.get(F.split("url", "/"), F.lit(2)).alias("part"))


@query("q_o56_fn_time", "SELECT event_id, CAST(date_trunc('hour', ts) AS VARCHAR) AS h, date_diff('day', DATE '2000-01-01', CAST(ts AS DATE)) AS days, extract(hour FROM ts) AS hr, extract(minute FROM ts) AS mi, dayofweek(ts) + 1 AS dow, CAST(CAST(ts AS DATE) + 3 AS VARCHAR) AS later, epoch_us(ts) AS us FROM events")
def fn_time(s, d):
    t = F.col("ts")
    return table(s, d, "events").select("event_id", F.date_format(F.date_trunc("hour", t), "yyyy-MM-dd HH:mm:ss").alias("h"), F.datediff(t, F.lit("2000-01-01").cast("date")).alias("days"), F.hour(t).alias("hr"), F.minute(t).alias("mi"), F.dayofweek(t).alias("dow"), F.date_add(t.cast("date"), 3).cast("string").alias("later"), micros(t).alias("us"))


@query("q_o57_fn_math", "SELECT event_id, round(exp(-value / 100), 6) AS e, round(ln(value + 1), 6) AS l, round(1 / (1 + exp(-value / 50)), 6) AS sig, round(sqrt(value), 6) AS sq, round(pow(value, 1.5), 4) AS p, floor(value)::BIGINT AS f, ceil(value)::BIGINT AS c, sign(value - 50)::INT AS sg, user_id % 7 AS m, round(tanh(value / 100), 6) AS th FROM events")
def fn_math(s, d):
    v = F.col("value")
    return table(s, d, "events").select("event_id", F.round(F.exp(-v / 100), 6).alias("e"), F.round(F.log1p(v), 6).alias("l"), F.round(1 / (1 + F.exp(-v / 50)), 6).alias("sig"), F.round(F.sqrt(v), 6).alias("sq"), F.round(F.pow(v, F.lit(1.5)), 4).alias("p"), F.floor(v).alias("f"), F.ceil(v).alias("c"), F.signum(v - 50).cast("int").alias("sg"), F.pmod("user_id", F.lit(7)).alias("m"), F.round(F.tanh(v / 100), 6).alias("th"))


@query("q_o58_fn_array", cte("s1") + ", a AS (SELECT src, list_sort(list(DISTINCT dst)) AS x FROM s1 WHERE pos < 1000 GROUP BY src) SELECT src, len(x) AS n, x[1] AS first, len(list_intersect(x, [1, 3, 5, 7, 9, 11])) AS hit, list_has_any(x, [1, 3]) AS any, list_sum(list_transform(x, lambda v: v * 2)) AS dbl, len(list_filter(x, lambda v: v > 99)) AS big, coalesce(list_position(x, 7), 0) AS at FROM a".replace(" AS at FROM", " AS at7 FROM"))
def fn_array(s, d):
    a = streams.interactions(s, d).where("pos < 1000").groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("x"))
    lit = F.array(*[F.lit(k).cast("long") for k in (1, 3, 5, 7, 9, 11)])
    return a.select("src", F.size("x").alias("n"), F.element_at("x", 1).alias("first"), F.size(F.array_intersect("x", lit)).alias("hit"), F.arrays_overlap("x", F.slice(lit, 1, 2)).alias("any"), F.aggregate(F.transform("x", lambda v: v * 2), F.lit(0).cast("long"), lambda p, v: p + v).alias("dbl"), F.size(F.filter("x", lambda v: v > 99)).alias("big"), F.array_position("x", F.lit(7).cast("long")).alias("at7"))


@query("q_o59_fn_map", cte("s1") + ", g AS (SELECT src, dst, min(pos) AS p FROM s1 WHERE pos < 2000 GROUP BY ALL) SELECT src, count(*) AS n, sum(p) AS total, max(CASE WHEN dst = 1 THEN p END) AS at_one, count(*) FILTER (WHERE p > 500) AS late FROM g GROUP BY src")
def fn_map(s, d):
    g = streams.interactions(s, d).where("pos < 2000").groupBy("src", "dst").agg(F.min("pos").alias("p"))
    m = g.groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", "p"))).alias("m"))
    return m.select("src", F.size("m").alias("n"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, v: a + v).alias("total"), F.try_element_at("m", F.lit(1).cast("long")).alias("at_one"), F.size(F.map_filter("m", lambda k, v: v > 500)).alias("late"))


@query("q_o60_fn_json", "SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k, (props->>'$.none') IS NULL AS missing, CAST(props->>'$.k' AS BIGINT) + 1 AS next FROM events")
def fn_json(s, d):
    v = F.parse_json("props")
    return table(s, d, "events").select("event_id", F.variant_get(v, "$.k", "bigint").alias("k"), F.try_variant_get(v, "$.none", "bigint").isNull().alias("missing"), (F.get_json_object("props", "$.k").cast("long") + 1).alias("next"))


@query("q_o61_fn_hash", "SELECT event_id, md5(event_type) AS m, substr(sha256(event_type), 1, 16) AS h, TRY_CAST(event_type AS INT) AS t, user_id << 2 AS sl, user_id & 5 AS a, xor(user_id, 9) AS x FROM events")
def fn_hash(s, d):
    u = F.col("user_id")
    return table(s, d, "events").select("event_id", F.md5("event_type").alias("m"), F.substring(F.sha2("event_type", 256), 1, 16).alias("h"), F.expr("try_cast(event_type AS INT)").alias("t"), F.shiftleft(u, 2).alias("sl"), u.bitwiseAND(5).alias("a"), u.bitwiseXOR(9).alias("x"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda p, v: p + v)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def softmax(a: Column) -> Column:
    top = F.array_max(a)
    e = F.transform(a, lambda x: F.exp((x - top).cast("double")))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda p, v: p + v))


def link_score(zu: Column, zv: Column) -> Column:
    """Probability of a link from the dot product."""
    return 1 / (1 + F.exp(-dot(zu, zv)))


@query("q_o62_fn_vector", "SELECT a.vec_id, round(list_inner_product(a.v, b.v), 4) AS dot, round(list_cosine_similarity(a.v, b.v), 4) AS cos, round(sqrt(list_inner_product(a.v, a.v)), 4) AS l2 FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) a JOIN (SELECT vec_id - 1 AS vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) b ON a.vec_id = b.vec_id")
def fn_vector(s, d):
    e = table(s, d, "embeddings")
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("w"))
    j = e.join(b, "vec_id")
    return j.select("vec_id", F.round(dot(F.col("embedding"), F.col("w")), 4).alias("dot"), F.round(cosine(F.col("embedding"), F.col("w")), 4).alias("cos"), F.round(norm(F.col("embedding")), 4).alias("l2"))


def aggregate_vectors(df: DataFrame, by: list[str], vec: str, how: str = "mean") -> DataFrame:
    """Element-wise mean, sum or max of vectors by group: exploded by dimension, so partial sums go before the shuffle."""
    f = {"mean": F.avg, "sum": F.sum, "max": F.max}[how]
    e = df.select(*by, F.posexplode(vec).alias("dim", "x"))
    g = e.groupBy(*by, "dim").agg(f(F.col("x").cast("double")).alias("x"))
    return g.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda t: t["x"]).alias(vec))


def static_layers(nodes: DataFrame, edges: DataFrame, scale: list[tuple[float, float]], how: str = "mean") -> DataFrame:
    """``node_id, z`` after one layer per (neighbour, self) weight pair: gather in-neighbours, then update."""
    z = nodes
    for wn, ws in scale:
        h = aggregate_vectors(edges.select("src", "dst").distinct().join(z.select(F.col("node_id").alias("src"), "z"), "src"), ["dst"], "z", how).select(F.col("dst").alias("node_id"), F.col("z").alias("h"))
        z = z.join(h, "node_id", "left").select("node_id", F.when(F.col("h").isNull(), F.transform("z", lambda x: F.tanh(x * ws))).otherwise(F.zip_with("z", "h", lambda a, b: F.tanh(a * ws + b * wn))).alias("z"))
    return z


_N = cte("s1") + ", g AS (SELECT DISTINCT src, dst FROM s1 WHERE pos <= 500), n AS (SELECT src AS id FROM g UNION SELECT dst FROM g), z0 AS (SELECT id, dim, CAST(v AS DOUBLE) AS v FROM (SELECT id, unnest(embedding[1:4]) AS v, generate_subscripts(embedding[1:4], 1) AS dim FROM n JOIN embeddings ON vec_id = id % (SELECT count(*) FROM embeddings)))"


def _z0(s, d):
    g = spans.graph_at(spans.edge_spans(streams.interactions(s, d)), 500)
    emb = table(s, d, "embeddings")
    n = g.select(F.explode(F.array("src", "dst")).alias("node_id")).distinct()
    z = n.withColumn("vec_id", F.pmod("node_id", F.lit(emb.count()))).join(emb, "vec_id").select("node_id", F.transform(F.slice("embedding", 1, 4), lambda x: x.cast("double")).alias("z"))
    return g, z


@query("q_m45_static_layer", _N + ", h AS (SELECT g.dst AS id, dim, avg(v) AS h FROM g JOIN z0 ON z0.id = g.src GROUP BY ALL) SELECT z0.id AS node_id, z0.dim - 1 AS dim, round(tanh(v * 0.5 + coalesce(h, 0) * 0.7), 5) AS z FROM z0 LEFT JOIN h ON h.id = z0.id AND h.dim = z0.dim")
def static_layer(s, d):
    g, z = _z0(s, d)
    return static_layers(z, g, [(0.7, 0.5)]).select("node_id", F.posexplode("z").alias("dim", "z")).withColumn("z", F.round("z", 5))


for _how, _fn in (("mean", "avg"), ("sum", "sum"), ("max", "max")):

    @query(f"q_m46_aggregate_{_how}", _N + f" SELECT g.dst AS node_id, dim - 1 AS dim, round({_fn}(v), 5) AS z FROM g JOIN z0 ON z0.id = g.src GROUP BY ALL")
    def vector_aggregate(s, d, how=_how):
        g, z = _z0(s, d)
        return aggregate_vectors(g.join(z.withColumnRenamed("node_id", "src"), "src"), ["dst"], "z", how).select(F.col("dst").alias("node_id"), F.posexplode("z").alias("dim", "z")).withColumn("z", F.round("z", 5))


@query("q_m52_decay", cte("s1") + ", g AS (SELECT pos, (epoch_us(ts) - coalesce(lag(epoch_us(ts)) OVER (PARTITION BY src ORDER BY pos), epoch_us(ts))) / 1000000.0 AS dt FROM s1) SELECT pos, round(1 / ln(exp(1) + dt), 6) AS log_decay, round(exp(-dt / 86400), 6) AS exp_decay, round(ln(1 + dt), 6) AS drive FROM g")
def decay(s, d):
    dt = F.col("dt_u")
    return spans.elapsed(streams.interactions(s, d)).select("pos", F.round(1 / F.log(F.lit(2.718281828459045) + dt), 6).alias("log_decay"), F.round(F.exp(-dt / 86400), 6).alias("exp_decay"), F.round(F.log1p(dt), 6).alias("drive"))


def targets_seen(ev: DataFrame, width: int = 65_536) -> tuple[DataFrame, DataFrame]:
    """``ix, cand`` of every target by its first event, and ``pos, seen``: the number first seen before each event."""
    first = ev.where("dst IS NOT NULL").groupBy("dst").agg(F.min("pos").alias("first"))
    pool = assign_positions(first, ["first"], lambda x: x.select(F.col("pos").alias("ix"), F.col("dst").alias("cand"), "first"))
    e = ev.where("dst IS NOT NULL").select("pos").join(pool.select(F.col("first").alias("pos"), F.lit(1).alias("new")), "pos", "left")
    e = e.select("pos", F.floor(F.col("pos") / width).alias("b"), F.coalesce("new", F.lit(0)).alias("new"))
    per = e.groupBy("b").agg(F.sum("new").alias("n"))  # one row per bucket of positions
    earlier = per.select("b", F.coalesce(F.sum("n").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("new").over(Window.partitionBy("b").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return pool.select("ix", "cand"), e.withColumn("inside", inside).join(earlier, "b").select("pos", (F.col("base") + F.col("inside")).alias("seen"))


def negatives(ev: DataFrame, n_neg: int = 5, seed: int = 0) -> DataFrame:
    """``pos, src, dst, y, neg_ix``: seeded candidates by arithmetic among the targets seen before; the next one where the true node comes up.

    An event before which no other target was seen has none.
    """
    pool, seen = targets_seen(ev)
    e = ev.where("dst IS NOT NULL").select("pos", "src", "dst").join(seen, "pos").where("seen > 0").withColumn("neg_ix", F.explode(F.sequence(F.lit(0), F.lit(n_neg - 1))))
    e = e.withColumn("ix", (F.col("pos") * 48271 + F.col("neg_ix") * 69621 + seed) % F.col("seen"))
    e = e.join(pool, "ix").withColumn("ix2", F.when(F.col("cand") == F.col("dst"), (F.col("ix") + 1) % F.col("seen")).otherwise(F.col("ix"))).drop("cand", "ix")
    return e.join(pool, F.col("ix2") == F.col("ix")).where("cand <> dst").select("pos", "src", F.col("cand").alias("dst"), F.lit(0).alias("y"), "neg_ix")


def link_samples(ev: DataFrame, n_neg: int = 5, seed: int = 0) -> DataFrame:
    """Positives (neg_ix -1) and negatives as one binary task."""
    return ev.where("dst IS NOT NULL").select("pos", "src", "dst", F.lit(1).alias("y"), F.lit(-1).alias("neg_ix")).unionByName(negatives(ev, n_neg, seed))


_NEG = cte("s1") + """, pool AS (SELECT row_number() OVER (ORDER BY first) - 1 AS ix, cand, first FROM (SELECT dst AS cand, min(pos) AS first FROM s1 GROUP BY dst)),
sn AS (SELECT s1.pos, s1.src, s1.dst, sum(CASE WHEN f.first IS NULL THEN 0 ELSE 1 END) OVER (ORDER BY s1.pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM s1 LEFT JOIN pool f ON f.first = s1.pos),
e AS (SELECT pos, src, dst, i, CAST((pos * 48271 + i * 69621) % m AS BIGINT) AS ix, m FROM sn, (SELECT unnest([0, 1, 2, 3, 4]) AS i) WHERE m > 0),
ng AS (SELECT pos, src, q.cand AS dst, 0 AS y, i AS neg_ix FROM e JOIN pool p ON p.ix = e.ix JOIN pool q ON q.ix = CASE WHEN p.cand = e.dst THEN (e.ix + 1) % m ELSE e.ix END WHERE q.cand <> e.dst),
smp AS (SELECT pos, src, dst, 1 AS y, -1 AS neg_ix FROM s1 UNION ALL SELECT * FROM ng)"""


@query("q_m53_negatives", _NEG + " SELECT * FROM ng")
def q_negatives(s, d):
    return negatives(streams.interactions(s, d))


@query("q_m54_link_samples", _NEG + " SELECT * FROM smp")
def q_link_samples(s, d):
    return link_samples(streams.interactions(s, d))


def _scored(s, d, digits=9):
    emb = table(s, d, "embeddings")
    n = emb.count()
    e = emb.select(F.col("vec_id"), F.slice("embedding", 1, 8).alias("z"))
    x = link_samples(streams.interactions(s, d)).withColumns({"iu": F.pmod("src", F.lit(n)), "iv": F.pmod("dst", F.lit(n))})
    x = x.join(e.select(F.col("vec_id").alias("iu"), F.col("z").alias("zu")), "iu").join(e.select(F.col("vec_id").alias("iv"), F.col("z").alias("zv")), "iv")
    return x.select("pos", "src", "dst", "y", "neg_ix", F.round(link_score(F.col("zu"), F.col("zv")), digits).alias("score"))


_SC = _NEG + ", sc AS (SELECT pos, src, dst, y, neg_ix, round(1 / (1 + exp(-list_inner_product(CAST(a.embedding[1:8] AS DOUBLE[]), CAST(b.embedding[1:8] AS DOUBLE[])))), 9) AS score FROM smp, (SELECT count(*) AS k FROM embeddings) JOIN embeddings a ON a.vec_id = src % k JOIN embeddings b ON b.vec_id = dst % k)"


@query("q_m55_link_score", _SC.replace("), 9) AS score", "), 5) AS score") + " SELECT pos, dst, neg_ix, score FROM sc")
def q_link_score(s, d):
    return _scored(s, d, 5).select("pos", "dst", "neg_ix", "score")


@query("q_m56_node_class", "WITH v AS (SELECT vec_id, label, generate_subscripts(embedding, 1) AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), c AS (SELECT label, dim, avg(x) AS m FROM v GROUP BY ALL), ds AS (SELECT v.vec_id, any_value(v.label) AS truth, c.label AS label, sum((x - m) * (x - m)) AS dist FROM v JOIN c ON c.dim = v.dim GROUP BY v.vec_id, c.label) SELECT vec_id, arg_min(label, round(dist, 9)) AS predicted FROM ds GROUP BY vec_id")
def node_class(s, d):
    """Nearest class centroid; centroids are as many as classes."""
    e = table(s, d, "embeddings").select("vec_id", "label", "embedding")
    c = aggregate_vectors(e, ["label"], "embedding", "mean").select(F.col("label").alias("c"), F.col("embedding").alias("m"))
    x = e.crossJoin(F.broadcast(c))  # one row per class, a bounded side
    dist = F.aggregate(F.zip_with("embedding", "m", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda p, v: p + v)
    return x.withColumn("dist", F.round(dist, 9)).groupBy("vec_id").agg(F.min_by("c", "dist").alias("predicted"))


@query("q_m57_bce", _SC + " SELECT round(avg(-(y * ln(score) + (1 - y) * ln(1 - score))), 5) AS bce FROM sc")
def q_bce(s, d):
    return measures.bce(_scored(s, d)).select(F.round("bce", 5).alias("bce"))


@query("q_a01_auc", _SC + ", r AS (SELECT pos // 1000 AS window_id, y, rank() OVER (PARTITION BY pos // 1000 ORDER BY score) + (count(*) OVER (PARTITION BY pos // 1000, score) - 1) / 2.0 AS r FROM sc) SELECT window_id, round((sum(CASE WHEN y = 1 THEN r END) - sum(y) * (sum(y) + 1) / 2.0) / (sum(y) * (count(*) - sum(y))), 5) AS auc, count(*) AS n FROM r GROUP BY window_id")
def q_auc(s, d):
    x = _scored(s, d).withColumn("window_id", F.floor(F.col("pos") / 1000))
    return measures.auc(x, by=["window_id"]).select("window_id", F.round("auc", 5).alias("auc"), "n")


@query("q_a01_auc_histogram", _SC + ", r AS (SELECT y, CAST(floor(least(score * 65536, 65535)) AS INT) AS b FROM sc), k AS (SELECT y, rank() OVER (ORDER BY b) + (count(*) OVER (PARTITION BY b) - 1) / 2.0 AS r FROM r) SELECT round((sum(CASE WHEN y = 1 THEN r END) - sum(y) * (sum(y) + 1) / 2.0) / (sum(y) * (count(*) - sum(y))), 5) AS auc FROM k")
def q_auc_histogram(s, d):
    return measures.auc_histogram(_scored(s, d)).select(F.round("auc", 5).alias("auc"))


@query("q_a02_mean_of_best", _SC + ", r AS (SELECT pos // 1000 AS w, (pos // 200) % 5 AS e, y, rank() OVER (PARTITION BY pos // 200 ORDER BY score) + (count(*) OVER (PARTITION BY pos // 200, score) - 1) / 2.0 AS r FROM sc), a AS (SELECT w, e, (sum(CASE WHEN y = 1 THEN r END) - sum(y) * (sum(y) + 1) / 2.0) / (sum(y) * (count(*) - sum(y))) AS auc FROM r GROUP BY ALL), b AS (SELECT w, max(auc) AS auc FROM a GROUP BY w) SELECT round(avg(auc), 5) AS auc, count(auc) AS windows FROM b")
def q_mean_of_best(s, d):
    x = _scored(s, d).withColumns({"window_id": F.floor(F.col("pos") / 1000), "epoch": F.floor(F.col("pos") / 200) % 5})
    log = measures.auc(x, by=["window_id", "epoch"]).withColumns({"model": F.lit("dot"), "method": F.lit("batch")})
    return measures.mean_of_best(log).select(F.round("auc", 5).alias("auc"), "windows")


@query("q_a12_store_bytes", cte("s1") + ", t AS (SELECT pos, src AS n FROM s1 UNION SELECT pos, dst FROM s1) SELECT (SELECT count(*) FROM t) + (SELECT count(DISTINCT n) FROM t) AS versions, (SELECT count(*) FROM t) * 4 + (SELECT count(DISTINCT n) FROM t) * 256 AS bytes")
def q_store_bytes(s, d):
    from evograph.workloads.methods import _versions

    return measures.store_bytes(_versions(s, d)[2])


@query("q_a18_accuracy", _SC + " SELECT round(avg(CASE WHEN (score >= 0.5) = (y = 1) THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM sc")
def q_accuracy(s, d):
    return measures.accuracy(_scored(s, d))
