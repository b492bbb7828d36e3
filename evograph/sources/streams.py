"""Event streams carved out of the given tables.

Every stream has the columns of ``schema.EVENT``. Ids are tagged by side: left nodes are even
(``2 * id``), right nodes odd (``2 * id + 1``), so one column holds both.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.sources.tables import table
from evograph.stream.positions import assign_positions

#: Event type to (kind, class): lasting associations and passing communications.
MIXED = {"purchase": ("edge_add", "association"), "click": ("edge_add", "communication"), "view": ("edge_add", "communication"), "signup": ("node_add", "association"), "error": ("edge_del", "association")}


def left(c: Column) -> Column:
    return c.cast("long") * 2


def right(c: Column) -> Column:
    return c.cast("long") * 2 + 1


def _event(df: DataFrame, order: list[str], src: Column, dst: Column, ts: str, kind: Column, cls: Column, weight: Column) -> DataFrame:
    cols = [src.alias("src"), dst.alias("dst"), F.col(ts).alias("ts"), kind.alias("kind"), cls.alias("kind_class"), weight.cast("double").alias("weight")]
    return assign_positions(df, order, lambda d: d.select("pos", *cols))


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("k"))


def interactions(spark: SparkSession, sf_dir: str, mixed: bool = False) -> DataFrame:
    """User-item network of ``events``; ``mixed`` maps event types to all kinds of update."""
    e = _events(spark, sf_dir)
    if not mixed:
        return _event(e, ["ts", "event_id"], left(F.col("user_id")), right(F.col("k")), "ts", F.lit("edge_add"), F.lit("communication"), F.col("value"))
    kind = F.create_map(*[F.lit(x) for t, (k, _) in MIXED.items() for x in (t, k)])[F.col("event_type")]
    cls = F.create_map(*[F.lit(x) for t, (_, c) in MIXED.items() for x in (t, c)])[F.col("event_type")]
    dst = F.when(F.col("event_type") != "signup", right(F.col("k")))
    return _event(e, ["ts", "event_id"], left(F.col("user_id")), dst, "ts", kind, cls, F.col("value"))


def community(spark: SparkSession, sf_dir: str, bursts: bool = False) -> DataFrame:
    """Interactions with ten planted communities (a target that can be learned); optionally in bursts."""
    e = _events(spark, sf_dir).withColumn("k", F.col("user_id") % 10 * 10 + F.col("k") % 10)
    ev = _event(e, ["ts", "event_id"], left(F.col("user_id")), right(F.col("k")), "ts", F.lit("edge_add"), F.lit("communication"), F.col("value"))
    return _bursts(ev) if bursts else ev


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Interactions re-ordered so that users act in bursts (time order is given up; ts counts positions)."""
    return _bursts(interactions(spark, sf_dir))


def _bursts(ev: DataFrame) -> DataFrame:
    e = ev.withColumn("block", F.floor(F.col("pos") / 200)).withColumnRenamed("pos", "old")
    start = F.lit("2000-01-01 00:00:00").cast("timestamp_ntz")
    out = assign_positions(e, ["block", "src", "old"], lambda d: d.select("pos", "src", "dst", "kind", "kind_class", "weight"))
    return out.withColumn("ts", start + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("pos").cast("decimal(18,6)"))).select("pos", "src", "dst", "ts", "kind", "kind_class", "weight")


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity")
    return li.join(o, li["l_orderkey"] == o["o_orderkey"])


_LINE_ORDER = ["o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers buy parts; sparse."""
    return _event(_lines(spark, sf_dir), _LINE_ORDER, left(F.col("o_custkey")), right(F.col("l_partkey")), "o_orderdate", F.lit("edge_add"), F.lit("association"), F.col("l_quantity"))


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers meet suppliers; denser."""
    return _event(_lines(spark, sf_dir), _LINE_ORDER, left(F.col("o_custkey")), right(F.col("l_suppkey")), "o_orderdate", F.lit("edge_add"), F.lit("association"), F.col("l_quantity"))


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One sub-stream per conversation: the conversation meets the role that speaks."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").alias("n"))
    role = F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2)
    start = F.lit("2000-01-01 00:00:00").cast("timestamp_ntz")
    c = c.withColumn("ts", start + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("turn").cast("decimal(18,6)")))
    return _event(c, ["conv_id", "turn", "role"], left(F.col("conv_id")), right(role), "ts", F.lit("edge_add"), F.lit("communication"), F.col("n"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``page_id, host, ord, href``: links of the pages' html in order of appearance."""
    p = table(spark, sf_dir, "pages").select("page_id", F.expr("parse_url(url, 'HOST')").alias("host"), F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1).alias("hrefs"))
    return p.select("page_id", "host", F.posexplode("hrefs").alias("ord", "href"))


def site_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts and the paths that their pages link to: an initial graph. Ids are hashes of the names."""
    name = lambda c: F.conv(F.substring(F.md5(c), 1, 12), 16, 10).cast("long")
    start = F.lit("2000-01-01 00:00:00").cast("timestamp_ntz")
    return _event(page_links(spark, sf_dir).withColumn("ts", start), ["page_id", "ord"], left(name(F.col("host"))), right(name(F.col("href"))), "ts", F.lit("edge_add"), F.lit("association"), F.lit(1.0))


def doc_feed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sources publish documents."""
    d = table(spark, sf_dir, "documents").select("doc_id", "n_chars", F.regexp_extract("source", "([0-9]+)$", 1).cast("long").alias("s"))
    start = F.lit("2000-01-01 00:00:00").cast("timestamp_ntz")
    d = d.withColumn("ts", start + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("doc_id").cast("decimal(18,6)")))
    return _event(d, ["doc_id"], left(F.col("s")), right(F.col("doc_id")), "ts", F.lit("edge_add"), F.lit("association"), F.col("n_chars"))


STREAMS = {"s1": interactions, "s2": purchases, "s3": supply}
