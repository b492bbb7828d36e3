"""Quality rules: simple text measures and cross-document line frequency, native DataFrame code.

A line, lower-cased, with white space and digit runs folded, is hashed; for every host the
number of distinct documents that hold it is counted. Lines held by more than ``max_share`` of
the host's documents, though by more than ``min_docs`` of a small host and by ``MAX_DOCS`` of any host at most,
are boilerplate and go, if ``MIN_TEXTS`` different texts hold them: what fewer hold is a passage
of copies of one text, and copies are for deduplication to remove. A document that keeps less than ``min_kept`` of its words without them is
depleted and rejected, as is one that fails the base rules.

A host with a third of all rows is no special case: lines are made distinct inside their
document, counted in part before any shuffle, and the boilerplate lines come back by an
equi-join whose large side can be split. Nulls: a null text has no words and fails; a null
host is the empty host. Repeated rows get equal verdicts. Empty tables give empty results.
Columns other than ``doc_id, text, source`` play no part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.llm.common import table

GAP = r"[\x20\x09-\x0D]+"
_BLANKS = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: A line is boilerplate beyond this share of a host's documents; the limit is no lower and no higher than these numbers.
MAX_SHARE, MIN_DOCS, MAX_DOCS = 0.1, 10, 10_000
#: Different texts that hold a line of boilerplate.
MIN_TEXTS = 10
#: A document that keeps less of its words is depleted.
MIN_KEPT = 0.3


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, GAP), lambda w: w != "")


def normal_line(line: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(F.regexp_replace(line, GAP, " "), "[0-9]+", "0")))


def _repeat_words(df: DataFrame) -> DataFrame:
    """Add ``n_repeat_words`` to rows with ``words``: positions inside 3-word windows found twice."""
    n = F.size("words")
    grams = F.when(n >= 3, F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get("words", i), F.get("words", i + 1), F.get("words", i + 2)))).otherwise(F.array().cast("array<bigint>"))
    df = df.withColumn("grams", grams)
    again = F.size(F.array_distinct("grams")) < F.size("grams")
    df = df.withColumn("sorted", F.when(again, F.sort_array(F.transform("grams", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    # the array itself, not an array of its field: that would be built anew for every element
    same = lambda x, j: F.coalesce(F.get("sorted", j)["h"] == x["h"], F.lit(False))
    df = df.withColumn("hits", F.filter("sorted", lambda x, j: same(x, j - 1) | same(x, j + 1)))
    marks = F.array_distinct(F.flatten(F.transform("hits", lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2))))
    return df.withColumn("n_repeat_words", F.when(F.col("hits").isNull(), F.lit(0)).otherwise(F.size(marks)).cast("long")).drop("grams", "sorted", "hits")


def base_measures(docs: DataFrame) -> DataFrame:
    """``doc_id, print`` and the base measures with their verdict."""
    t = F.coalesce("text", F.lit(""))
    df = docs.select("doc_id", t.alias("text")).withColumn("words", words_of(F.col("text")))
    df = _repeat_words(df)
    line_words = F.filter(F.split("text", "\n"), lambda x: F.translate(x, _BLANKS, "") != "")
    n = F.size("words").cast("long")
    df = df.select(
        "doc_id",
        F.xxhash64("text").alias("print"),
        n.alias("n_words"),
        F.length(F.translate("text", _BLANKS, "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        (F.size(line_words) - F.size(F.array_distinct(line_words))).cast("long").alias("n_dup_lines"),
        # not a deterministic column, so that no filter on it is moved below and evaluated inside the lambdas
        (F.col("n_repeat_words") + F.monotonically_increasing_id() * 0).alias("n_repeat_words"),
    )
    failed = (F.col("n_words") < MIN_WORDS) | (F.col("n_repeat_words") * 100 > F.col("n_words") * MAX_REPEAT_PERCENT)
    return df.withColumn("base_failed", failed)


def document_lines(docs: DataFrame) -> DataFrame:
    """``host, doc_id, print, line, n, size``: each distinct normalised line of a text, its occurrences' words."""
    df = docs.select("doc_id", F.coalesce("source", F.lit("")).alias("host"), F.coalesce("text", F.lit("")).alias("text"))
    line = F.transform(F.split("text", "\n"), lambda x: normal_line(x))
    df = df.select("doc_id", "host", F.xxhash64("text").alias("print"), F.filter(line, lambda x: x != "").alias("lines"))
    item = F.transform("lines", lambda x: F.struct(F.xxhash64(x).alias("line"), F.size(F.split(x, " ")).alias("size")))
    df = df.select("doc_id", "host", "print", item.alias("items"))
    one = F.array_distinct("items")
    return df.select("doc_id", "host", "print", F.explode(one).alias("x")).select("doc_id", "host", "print", "x.line", "x.size")


def boilerplate(lines: DataFrame, docs: DataFrame, min_docs: int = MIN_DOCS, max_share: float = MAX_SHARE) -> DataFrame:
    """``host, line``: lines in more distinct documents of a host than its limit."""
    per_text = lines.groupBy("host", "line", "print", "doc_id").agg(F.lit(1).alias("one")).groupBy("host", "line", "print").agg(F.count("*").alias("docs"))
    per_line = per_text.groupBy("host", "line").agg(F.sum("docs").alias("docs"), F.count("*").alias("texts"))
    rows = docs.select(F.coalesce("source", F.lit("")).alias("host"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("print"), "doc_id")
    hosts = rows.groupBy("host", "print", "doc_id").agg(F.lit(1).alias("one")).groupBy("host").agg(F.count("*").alias("all_docs"))
    many = per_line.where((F.col("docs") > min_docs) & (F.col("texts") >= MIN_TEXTS)).join(hosts, "host")
    return many.where(F.col("docs") > F.least(F.lit(float(MAX_DOCS)), F.col("all_docs") * max_share)).select("host", "line")


def depletion(docs: DataFrame, min_docs: int = MIN_DOCS, max_share: float = MAX_SHARE) -> DataFrame:
    """``doc_id, print, gone``: the boilerplate lines of each document that has some."""
    lines = document_lines(docs)
    hit = lines.join(boilerplate(lines, docs, min_docs, max_share), ["host", "line"])
    return hit.groupBy("doc_id", "print").agg(F.collect_set(F.struct("line", "size")).alias("gone"))


def rules(docs: DataFrame, min_docs: int = MIN_DOCS, max_share: float = MAX_SHARE, min_kept: float = MIN_KEPT) -> DataFrame:
    """One row per document: base measures, words lost with boilerplate lines, verdict."""
    base, gone = base_measures(docs), depletion(docs, min_docs, max_share)
    g = gone.select(F.col("doc_id").alias("g_id"), F.col("print").alias("g_print"), F.aggregate("gone", F.lit(0).cast("long"), lambda s, x: s + x["size"]).alias("lost"))
    df = base.join(g, F.col("doc_id").eqNullSafe(F.col("g_id")) & (F.col("print") == F.col("g_print")), "left")
    lost = F.coalesce("lost", F.lit(0).cast("long"))
    depleted = (F.col("n_words") - lost) < F.col("n_words") * F.lit(min_kept)
    return df.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & ~depleted).alias("kept"), lost.alias("n_boilerplate_words"))


def filter_documents(docs: DataFrame, min_docs: int = MIN_DOCS, max_share: float = MAX_SHARE, min_kept: float = MIN_KEPT) -> DataFrame:
    """Documents that pass, with the given columns, their boilerplate lines removed."""
    names = docs.columns
    base = base_measures(docs).where(~F.col("base_failed")).select("doc_id", "print", "n_words").distinct()
    gone = depletion(docs, min_docs, max_share)
    v = base.alias("b").join(gone.alias("g"), F.col("b.doc_id").eqNullSafe(F.col("g.doc_id")) & (F.col("b.print") == F.col("g.print")), "left")
    lost = F.coalesce(F.aggregate("gone", F.lit(0).cast("long"), lambda s, x: s + x["size"]), F.lit(0).cast("long"))
    ok = v.where((F.col("n_words") - lost) >= F.col("n_words") * F.lit(min_kept)).select(F.col("b.doc_id").alias("v_id"), F.col("b.print").alias("v_print"), F.transform(F.coalesce("gone", F.array().cast("array<struct<line:bigint,size:int>>")), lambda x: x["line"]).alias("v_gone"))
    others = [c for c in names if c not in ("doc_id", "text")]  # renamed meanwhile: they may be called anything
    df = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("v_key"), *[F.col(f"`{c}`").alias(f"o{i}") for i, c in enumerate(others)])
    df = df.join(ok, F.col("doc_id").eqNullSafe(F.col("v_id")) & (F.col("v_key") == F.col("v_print")))
    rest = F.array_join(F.filter(F.split("text", "\n"), lambda x: ~F.array_contains("v_gone", F.xxhash64(normal_line(x)))), "\n")
    df = df.withColumn("text", F.when(F.size("v_gone") > 0, rest).otherwise(F.col("text")))
    back = {c: F.col(f"o{i}") for i, c in enumerate(others)} | {c: F.col(c) for c in ("doc_id", "text")}
    if "n_chars" in back:
        back["n_chars"] = F.length("text").cast(docs.schema["n_chars"].dataType)
    return df.select(*[back[c].alias(c) for c in names])


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules(table(spark, sf_dir, "documents"))


OP8_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(source, '') AS host, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, host, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words FROM d),
g AS (SELECT doc_id, i, words[i] AS a, words[i + 1] AS b, words[i + 2] AS c
      FROM (SELECT doc_id, words, unnest(generate_series(1, len(words) - 2)) AS i FROM w WHERE len(words) >= 3)),
hit AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, a, b, c) AS n FROM g) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n_repeat FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM hit) GROUP BY doc_id),
l AS (SELECT doc_id, host, text, unnest(string_split(text, chr(10))) AS line FROM d),
lw AS (SELECT doc_id, count(*) - count(DISTINCT line) AS dup FROM l WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
nl AS (SELECT DISTINCT doc_id, host, text,
         lower(trim(regexp_replace(regexp_replace(line, '[\x20\x09-\x0D]+', ' ', 'g'), '[0-9]+', '0', 'g'), ' ')) AS line FROM l),
ln AS (SELECT * FROM nl WHERE line <> ''),
freq AS (SELECT host, line, count(*) AS docs, count(DISTINCT text) AS texts FROM (SELECT DISTINCT host, line, doc_id, text FROM ln) GROUP BY host, line),
hosts AS (SELECT host, count(*) AS all_docs FROM (SELECT DISTINCT host, doc_id, text FROM d) GROUP BY host),
boiler AS (SELECT f.host, f.line FROM freq f JOIN hosts h ON f.host = h.host WHERE f.texts >= 10 AND f.docs > 10 AND f.docs > least(10000, h.all_docs * 0.1)),
lost AS (SELECT doc_id, sum(len(string_split(ln.line, ' '))) AS n FROM ln JOIN boiler b ON ln.host = b.host AND ln.line = b.line GROUP BY doc_id),
m AS (SELECT w.doc_id, len(words) AS n_words,
        length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
        length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
        coalesce(lw.dup, 0) AS n_dup_lines, coalesce(rep.n_repeat, 0) AS n_repeat_words, coalesce(lost.n, 0) AS lost
      FROM w LEFT JOIN rep ON w.doc_id = rep.doc_id LEFT JOIN lw ON w.doc_id = lw.doc_id LEFT JOIN lost ON w.doc_id = lost.doc_id)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
  CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND NOT (n_words - lost < n_words * 0.3) AS kept,
  CAST(lost AS BIGINT) AS n_boilerplate_words
FROM m
"""
