"""Repeated rows, null ids, clashing extra columns, long texts and ties of the operators that other files do not cover."""

from __future__ import annotations

import hashlib
import time
import weakref

import pytest
from pyspark.sql import functions as F

from evograph.llm import chat_format as C
from evograph.llm import embedding_dedup as E
from evograph.llm import language_id as L
from evograph.llm import minhash_dedup as M
from evograph.llm import packing as K
from evograph.llm import piece_codec as P
from evograph.llm import quality_model as Q
from evograph.llm import quality_rules as R
from evograph.llm.common import components, slices

CLASH = ("print", "n", "root", "deal", "key", "ids", "score", "kept", "length", "words", "host", "line", "class", "size")


@pytest.fixture(scope="module")
def odd(spark):
    long = "word another third " * 40_000
    rows = [(1, "one two three four five six", "en", "a", 1), (1, "one two three four five six", "en", "a", 1), (1, "other text of the same id here", None, None, None), (None, "no id at all, but words", "en", "a", 3), (5, long, "en", "a", len(long)), (6, None, None, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumns({c: F.lit("x") for c in CLASH}), long


def test_pieces(odd):
    import sentencepiece

    df, long = odd
    lib = sentencepiece.SentencePieceProcessor(model_file=P.model_path())
    got = P.codec_digest(df).collect()
    assert len(got) == 6 and len({r["ids_sha256"] for r in got if r["doc_id"] == 1}) == 2
    ids = lib.encode(long) + [2]
    assert next(r for r in got if r["doc_id"] == 5)["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()


def test_language(odd, spark):
    df, _ = odd
    m = L.fit(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    got = L.identify(df, m).collect()
    assert len(got) == 6 and {r["lang_pred"] for r in got if r["doc_id"] == 6} == {"und"}
    assert all(0 <= r["score"] <= 1 for r in got)


def test_near_duplicates(odd):
    df, _ = odd
    got = {r["doc_id"]: (r["class_id"], r["kept"]) for r in M.near_duplicates(df).collect()}
    assert got == {1: (1, True), None: (None, True), 5: (5, True), 6: (6, True)}
    kept = M.keep_one(df)
    assert kept.columns == df.columns and kept.count() == 5  # of the repeated row one stays


def test_packing(odd):
    df, _ = odd
    rows = K.pack(df).collect()
    assert sum(r["piece"] == 0 for r in rows) == 6 and max(r["offset"] + r["length"] for r in rows) <= 4096


def test_rules(odd):
    df, _ = odd
    got = R.rules(df).collect()
    assert len(got) == 6 and next(r for r in got if r["doc_id"] == 5)["n_words"] == 120_000
    assert R.filter_documents(df).columns == df.columns


def test_quality(odd, spark):
    df, _ = odd
    labels = spark.createDataFrame([(1, 1, 0), (1, 1, 0), (5, 0, 0), (None, 1, 1), (6, None, 0)], "doc_id long, quality int, toxic int")
    m = Q.fit(df, labels)
    got = Q.score(df, m).collect()
    assert len(got) == 6 and len({r["score"] for r in got if r["doc_id"] == 1}) == 2  # equal rows, equal scores
    assert Q.keep_good(df, m).columns == df.columns


def test_vectors(spark):
    rows = [(1, [1.0, 0.0], "x"), (1, [1.0, 0.0], "y"), (None, [1.0, 0.0], "z"), (2, [], "z"), (3, [1.0, 0.0], None)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, class string").withColumns({c: F.lit(1) for c in ("lead", "copies", "print", "root", "links")})
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in E.near_duplicates(df).collect()}
    assert got == {1: (1, 1), 3: (1, 1), 2: (0, 2), None: (0, None)}


def test_chat_lists_without_turns(spark):
    df = spark.createDataFrame([(1, '{"messages": []}'), (2, "{}"), (3, "[]"), (4, None)], "id long, rec string")
    assert C.json_turns(df, "id", "rec").count() == 0


@pytest.mark.parametrize("held", [lambda: K._tokens(K.tokenizer_path()), lambda: P.codec(P.model_path())], ids=["packing", "piece_codec"])
def test_a_worker_gives_back_what_it_kept_for_another_operator(held):
    ref = weakref.ref(held())
    assert held() is ref()  # kept for the operator's own next task
    list(slices(["some other operator's text"]))
    assert ref() is None


def test_rounds_leave_no_shuffle_files(spark):
    """Shuffle files of the rounds of components go when a round is checkpointed, not when the driver collects garbage."""

    def files() -> int:
        found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return sum(found.apply(k).getName().startswith("shuffle_") for k in range(found.size()))

    before = files()
    links = spark.range(300).selectExpr("id AS a", "id + 1 AS b")
    root = components(links)
    left = files()
    for _ in range(50):  # files are deleted in the background
        if left <= before:
            break
        time.sleep(0.1)
        left = files()
    assert left <= before
    assert {r["root"] for r in root.collect()} == {0} and root.count() == 300
