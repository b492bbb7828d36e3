from __future__ import annotations

from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from tests.llm.test_dedup import probability_jaccard, shingles
from tests.llm.test_native import measures
from tests.llm.test_tokens import check_packing


def test_stages(spark, tmp_path):
    """Every stage over all that its predecessor kept; kept rows obey each stage's rule."""
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    seen = [{r["doc_id"]: r["text"] for r in docs.collect()}]
    df = docs
    for name, stage in pipeline.STAGES:
        out = stage(spark, df, d)
        if name != pipeline.STAGES[-1][0]:
            assert out.columns == docs.columns
        out.write.parquet(str(tmp_path / name))
        df = spark.read.parquet(str(tmp_path / name))
        if "text" in df.columns:
            seen.append({r["doc_id"]: r["text"] for r in df.collect()})
            assert set(seen[-1]) <= set(seen[-2])
    q, rules, near, cut = seen[1:]
    good = [i for i, y in labels.items() if y == 1]
    assert sum(i in q for i in good) >= 0.97 * len(good)
    assert set(rules) == {i for i, t in q.items() if not measures(t)[-1]} or all(not measures(q[i])[-1] for i in rules)
    s = {i: shingles(t) for i, t in near.items()}
    ids = sorted(s)
    assert not [(i, j) for i in ids for j in ids if j < i and s[i].keys() & s[j].keys() and probability_jaccard(s[i], s[j]) >= 0.8]
    assert set(cut) == set(near)
    n, least = check_packing(df.collect(), cut)
    assert n <= least + 1


def test_run(spark):
    assert pipeline.run(spark, "/root/testdata/sf0.001").count() > 0


def test_edges(spark):
    """Nulls in any column, repeated rows, columns with clashing names, and empty tables pass every stage but the fitted one."""
    text = " ".join(f"w{k}" for k in range(80))
    rows = [(1, text, "en", "a", 5), (1, text, "en", "a", 5), (None, None, None, None, None), (2, "", "en", None, 0), (3, text + " z", None, "a", None), (None, text.upper(), "en", "b", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumns({c: F.lit(9) for c in ("print", "deal", "o0", "v_key", "gone_id", "p1", "n")})
    for name, stage in pipeline.STAGES[1:-1]:
        for x in (df, df.where("doc_id = 77")):
            out = stage(spark, x, "")
            assert out.columns == df.columns and out.dtypes == df.dtypes
            assert (out.count() > 0) == (x is df)
    packed = pipeline.pack_sequences(spark, df, "").collect()
    assert len(packed) == len(rows) and pipeline.pack_sequences(spark, df.where("doc_id = 77"), "").count() == 0
