"""Cases that smaller jobs than the whole one got wrong."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import functions as F

from evograph.llm import html_extract as H
from evograph.llm import language_id as L
from evograph.llm import minhash_dedup as M
from evograph.llm import quality_model as Q


def test_a_rare_class_is_drawn(spark, docs_of):
    r = random.Random(0)
    texts = [" ".join(r.choice("the of and sun sea hill road tree".split()) for _ in range(30)) for _ in range(400)]
    bad = (100, 201, 302)
    for k in bad:
        texts[k] = "#### $$$$ %%%% " * 20
    labels = spark.createDataFrame([(k, int(k not in bad), 0) for k in range(400)], "doc_id long, quality int, toxic int")
    m = Q.fit(docs_of(texts), labels, labelled=20)
    assert isinstance(m, Q.CoModel)
    kept = {x["doc_id"]: x["kept"] for x in Q.score(docs_of(texts), m).collect()}
    assert not any(kept[k] for k in bad) and sum(kept.values()) >= 390


def test_every_unlabelled_document_is_a_candidate(spark, docs_of):
    """The surest of all rows, whatever the size of the input; rows seen alike count once."""
    r = random.Random(1)
    texts = [" ".join(r.choice("ab cd ef gh #x 12".split()) for _ in range(r.randrange(3, 40))) for _ in range(600)] + ["zz zz zz zz"] * 5
    docs = docs_of(texts).repartition(7)
    rng = np.random.default_rng(2)
    content, record = Q.views(texts, ["s"] * len(texts), ["en"] * len(texts), [len(t) for t in texts])
    models = [rng.normal(size=content.shape[1] + 1) * 3, rng.normal(size=record.shape[1] + 1)]
    known = set(range(0, 600, 5))
    got = Q.sure_rows(docs, models, known, set(), 20)
    at = {x["print"]: texts[x["doc_id"]] for x in docs.select("doc_id", Q._print().alias("print")).collect()}
    free = {t: k for k, t in enumerate(texts) if k not in known}
    for me, x in ((0, content), (1, record)):
        z = x @ models[me][:-1] + models[me][-1]
        for kind, sure in ((2 * me, z), (2 * me + 1, -z)):
            want = sorted((float(sure[k]) for k in free.values() if sure[k] > 1), reverse=True)[:20]
            assert np.allclose([v for v, _ in got[kind]], want)
            assert len({at[p] for _, p in got[kind]}) == len(want)


def test_every_language_is_learned(spark):
    """More than 64 languages, each with a word of its own."""
    rows = [(100 * k + i, f"word{k}x{k}y{k} " * 5, f"q{k:02d}") for k in range(70) for i in range(4 if k < 66 else 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").where(~L.held_out(F.col("doc_id")))
    m = L.fit(docs, dims=256)
    assert {x for v in m.families.values() for x in v} == {x["lang"] for x in docs.select("lang").distinct().collect()} and len(m.families) > 64


def test_rows_of_one_id(spark):
    """Repeated rows stay once; every text of an id takes part, and no text goes without a copy that stays."""
    r = random.Random(3)
    text = lambda: " ".join(f"w{r.randrange(9000)}" for _ in range(40))
    a, b, c, d = text(), text(), text(), text()
    rows = [(1, a), (1, a), (1, a), (2, a), (5, b), (5, c), (3, b + " end"), (7, c + " end"), (9, d), (9, None), (9, None), (None, d), (None, d)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("print", F.lit(0)).repartition(5)
    got = {x["doc_id"]: x["class_id"] for x in M.near_duplicates(docs).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 5: 3, 7: 3, 9: 9, None: None}
    kept = M.keep_one(docs)
    assert kept.columns == docs.columns
    want = [(1, a), (3, b + " end"), (5, c), (9, d), (9, None), (None, d), (None, d)]
    assert sorted(((x["doc_id"], x["text"]) for x in kept.collect()), key=str) == sorted(want, key=str)


def test_text_after_drawings_stays():
    texts = lambda page: [t for t, *_ in H.blocks(page)]
    assert texts("<p>One <svg class=i/> two.</p><p>Three.</p><svg><path d='M0'/></svg><p>Four.</p>") == ["One two.", "Three.", "Four."]
    assert texts("<p>One <svg><path d=''> two.</p><p>Three.</p>") == ["One two.", "Three."]
    assert texts("<div><svg><g><path><p>Three.</p><noscript><p>Four.</p></div><canvas/><p>Five.</p>") == ["Three.", "Four.", "Five."]
    assert texts("<p>Let <math><mi>x</mi><mo>=</mo><mn>1</mn></math> be.</p><math/><object/><p>Next.</p>") == ["Let x = 1 be.", "Next."]
    assert texts("<object data=a><p>Fallback.</p></object><select><option>A<option>B</select><p>End.</p>") == ["Fallback.", "A", "B", "End."]
    assert texts("<svg><foreignObject><p>In a drawing.</p></foreignObject></svg><p>After.</p>") == ["In a drawing.", "After."]
    assert texts("<script src=a /><p>Stays.</p><style>p{}</style><script>x<p>no</script><iframe/>End.") == ["Stays.", "End."]
    assert H.main_text("<article><h1>Title of it<svg/></h1><p>A first sentence of the article, with words.</p><p>A second one follows here.</p></article>", H.model()).endswith("A second one follows here.")
