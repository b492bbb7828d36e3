from __future__ import annotations

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from evograph.llm import embedding_dedup as E
from evograph.llm import minhash_dedup as M
from evograph.llm.common import byte_words, components, forest


def roots(pairs, ids):
    par = {i: i for i in ids}

    def find(x):
        while par[x] != x:
            x = par[x]
        return x

    for a, b in pairs:
        p, q = find(a), find(b)
        par[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}


def test_components(spark):
    r = random.Random(0)
    pairs = [(r.randrange(200), r.randrange(200)) for _ in range(150)] + [(k, k + 1) for k in range(300, 360)]
    want = roots(pairs, {x for p in pairs for x in p})
    got = {x["id"]: x["root"] for x in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert all(got.get(i, i) == want[i] for i in want)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
    assert len(forest(np.array([0, 1, 0]), np.array([1, 2, 2]), 3)) == 2


def shingles(t):
    w = (t or "").split()
    return Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else Counter()


def probability_jaccard(x, y):
    """By the definition, element by element."""
    return sum(1 / sum(max(x[e] / x[d], y[e] / y[d]) for e in x.keys() | y.keys()) for d in x.keys() & y.keys())


def thue_morse(n):
    s = "a"
    while len(s) < n:
        s += s.translate(str.maketrans("ab", "ba"))
    return s


def test_word_hash_has_no_algebra():
    """Complementary Thue-Morse words collide under every polynomial modulo a power of two."""
    x = thue_morse(4096)
    ws = [x, x.translate(str.maketrans("ab", "ba")), "a" * 8, "a" * 9, "a" * 16, "a" * 8 + "b" * 8, "b" * 8 + "a" * 8, "abcdefgh", "abcdefgh\0"]
    s, e, h = byte_words(" ".join([*ws, *ws]).encode())
    assert [y - x for x, y in zip(s, e)] == [len(w) for w in ws] * 2
    assert len(set(h.tolist())) == len(ws) and (h[: len(ws)] == h[len(ws) :]).all()


def near_texts(seed=0):
    r = random.Random(seed)
    word = lambda: f"w{r.randrange(4000)}"
    out = []
    for _ in range(12):
        base = [word() for _ in range(r.choice([6, 60, 150]))]
        if r.random() < 0.4:  # passages that repeat give weights over one
            base += base[: len(base) // 2] * r.randrange(1, 4)
        out.append(" ".join(base))
        for _ in range(r.choice([0, 2, 60])):
            w = list(base)
            for _ in range(r.randrange(4)):
                w[r.randrange(len(w))] = word()
            out.append(" ".join(w))
    return out + [None, "", "a b", "a b", "a b c", " \n"]


@pytest.mark.parametrize("few,weighting", [(2, "tf"), (16, "tf"), (2, "set")])
def test_near_duplicates_equal_brute_force(docs_of, monkeypatch, few, weighting):
    monkeypatch.setattr(M, "FEW", few)
    monkeypatch.setattr(M, "BLOCK_SHINGLES", 2000)
    ts = near_texts()
    s = [shingles(t) if weighting == "tf" else Counter(set(shingles(t))) for t in ts]
    pairs = [(i, j) for i in range(len(ts)) for j in range(i) if len(s[i].keys() & s[j].keys()) > 0 and probability_jaccard(s[i], s[j]) >= 0.8 - 1e-12]
    want = roots(pairs, range(len(ts)))
    got = {r["doc_id"]: (r["class_id"], r["kept"]) for r in M.near_duplicates(docs_of(ts), weighting=weighting).collect()}
    assert {k: v[0] for k, v in got.items()} == want
    assert all(kept == (want[k] == k) for k, (_, kept) in got.items())
    if weighting == "tf":
        assert M.keep_one(docs_of(ts)).count() == len(set(want.values()))


def test_exact_similarity_and_blocks():
    r = np.random.default_rng(3)
    sets = []
    for _ in range(30):
        k = np.sort(r.choice(60, r.integers(1, 40), replace=False)).astype(np.uint64)
        sets.append((k, r.integers(1, 5, len(k)).astype(float)))
    d = [dict(zip(k.tolist(), w)) for k, w in sets]
    d = [Counter(x) for x in d]
    near = []
    for i in range(30):
        for j in range(30):
            want = probability_jaccard(d[i], d[j])
            assert abs(M.probability_jaccard(*sets[i], *sets[j]) - want) < 1e-9
            near += [(i, j)] if want >= 0.3 and i != j else []
    ids = list(range(30))
    found = M.block_links((ids, ids, sets), (ids, ids, sets), 0.3)
    assert set(found) <= set(near) and roots(found, ids) == roots(near, ids)


def test_sketch_estimates():
    """Agreement of slots estimates the (weighted) probability Jaccard similarity."""
    r = np.random.default_rng(0)
    a, b = np.arange(1, 101).astype(np.uint64), np.arange(21, 121).astype(np.uint64)
    s = np.concatenate([a, b]) * np.uint64(0x9E3779B97F4A7C15)
    doc = np.repeat([0, 1], 100)
    for weighted in (False, True):
        w = np.ones(200) if not weighted else np.concatenate([r.integers(1, 5, 100), r.integers(1, 5, 100)]).astype(float)
        sig = M.sketch(doc, s, w, 2, 4000)
        x, y = dict(zip(s[:100].tolist(), w[:100])), dict(zip(s[100:].tolist(), w[100:]))
        keys = set(x) | set(y)
        jp = sum(1 / sum(max(x.get(t, 0) / x[d], y.get(t, 0) / y[d]) for t in keys) for d in set(x) & set(y))
        assert abs((sig[0] == sig[1]).mean() - jp) < 0.03


def test_weighted_and_edges(spark, docs_of, empty):
    ts = ["a b c d e f " * 4, "a b c d e f " * 4, "g h i j k l"]
    got = {r["doc_id"]: r["class_id"] for r in M.near_duplicates(docs_of(ts), weighting="tf").collect()}
    assert got == {0: 0, 1: 0, 2: 2}
    assert M.near_duplicates(empty).count() == 0 and M.keep_one(empty).count() == 0
    df = docs_of(ts).withColumn("rep", F.lit(1)).withColumn("gone_id", F.lit(2))
    assert M.keep_one(df).columns == df.columns
    null = spark.createDataFrame([(None, "x y z a b c"), (3, "x y z a b c")], "doc_id long, text string")
    assert {(r["doc_id"], r["kept"]) for r in M.near_duplicates(null).collect()} == {(None, True), (3, True)}


def test_vectors_equal_brute_force(spark):
    r = np.random.default_rng(1)
    base = r.normal(size=(40, 24))
    v = np.concatenate([base, base[:15] + 0.12 * r.normal(size=(15, 24)), base[:5], np.repeat(base[7:8], 30, 0) + 0.15 * r.normal(size=(30, 24)), 3 * base[:2]])
    rows = [(i, x.tolist()) for i, x in enumerate(v)]
    rows += [(900, None), (901, [0.0] * 24), (902, [float("nan")] + [1.0] * 23), (903, [float("inf")] * 24), (904, [1.0, 2.0]), (905, [None] + [1.0] * 23)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    u = v / np.linalg.norm(v, axis=1, keepdims=True)
    c = u @ u.T
    pairs = [(i, j) for i in range(len(v)) for j in range(i) if c[i, j] >= 0.95]
    want = roots(pairs, [x for x, _ in rows])
    links = {i: sum(1 for j in range(len(v)) if j != i and c[i, j] >= 0.95) for i in range(len(v))}
    for tile, group in ((8, 20), (1024, 16384)):
        got = {x["vec_id"]: x for x in E.near_duplicates(df, tile_rows=tile, group_rows=group).collect()}
        assert {k: x["component_id"] for k, x in got.items()} == want
        assert all(got[i]["n_links"] == links.get(i, 0) for i in want)
    assert E.near_duplicates(df.where("vec_id < 0")).count() == 0
    mixed = [(1, [1.0, 1.0], "a"), (2, [2.0, 2.0], "b"), (3, [1.0, 0.0, 0.0], "c"), (4, [1.0, 0.01, 0.0], "d"), (5, [1.0, 0.0], "e"), (1, [1.0, 1.0], "f"), (6, [0.0, 1.0, 0.0], None)]
    got = {x["vec_id"]: (x["n_links"], x["component_id"]) for x in E.near_duplicates(spark.createDataFrame(mixed, "vec_id long, embedding array<float>, lead string")).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (1, 3), 4: (1, 3), 5: (0, 5), 6: (0, 6)}  # every length is compared
    # one id with two vectors has the links of both, and passes them on to neither's copies
    two = spark.createDataFrame([(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [3.0, 0.0]), (3, [0.1, 3.0]), (4, [0.11, 3.0])], "vec_id long, embedding array<double>")
    got = {x["vec_id"]: (x["n_links"], x["component_id"]) for x in E.near_duplicates(two).collect()}
    assert got == {1: (3, 1), 2: (1, 1), 3: (2, 1), 4: (2, 1)}
    assert E.near_duplicates(df.where("vec_id = 900")).first()["kept"]


def test_size_estimates_do_not_grow_with_rounds(spark):
    """Each self-join squares the estimate that a checkpoint hands on; plans on the driver then hold megabytes of digits."""
    root = components(spark.createDataFrame([(k, k + 1) for k in range(40)], "a long, b long"))
    size = root._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    assert size.bit_length() <= 64
    assert {x["root"] for x in root.collect()} == {0}
