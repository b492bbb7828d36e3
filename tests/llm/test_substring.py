from __future__ import annotations

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from evograph.llm import substring_dedup as S

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(texts, window):
    words = [WORD.findall(t or "") for t in texts]
    count = Counter(tuple(w[i : i + window]) for w in words for i in range(len(w) - window + 1))
    out = []
    for w in words:
        gone = set()
        for i in range(len(w) - window + 1):
            if count[tuple(w[i : i + window])] > 1:
                gone |= set(range(i, i + window))
        kept = [x for k, x in enumerate(w) if k not in gone]
        out.append((len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return out


def corpus(seed):
    r = random.Random(seed)
    vocab = [f"w{k}é" for k in range(40)]
    line = lambda n: [r.choice(vocab) for _ in range(n)]
    shared = [line(n) for n in (34, 35, 36, 60, 90)]
    texts = []
    for _ in range(30):
        w = line(r.randrange(0, 80))
        for _ in range(r.randrange(3)):
            at = r.randrange(len(w) + 1)
            w[at:at] = r.choice(shared)
        texts.append(r.choice([" ", "\n", "\t "]).join(w))
    texts += ["a " * 200, "a b " * 90, "a " * 34, "a " * 35, "a " * 36, "x y z " * 30, None, "", " \n ", texts[0], "solo"]
    texts.append(" ".join(line(3000) + shared[3] + line(500) + shared[3]))
    return texts


@pytest.mark.parametrize("seed", range(2))
def test_equals_brute_force(docs_of, seed):
    texts = corpus(seed)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in S.dedup_digest(docs_of(texts)).collect()}
    assert [got[k] for k in range(len(texts))] == brute(texts, S.WINDOW)


def test_equal_windows_have_equal_tops(monkeypatch):
    """Equal windows in different surroundings have one top in one place, however the text is stretched."""
    r = np.random.default_rng(0)
    longest = 0
    for vocab in (1, 2, 3, 6, 1000):
        for _ in range(60):
            win = r.integers(0, vocab, S.WINDOW)
            found = []
            for stretch in (1 << 20, 7):
                monkeypatch.setattr(S, "STRETCH", stretch)
                before, after = r.integers(0, vocab, r.integers(0, 20)), r.integers(0, vocab, r.integers(0, 20))
                w = np.concatenate([before, win, after])
                at, top, place = S.tops(S.mix(w.astype(np.uint64) + np.uint64(1)), np.array([0, 0, len(w), len(w)]))
                assert at.tolist() == list(range(len(w) - S.WINDOW + 1))
                k = len(before)
                first, size = (place[k] >> 16) - k, place[k] & 0xFFFF
                assert 0 <= first and first + size <= S.WINDOW
                found.append((int(top[k]), int(first), int(size)))
            assert found[0] == found[1]
            longest = max(longest, found[0][2])
    assert longest >= 10


def test_names_have_no_longest_length():
    h = S.mix(np.full(500, 7, dtype=np.uint64))
    name, start, _ = S.name_runs(h, np.arange(501), np.zeros(500, dtype=np.int64))
    assert len(name) == 1 and start.tolist() == [0, 500]
    r = np.random.default_rng(1)
    h = S.mix(r.integers(0, 50, 4000).astype(np.uint64))
    name, start, doc = h, np.arange(4001), np.zeros(4000, dtype=np.int64)
    for k in range(40):
        name, start, _ = S.name_runs(name, start, doc)
        name, start, _, _ = S.name_pairs(name, start, doc, k)
    assert len(name) < 4 and start[-1] == 4000


def test_stage_keeps_columns(docs_of):
    texts = corpus(3)
    df = docs_of(texts).withColumn("u_id", F.lit(1)).withColumn("tag", F.lit("x"))
    out = S.remove_repeats(df)
    assert out.columns == df.columns and out.dtypes == df.dtypes
    want = brute(texts, S.WINDOW)
    for r in out.collect():
        words = WORD.findall(r["text"] or "")
        assert hashlib.sha256(" ".join(words).encode()).hexdigest() == want[r["doc_id"]][2]
        assert r["text"] == texts[r["doc_id"]] if want[r["doc_id"]][1] == 0 else r["n_chars"] == len(r["text"])


def test_edges(spark, docs_of, empty):
    assert S.dedup_digest(empty).count() == 0 and S.remove_repeats(empty).count() == 0
    long = " ".join(f"t{k}" for k in range(60))
    same_id = spark.createDataFrame([(1, long), (1, long), (None, long + " z"), (2, "short")], "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["n_words"], r["n_removed"]) for r in S.dedup_digest(same_id).collect())
    assert got == [("1", 60, 60), ("1", 60, 60), ("2", 1, 0), ("None", 61, 60)]
