from __future__ import annotations

import hashlib
import random
import zlib

import numpy as np
import pytest

from evograph.llm import packing as K
from evograph.llm import piece_codec as P

ODD = ["", " ", "  a", "▁x", "a▁b", "ﬁ é", "a\tb\nc", "中文😀", "\x00a", "<s> </s>", "<0x41>", "½ Ⅷ  x", "a" * 1500, "ab" * 700 + " " * 300, "don't It's we'LL", "ΑΣ Σ ΑΣΑ", "İstanbul", "x\x1cy", "a\x85b", "é É", "<|endoftext|>z", "²a 3b_c"]


def texts(n=300, seed=0):
    r = random.Random(seed)
    return ODD + ["".join(r.choice("abcdeÀéxΣσ'sI  \t\n<>▁の😀thing0123.,!") for _ in range(r.randrange(60))) for _ in range(n)]


@pytest.fixture(scope="module")
def piece():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=P.model_path())


def test_codec_is_the_library(piece):
    c = P.codec(P.model_path())
    for t in texts():
        ids = piece.encode(t) + [2]
        assert c.encode(t) == ids and c.decode(ids) == piece.decode(ids)
    r = random.Random(1)
    for _ in range(300):
        ids = [r.choice([r.randrange(32000), r.randrange(3, 259)]) for _ in range(7)]
        assert c.decode(ids) == piece.decode(ids)


def test_codec_queries(docs_of, empty, piece):
    ts = [*texts(50), None]
    rows = {r["doc_id"]: r for r in P.codec_digest(docs_of(ts)).collect()}
    for k, t in enumerate(ts):
        ids = (piece.encode(t) if t else []) + [2]
        assert rows[k]["n_tokens"] == len(ids)
        assert rows[k]["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert rows[k]["decoded_sha256"] == hashlib.sha256(piece.decode(ids).encode()).hexdigest()
    full = {r["doc_id"]: r for r in P.encode_documents(docs_of(ts)).collect()}
    assert full[0]["ids"] == [2] and full[2]["decoded"] == "  a"
    assert P.codec_digest(empty).count() == 0


def test_word_table_turns_over(piece, monkeypatch):
    monkeypatch.setattr(P, "TABLE_WORDS", 20)
    c = P.PieceCodec(P.model_path())
    for k in range(5):
        n, _, _ = c.digest([f"some words {j} of round {k}" for j in range(30)])
        assert n == [len(piece.encode(f"some words {j} of round {k}")) + 1 for j in range(30)]


def test_word_tokens_are_the_library():
    from tokenizers import Tokenizer

    tok, w, ts = Tokenizer.from_file(K.tokenizer_path()), K.WordTokens(K.tokenizer_path()), texts()
    for t, ids in zip(ts, w.ids(ts)):
        assert np.frombuffer(ids, "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids


def check_packing(rows, texts_by_id):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(K.tokenizer_path())
    got = {}
    for r in rows:
        got.setdefault(r["doc_id"], []).append(r)
    total = 0
    for k, t in texts_by_id.items():
        ids = tok.encode(t or "", add_special_tokens=False).ids + [1]
        total += len(ids)
        parts = sorted(got[k], key=lambda r: r["piece"])
        assert [p["start"] for p in parts] == list(range(0, len(ids), 4096))
        for p in parts:
            chunk = ids[p["start"] : p["start"] + 4096]
            assert p["length"] == len(chunk) and p["ids_crc32"] == zlib.crc32(np.array(chunk, "<u4").tobytes())
    seqs = {}
    for r in rows:
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for s in seqs.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        assert at <= 4096
    return len(seqs), -(-total // 4096)


def test_packing(docs_of, empty):
    r = random.Random(2)
    ts = [" ".join(r.choice(["the", "cat", "sat", "xyzzy"]) for _ in range(r.choice([0, 3, 40, 400, 1500, 9000]))) for _ in range(150)] + [None, "", "one"] + ["copy of it " * 30] * 40
    n, least = check_packing(K.pack(docs_of(ts)).collect(), dict(enumerate(ts)))
    assert n <= least * 1.08  # pieces of over half a sequence leave gaps that nothing fills
    assert K.pack(empty).count() == 0


def plan_histograms():
    r = np.random.default_rng(0)
    yield {4096: 7}
    yield {1: 3}
    yield {2049: 5}
    yield {3000: 9, 1095: 20}
    yield {int(k): int(n) for k, n in zip(r.choice(4096, 300, replace=False) + 1, r.integers(1, 40, 300))}
    for n in (200, 3000):  # like documents: mostly short, few of any one length
        x = np.minimum(4096, np.exp(r.normal(6, 1.2, n)).astype(int) + 2)
        yield dict(zip(*(v.tolist() for v in np.unique(x, return_counts=True))))


def test_plan_places_every_piece():
    for hist in plan_histograms():
        p = K.make_plan(hist)
        got = {}
        for n, items in p.groups:
            assert n > 0 and sum(a * b for a, b in items) <= 4096
            for a, b in items:
                got[a] = got.get(a, 0) + n * b
        assert got == hist and p.sequences >= p.lp_bound - 1e-6
        plain = sum(n for n, _ in K.best_fit(dict(hist), 4096))
        assert p.sequences <= plain
        assert p.sequences == p.lp_sequences + p.priced_sequences + p.best_fit_sequences
    assert K.make_plan({2049: 5}).sequences == 5


def test_plan_is_the_programs():
    """The columns cover every length, near the bound, and best fit is for the last few sequences only."""
    for hist in list(plan_histograms())[-2:]:
        lengths = np.array(sorted(hist))
        amount, bound = K.solve_lp(lengths, np.array([hist[k] for k in lengths.tolist()], float), 4096)
        got = dict.fromkeys(hist, 0.0)
        for items, x in amount.items():
            assert sum(a * b for a, b in items) <= 4096
            for a, b in items:
                got[a] += b * x
        assert all(got[k] >= hist[k] - 1e-6 for k in hist)
        assert sum(amount.values()) <= 1.1 * bound
        p = K.make_plan(hist)
        assert p.best_fit_sequences <= 0.05 * p.sequences + 1 and p.sequences <= 1.01 * p.lp_bound + 1
