"""Windows against brute force, and the worked examples."""

from __future__ import annotations

import random

import numpy as np
import pytest

from evograph.streaming.online import WindowFormer
from evograph.train.engine import Events
from evograph.train.spark_fit import local_windows
from evograph.windows import adaptive, fixed
from evograph.workloads.experiments import NINE_MIXED, tiny


def brute_length(pairs, i, low, high):
    """Grow by sets, one event at a time."""
    n = len(pairs)
    end, seen = min(n, i + low), set()
    for u, v in pairs[i:end]:
        seen |= {u, v} - {None}
    while end < min(n, i + high) and seen & set(pairs[end]):
        seen |= set(pairs[end]) - {None}
        end += 1
    return end - i


def random_pairs(seed, n=80, nodes=12):
    r = random.Random(seed)
    return [(r.randrange(nodes), r.randrange(nodes)) for _ in range(n)]


@pytest.mark.parametrize("low,high,want", [(2, 6, [3, 2, 6, 6, 5, 4, 3, 2, 1]), (3, 6, [3, 6, 6, 6, 5, 4, 3, 2, 1]), (4, 6, [6, 6, 6, 6, 5, 4, 3, 2, 1]), (4, 9, [9, 8, 7, 6, 5, 4, 3, 2, 1])])
def test_worked_lengths(spark, low, high, want):
    got = adaptive.adaptive_length(tiny(spark, NINE_MIXED), low, high).orderBy("start_pos").collect()
    assert [r["size"] for r in got] == want


@pytest.mark.parametrize("seed", range(3))
def test_length_equals_growth(spark, seed):
    pairs = random_pairs(seed)
    got = adaptive.adaptive_length(tiny(spark, pairs), 4, 11, bucket=16).orderBy("start_pos").collect()
    assert [r["size"] for r in got] == [brute_length(pairs, i, 4, 11) for i in range(len(pairs))]


@pytest.mark.parametrize("bucket", [16, 64, 1 << 16])
def test_chain_over_buckets(spark, bucket):
    """The jump tables give the chain that walking gives, whatever the buckets are."""
    pairs = random_pairs(5, 200, 20)
    want, a = [], 0
    while True:
        size = brute_length(pairs, a, 5, 14)
        want.append((a, a + size))
        if a + size >= len(pairs):
            break
        a += max(1, int(0.2 * size + 1e-9))
    got = adaptive.adaptive(tiny(spark, pairs), 5, 14, 0.2, bucket=bucket).orderBy("window_id").collect()
    assert [(r["start_pos"], r["end_pos"]) for r in got] == want
    ev = Events(np.arange(200), np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs]), np.arange(200.0), ["edge_add"] * 200, np.ones(200))
    assert local_windows(ev, "adaptive", low=5, high=14) == want


def test_equal_limits_are_fixed(spark):
    ev = tiny(spark, random_pairs(1, 50))
    a = adaptive.adaptive(ev, 10, 10, 0.2).select("start_pos", "end_pos").collect()
    b = fixed.fixed(spark, 50, 10, 2).select("start_pos", "end_pos").collect()
    assert sorted(a) == sorted(b)


def test_stride_of_size_is_batches(spark):
    a = fixed.fixed(spark, 47, 10, 10).select("start_pos", "end_pos").collect()
    assert sorted(a) == sorted(fixed.batches(spark, 47, 10).select("start_pos", "end_pos").collect())


@pytest.mark.parametrize("n,tail,want", [(0, "stop", 0), (1, "stop", 1), (3, "full", 0), (9, "full", 3), (9, "stop", 4), (9, "shrink", 5)])
def test_tails(spark, n, tail, want):
    assert fixed.fixed(spark, n, 4, 2, tail=tail).count() == want


def test_short_and_empty_streams(spark):
    one = tiny(spark, [(1, 1)])
    assert [tuple(r) for r in adaptive.adaptive(one, 100, 300).collect()] == [(0, 0, 1)]
    assert adaptive.adaptive(one.where("pos < 0"), 100, 300).count() == 0


def test_online_former_equals_batch(spark):
    pairs = random_pairs(9, 300, 25)
    f, got = WindowFormer(5, 14, 0.2), []
    for u, v in pairs:
        got += f.add(u, v)
        f = WindowFormer(5, 14, 0.2, f.dump())  # state survives being written
    want = [tuple(r) for r in adaptive.adaptive(tiny(spark, pairs), 5, 14).orderBy("window_id").collect()]
    assert got == want[: len(got)] and len(want) - len(got) <= 1
    assert len(f.prev) <= 15
