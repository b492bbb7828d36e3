"""Execution plans of a window: waves by level, chains, and a queue for p workers."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evograph.windows.fixed import members


def levels_of(pos: list[int], deps: dict[int, list[int]]) -> dict[int, int]:
    """Level of each event: one more than the highest level it waits for."""
    out: dict[int, int] = {}
    for p in sorted(pos):
        out[p] = 1 + max((out[q] for q in deps.get(p, ())), default=0)
    return out


def _rows(deps: DataFrame, ev: DataFrame, win: DataFrame, cost: str | None = None) -> DataFrame:
    m = members(ev, win)
    if cost:
        m = m.join(ev.select("pos", F.col(cost).cast("double").alias("cost")), "pos")
    else:
        m = m.withColumn("cost", F.lit(1.0))
    d = deps.where(F.col("earlier_pos") >= 0).groupBy("window_id", F.col("later_pos").alias("pos")).agg(F.collect_list("earlier_pos").alias("waits"))
    return m.join(d, ["window_id", "pos"], "left")


def _deps_of(pdf: pd.DataFrame) -> dict[int, list[int]]:
    return {int(p): [int(x) for x in w] for p, w in zip(pdf["pos"], pdf["waits"]) if w is not None}


def waves(deps: DataFrame, ev: DataFrame, win: DataFrame) -> DataFrame:
    """``window_id, pos, level``: events of one level may run together."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        lv = levels_of([int(p) for p in pdf["pos"]], _deps_of(pdf))
        pos = sorted(lv)
        return pd.DataFrame({"window_id": pdf["window_id"].iloc[0], "pos": pos, "level": [lv[p] for p in pos]})

    return _rows(deps, ev, win).groupBy("window_id").applyInPandas(run, "window_id long, pos long, level long")


def queue_of(pos: list[int], deps: dict[int, list[int]], cost: dict[int, float], workers: int) -> list[tuple[int, float, float, int]]:
    """(pos, start, finish, worker): ready events by position, the free worker with the least id takes the next."""
    left = {p: len(set(deps.get(p, ()))) for p in pos}
    after: dict[int, list[int]] = {}
    for p in pos:
        for q in set(deps.get(p, ())):
            after.setdefault(q, []).append(p)
    ready = [p for p in sorted(pos) if left[p] == 0]
    heapq.heapify(ready)
    free, busy, now, out = list(range(workers)), [], 0.0, []
    while ready or busy:
        while ready and free:
            p, w = heapq.heappop(ready), heapq.heappop(free)
            out.append((p, now, now + cost[p], w))
            heapq.heappush(busy, (now + cost[p], p, w))
        now = busy[0][0]
        while busy and busy[0][0] == now:
            _, p, w = heapq.heappop(busy)
            heapq.heappush(free, w)
            for q in after.get(p, ()):
                left[q] -= 1
                if left[q] == 0:
                    heapq.heappush(ready, q)
    return out


def list_schedule(deps: DataFrame, ev: DataFrame, win: DataFrame, workers: int = 4, cost: str | None = None) -> DataFrame:
    """``window_id, pos, start, finish, worker`` of the queue plan."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pos = [int(p) for p in pdf["pos"]]
        rows = queue_of(pos, _deps_of(pdf), dict(zip(pos, pdf["cost"].astype(float))), workers)
        out = pd.DataFrame(rows, columns=["pos", "start", "finish", "worker"])
        out.insert(0, "window_id", pdf["window_id"].iloc[0])
        return out

    return _rows(deps, ev, win, cost).groupBy("window_id").applyInPandas(run, "window_id long, pos long, start double, finish double, worker long")


def chain_plan(chains: DataFrame) -> DataFrame:
    """``window_id, chain_id, n, first_pos, last_pos``: one task per chain, its events in order."""
    return chains.groupBy("window_id", "chain_id").agg(F.count("*").alias("n"), F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"))


def concurrent_pairs(closed: DataFrame, ev: DataFrame, win: DataFrame) -> DataFrame:
    """``window_id, n_pairs, n_ordered, n_free``: pairs of a window, and those that may run together."""
    m = members(ev, win).groupBy("window_id").agg(F.count("*").alias("n"))
    o = closed.groupBy("window_id").agg(F.count("*").alias("n_ordered"))
    pairs = (F.col("n") * (F.col("n") - 1) / 2).cast("long")
    ordered = F.coalesce("n_ordered", F.lit(0))
    return m.join(o, "window_id", "left").select("window_id", pairs.alias("n_pairs"), ordered.alias("n_ordered"), (pairs - ordered).alias("n_free"))
