"""Adaptive windows: as long as events keep sharing nodes, between two limits.

An event at position j belongs to a window that starts at i if one of its nodes was touched at
i or later. With ``prev[j]`` the latest earlier position of any of its nodes this is
``prev[j] >= i``, so a window from i ends at the first j in ``[i + low, i + high)`` with
``prev[j] < i``, else at ``i + high``. Lengths of all starts are thus independent: one lag by
node and a bounded look-ahead inside position buckets with a halo. Only the chain of starts is
sequential; every bucket reduces it to a table (entry offset to exit), the tables are walked
on the driver, and every bucket lists its own windows again.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evograph.stream.positions import assign_positions

BUCKET = 65_536


def touches(ev: DataFrame) -> DataFrame:
    """``pos, node_id`` of the distinct nodes of each event; nulls are no nodes."""
    node = F.explode(F.array_distinct(F.filter(F.array("src", "dst"), lambda x: x.isNotNull())))
    return ev.select("pos", node.alias("node_id"))


def previous_touch(ev: DataFrame, reads: DataFrame | None = None) -> DataFrame:
    """``pos, prev``: the latest earlier position at which a node of the event was touched, -1 if none.

    With ``reads`` (pos, node_id) a window grows by subgraph instead of by endpoints: an event
    belongs to it if its node set meets that of an event inside.
    """
    t = reads if reads is not None else touches(ev)
    w = Window.partitionBy("node_id").orderBy("pos")
    p = t.withColumn("prev", F.coalesce(F.lag("pos").over(w), F.lit(-1)))
    return p.groupBy("pos").agg(F.max("prev").alias("prev"))


def _look_ahead(prev: np.ndarray, start: int, n: int, low: int, high: int, upto: int) -> np.ndarray:
    """Window ends for starts ``start .. upto - 1``; ``prev[k]`` belongs to position ``start + k``."""
    m = upto - start
    end = np.minimum(np.arange(start, upto) + high, n)
    open_ = np.ones(m, dtype=bool)
    for step in range(low, high):
        k = np.arange(m) + step
        inside = k < len(prev)
        hit = open_ & inside & (prev[np.minimum(k, len(prev) - 1)] < np.arange(start, upto))
        end[hit] = start + k[hit]
        open_ &= ~hit
        if not open_.any():
            break
    return end


def adaptive_length(ev: DataFrame, low: int = 100, high: int = 300, reads: DataFrame | None = None, bucket: int = BUCKET, prev: DataFrame | None = None) -> DataFrame:
    """``start_pos, size`` of the window from every position; ``prev`` as of ``previous_touch``, exact for the last ``high`` positions."""
    return _per_bucket(ev, low, high, reads, bucket, prev)


def _haloed(ev: DataFrame, high: int, reads: DataFrame | None, bucket: int, prev: DataFrame | None) -> DataFrame:
    """Positions with ``prev``, dealt to their bucket and, near its start, to the one before."""
    p = previous_touch(ev, reads) if prev is None else prev
    own, before = F.col("pos") / bucket, F.greatest(F.lit(0), F.col("pos") - high) / bucket
    home = F.array_distinct(F.array(own.cast("long"), before.cast("long")))
    return p.select(F.explode(home).alias("b"), "pos", "prev")


def _per_bucket(ev: DataFrame, low: int, high: int, reads: DataFrame | None, bucket: int, prev: DataFrame | None) -> DataFrame:
    n = ev.agg(F.max("pos")).first()[0]
    n = 0 if n is None else n + 1

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        b = int(key[0])
        start, upto = b * bucket, min(n, (b + 1) * bucket)
        end = _look_ahead(pdf.sort_values("pos")["prev"].to_numpy(), start, n, low, high, upto)
        return pd.DataFrame({"start_pos": np.arange(start, upto), "size": end - np.arange(start, upto)})

    return _haloed(ev, high, reads, bucket, prev).groupBy("b").applyInPandas(run, "start_pos long, size long")


def _step(size: np.ndarray, ratio: float, stride: int | None) -> np.ndarray:
    return np.full(len(size), stride) if stride is not None else np.maximum(1, np.floor(ratio * size + 1e-9).astype(np.int64))


def adaptive(ev: DataFrame, low: int = 100, high: int = 300, ratio: float = 0.2, stride: int | None = None, tail: str = "stop", reads: DataFrame | None = None, bounds: str = "half_open", bucket: int = BUCKET, prev: DataFrame | None = None) -> DataFrame:
    """``window_id, start_pos, end_pos``: start, length, move by ``ratio`` of the length (or ``stride``), repeat."""
    n = ev.agg(F.max("pos")).first()[0]
    n = 0 if n is None else n + 1
    lengths = adaptive_length(ev, low, high, reads, bucket, prev).withColumn("b", (F.col("start_pos") / bucket).cast("long"))
    reach = high if stride is None else max(high, stride)

    def chain(start: int, upto: int, size: np.ndarray, entry: int) -> tuple[list[int], int]:
        """Starts inside a bucket from an entry, and the first start past it (-1: the stream is done)."""
        nxt = np.arange(start, upto) + _step(size, ratio, stride)
        out, at = [], entry
        while at < upto:
            whole = at + size[at - start] < n
            if tail == "full" and size[at - start] < low:
                return out, -1
            out.append(at)
            if not whole and tail != "shrink":
                return out, -1
            at = int(nxt[at - start])
        return out, at if at < n else -1

    def exits(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        start = int(key[0]) * bucket
        upto = min(n, start + bucket)
        size = pdf.sort_values("start_pos")["size"].to_numpy()
        done, out = {}, []
        for entry in range(start, min(upto, start + reach)):  # paths merge soon; each start is walked once
            path, at = [], entry
            while at < upto and at not in done:
                path.append(at)
                whole = at + size[at - start] < n
                if (tail == "full" and size[at - start] < low) or (not whole and tail != "shrink"):
                    at = -1
                    break
                at = at + int(_step(size[at - start : at - start + 1], ratio, stride)[0])
            last = done.get(at, at if at < n else -1) if at >= 0 else -1
            for p in path:
                done[p] = last
            out.append(last)
        return pd.DataFrame({"b": int(key[0]), "entry": np.arange(start, start + len(out)), "leave": out})

    # at most `reach` small rows per bucket come to the driver, bucket by bucket
    entries, at = [], 0
    tables = lengths.groupBy("b").applyInPandas(exits, "b long, entry long, leave long").orderBy("b", "entry")
    for r in tables.toLocalIterator(prefetchPartitions=True):
        if at >= 0 and r["entry"] == at:
            entries.append((r["b"], at))
            at = r["leave"]
    spark = ev.sparkSession
    entry_df = spark.createDataFrame(entries, "b long, entry long") if entries else spark.createDataFrame([], "b long, entry long")

    def unroll(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        start = int(key[0]) * bucket
        upto = min(n, start + bucket)
        pdf = pdf.sort_values("start_pos")
        size = pdf["size"].to_numpy()
        starts, _ = chain(start, upto, size, int(pdf["entry"].iloc[0]))
        s = np.array(starts, dtype=np.int64)
        return pd.DataFrame({"start_pos": s, "end_pos": s + size[s - start]})

    win = lengths.join(F.broadcast(entry_df), "b").groupBy("b").applyInPandas(unroll, "start_pos long, end_pos long")
    if bounds == "listing":
        win = win.withColumn("end_pos", F.least(F.col("end_pos") + 1, F.lit(n)))
    return assign_positions(win, ["start_pos"], lambda d: d.select(F.col("pos").alias("window_id"), "start_pos", "end_pos"))


def locality_profile(ev: DataFrame, gaps: int = 5) -> DataFrame:
    """``gap, share``: share of events that have a node in common with the event ``gap`` before."""
    t = touches(ev)
    n = ev.count()
    later = t.select("node_id", "pos", F.explode(F.sequence(F.lit(1), F.lit(gaps))).alias("gap")).withColumn("at", F.col("pos") - F.col("gap"))
    hits = later.join(t.select(F.col("node_id"), F.col("pos").alias("at")), ["node_id", "at"]).select("gap", "pos").distinct().groupBy("gap").agg(F.count("*").alias("hits"))
    return hits.select("gap", F.round(F.col("hits") / F.greatest(F.lit(1), F.lit(n) - F.col("gap")), 6).alias("share"))


def locality_coverage(ev: DataFrame, win: DataFrame, gap: int = 5, width: int = 1024) -> DataFrame:
    """How many nearby events that share a node some window has together: pairs, covered, share."""
    t = touches(ev)
    later = t.select("node_id", F.col("pos").alias("j"), F.explode(F.sequence(F.lit(1), F.lit(gap))).alias("g")).withColumn("i", F.col("j") - F.col("g"))
    pairs = later.join(t.select("node_id", F.col("pos").alias("i")), ["node_id", "i"]).select("i", "j").distinct()
    w = win.withColumn("b", F.explode(F.sequence((F.col("start_pos") / width).cast("long"), ((F.col("end_pos") - 1) / width).cast("long"))))
    met = pairs.withColumn("b", (F.col("i") / width).cast("long")).join(w, "b").where((F.col("start_pos") <= F.col("i")) & (F.col("j") < F.col("end_pos")))
    covered = met.select("i", "j").distinct().withColumn("hit", F.lit(1))
    return pairs.join(covered, ["i", "j"], "left").agg(F.count("*").alias("pairs"), F.coalesce(F.sum("hit"), F.lit(0)).alias("covered")).withColumn("share", F.round(F.col("covered") / F.col("pairs"), 6))
