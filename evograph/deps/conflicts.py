"""Dependencies between the events of a window, from what they read and write.

``reads`` and ``writes`` are (pos, node_id). An event depends on an earlier one of its window
if it reads what that one writes. ``reduced`` keeps the last writer of each node only; since
writers read what they write, earlier writers are reached through it. ``stream_index`` finds
last writers once for the whole stream; a window keeps those inside it.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evograph.windows.adaptive import touches
from evograph.windows.fixed import members

ROOT = -1


def _inside(rel: DataFrame, win: DataFrame) -> DataFrame:
    return rel.join(members(rel.select("pos").distinct(), win), "pos")


def direct(reads: DataFrame, writes: DataFrame, win: DataFrame, hazards: str = "raw") -> DataFrame:
    """``window_id, later_pos, earlier_pos``: all conflicting pairs, by an equi-join on the node."""
    r = _inside(reads, win).select("window_id", "node_id", F.col("pos").alias("later_pos"))
    w = _inside(writes, win).select("window_id", "node_id", F.col("pos").alias("earlier_pos"))
    out = r.join(w, ["window_id", "node_id"]).where("earlier_pos < later_pos").select("window_id", "later_pos", "earlier_pos").distinct()
    return out if hazards == "raw" else out.unionByName(anti(reads, writes, win)).distinct()


def anti(reads: DataFrame, writes: DataFrame, win: DataFrame) -> DataFrame:
    """Pairs in which the later event overwrites what the earlier one reads."""
    w = _inside(writes, win).select("window_id", "node_id", F.col("pos").alias("later_pos"))
    r = _inside(reads, win).select("window_id", "node_id", F.col("pos").alias("earlier_pos"))
    return w.join(r, ["window_id", "node_id"]).where("earlier_pos < later_pos").select("window_id", "later_pos", "earlier_pos").distinct()


def stream_index(reads: DataFrame, writes: DataFrame) -> DataFrame:
    """``later_pos, earlier_pos``: for every node an event reads, the last event before that writes it."""
    both = reads.withColumn("w", F.lit(None).cast("long")).select("node_id", "pos", "w").unionByName(writes.select("node_id", "pos", F.col("pos").alias("w")))
    both = both.groupBy("node_id", "pos").agg(F.max("w").alias("w"))
    order = Window.partitionBy("node_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    last = both.withColumn("earlier_pos", F.last("w", ignorenulls=True).over(order))
    # a write without a read reads as well: writers read what they write
    return last.where("earlier_pos IS NOT NULL").select(F.col("pos").alias("later_pos"), "earlier_pos").distinct()


def for_window(index: DataFrame, win: DataFrame) -> DataFrame:
    """Dependencies of each window out of the stream's index."""
    m = members(index.select(F.col("later_pos").alias("pos")).distinct(), win).select("window_id", F.col("pos").alias("later_pos"))
    start = win.select("window_id", "start_pos")
    return index.join(m, "later_pos").join(start, "window_id").where("earlier_pos >= start_pos").select("window_id", "later_pos", "earlier_pos")


def reduced(reads: DataFrame, writes: DataFrame, win: DataFrame) -> DataFrame:
    """Last-writer dependencies of each window."""
    return for_window(stream_index(reads, writes), win)


def _window_rows(ev: DataFrame, spans: DataFrame, win: DataFrame) -> DataFrame:
    """Events of each window, and for some of its nodes the edges that live in it: one table, grouped by window.

    An edge matters to the windows that touch both of its ends. It goes out with the end that
    fewer windows touch, so a hub's edges travel with its neighbours and not with every window.
    """
    is_del = F.col("kind").isin("edge_del", "node_del").cast("int")
    events = members(ev, win).join(ev.select("pos", "src", "dst", is_del.alias("del")), "pos")
    ends = F.explode(F.array_distinct(F.filter(F.array("src", "dst"), lambda x: x.isNotNull())))
    touched = events.select("window_id", ends.alias("node")).distinct()
    n = touched.groupBy("node").agg(F.count("*").alias("n"))
    s = spans.join(n.select(F.col("node").alias("src"), F.col("n").alias("n_src")), "src").join(n.select(F.col("node").alias("dst"), F.col("n").alias("n_dst")), "dst")
    out = F.col("n_src") <= F.col("n_dst")
    edges = s.select(F.when(out, F.col("src")).otherwise(F.col("dst")).alias("node"), F.struct(F.when(out, F.col("dst")).otherwise(F.col("src")).alias("other"), "from_pos", "to_pos", out.alias("out")).alias("e"))
    lists = edges.groupBy("node").agg(F.collect_list("e").alias("edges"))
    # by the window's range: an end that is touched late may be read long before
    touched = touched.join(win.select("window_id", "start_pos", "end_pos"), "window_id")
    met = touched.join(lists, "node").select("window_id", "node", F.filter("edges", lambda e: (e["from_pos"] < F.col("end_pos")) & (e["to_pos"] >= F.col("start_pos"))).alias("e"))
    met = met.where(F.size("e") > 0).select("window_id", "node", F.col("e.other").alias("other"), F.col("e.from_pos").alias("from_pos"), F.col("e.to_pos").alias("to_pos"), F.col("e.out").alias("out"))
    return events.select("window_id", "pos", "src", "dst", "del").unionByName(met, allowMissingColumns=True)


def _reads_and_writes(t: pa.Table, direction: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted positions of a window, and which of its nodes each event reads (one hop) and writes."""
    is_event = np.asarray(t["pos"].is_valid())
    ev, li = t.filter(pa.array(is_event)), t.filter(pa.array(~is_event))
    order = np.argsort(ev["pos"].to_numpy())
    pos, gone = ev["pos"].to_numpy()[order], ev["del"].to_numpy()[order]
    nodes = np.unique(np.concatenate([ev[c].drop_null().to_numpy() for c in ("src", "dst")]))
    rank = np.argsort(order)
    writes = np.zeros((len(pos), len(nodes)), dtype=bool)
    for c in ("src", "dst"):
        ok = np.asarray(ev[c].is_valid())
        writes[rank[ok], np.searchsorted(nodes, ev[c].drop_null().to_numpy())] = True
    reads = writes.copy()
    if not len(li):
        return pos, reads, writes
    flat = {c: li[c].combine_chunks().flatten().to_numpy(zero_copy_only=False) for c in ("other", "from_pos", "to_pos", "out")}
    own, there = np.repeat(li["node"].to_numpy(), li["other"].combine_chunks().value_lengths().to_numpy()), np.isin(flat["other"], nodes)
    a, b = (np.searchsorted(nodes, x[there]) for x in (own, flat["other"]))
    out, since, until = flat["out"][there], flat["from_pos"][there], flat["to_pos"][there]
    src, dst = np.where(out, a, b), np.where(out, b, a)
    for at, nbr, use in ((dst, src, direction in ("in", "both")), (src, dst, direction in ("out", "both"))):
        if not use:
            continue
        by = np.argsort(at, kind="stable")
        first, last = (np.searchsorted(at[by], np.arange(len(nodes)), side) for side in ("left", "right"))
        for k in range(len(pos)):
            for x in np.flatnonzero(writes[k]):
                e = by[first[x] : last[x]]
                reads[k, nbr[e[(since[e] <= pos[k]) & (until[e] + gone[k] > pos[k])]]] = True
    return pos, reads, writes


def _last_writers(reads: np.ndarray, writes: np.ndarray) -> np.ndarray:
    """Whether an event depends on an earlier one as the last writer of a node it reads."""
    n = len(reads)
    last = np.full(reads.shape, -1)
    if n > 1:
        last[1:] = np.maximum.accumulate(np.where(writes, np.arange(n)[:, None], -1), axis=0)[:-1]
    out = np.zeros((n, n), dtype=bool)
    k, x = np.nonzero(reads & (last >= 0))
    out[k, last[k, x]] = True
    return out


def _pairs_of(what: str, reads: np.ndarray, writes: np.ndarray) -> np.ndarray:
    r, w = reads.astype(np.float32), writes.astype(np.float32)
    if what == "reduced":
        return _last_writers(reads, writes)
    if what == "direct":
        return np.tril(r @ w.T > 0, -1)
    anti_ = np.tril(w @ r.T > 0, -1)
    if what == "anti":
        return anti_
    dep = _last_writers(reads, writes)
    closed = np.zeros_like(dep)
    for k in range(len(dep)):
        before = np.flatnonzero(dep[k])
        closed[k] = dep[k] | closed[before].any(axis=0)
    return anti_ & ~closed


def one_hop(ev: DataFrame, spans: DataFrame, win: DataFrame, what: str, direction: str = "in") -> DataFrame:
    """``window_id, later_pos, earlier_pos`` for one-hop reads and endpoint writes, without ever listing an event's neighbours.

    ``what``: as ``direct``, ``anti`` or ``reduced``, or ``uncovered`` (``anti`` that the closure of
    ``reduced`` does not order). Only neighbours that the window itself touches can matter, so
    each window, a bounded group, is settled by itself from its events and the edges among its nodes.
    """
    if what not in ("direct", "anti", "reduced", "uncovered"):
        raise ValueError(f"unknown pairs {what!r}")

    def run(t: pa.Table) -> pa.Table:
        pos, reads, writes = _reads_and_writes(t, direction)
        later, earlier = np.nonzero(_pairs_of(what, reads, writes))
        return pa.table({"window_id": pa.array(np.full(len(later), t["window_id"][0].as_py(), dtype=np.int64)), "later_pos": pa.array(pos[later]), "earlier_pos": pa.array(pos[earlier])})

    return _window_rows(ev, spans, win).groupBy("window_id").applyInArrow(run, "window_id long, later_pos long, earlier_pos long")


def reduced_one_hop(ev: DataFrame, spans: DataFrame, win: DataFrame, direction: str = "in") -> DataFrame:
    """As ``reduced`` for one-hop reads and endpoint writes."""
    return one_hop(ev, spans, win, "reduced", direction)


def with_root(deps: DataFrame, ev: DataFrame, win: DataFrame) -> DataFrame:
    """Dependencies and an edge to the root for every event that has none."""
    m = members(ev, win).select("window_id", F.col("pos").alias("later_pos"))
    free = m.join(deps.select("window_id", "later_pos").distinct(), ["window_id", "later_pos"], "left_anti")
    return deps.unionByName(free.withColumn("earlier_pos", F.lit(ROOT).cast("long")))


def closure(deps: DataFrame) -> DataFrame:
    """``window_id, later_pos, earlier_pos``: everything each event must wait for. Windows are bounded groups."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        above: dict[int, set[int]] = {}
        direct_of: dict[int, list[int]] = {}
        for a, b in zip(pdf["later_pos"], pdf["earlier_pos"]):
            direct_of.setdefault(a, []).append(b)
        for p in sorted(direct_of):
            s = set(direct_of[p])
            for q in direct_of[p]:
                s |= above.get(q, set())
            above[p] = s
        rows = [(p, q) for p, s in above.items() for q in s]
        out = pd.DataFrame(rows, columns=["later_pos", "earlier_pos"])
        out.insert(0, "window_id", pdf["window_id"].iloc[0])
        return out

    return deps.where(F.col("earlier_pos") >= 0).groupBy("window_id").applyInPandas(run, "window_id long, later_pos long, earlier_pos long")


def uncovered(anti_deps: DataFrame, closed: DataFrame) -> DataFrame:
    """Overwrite hazards that no chain of dependencies orders."""
    return anti_deps.join(closed, ["window_id", "later_pos", "earlier_pos"], "left_anti")


def chains(deps: DataFrame, ev: DataFrame, win: DataFrame) -> DataFrame:
    """``window_id, pos, chain_id``: components without the root, named by their first event."""
    m = members(ev, win)
    edges = deps.where(F.col("earlier_pos") >= 0).select("window_id", F.col("later_pos").alias("pos"), "earlier_pos")
    rows = m.withColumn("earlier_pos", F.lit(None).cast("long")).unionByName(edges)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        root = {p: p for p in pdf["pos"]}

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        e = pdf.dropna()
        for a, b in zip(e["pos"], e["earlier_pos"].astype("int64")):
            p, q = find(a), find(int(b))
            root[max(p, q)] = min(p, q)
        pos = sorted(root)
        return pd.DataFrame({"window_id": pdf["window_id"].iloc[0], "pos": pos, "chain_id": [find(p) for p in pos]})

    return rows.groupBy("window_id").applyInPandas(run, "window_id long, pos long, chain_id long")
