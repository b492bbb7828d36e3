"""Quality classification by co-training two views of a document.

The text view sees content: hashed character trigrams, word repetition and layout shares. The
metadata view sees the record around it and nothing of the text: source, language tag and
recorded size. Each view is a logistic model. In every round each view labels all unlabelled documents and hands those
it is surest of, in the classes' proportion, to the other view's training set. It is sure where
its margin, calibrated on labelled rows kept aside, leaves little doubt beyond the classes'
shares (``SURE``); a view that knows nothing of quality hands over nothing. The views are
then calibrated (Platt) on labelled rows kept aside and combined by a third logistic model
on their log-odds, fitted on the same rows; every document gets both scores and the combined one.

Labelled rows are a hashed sample of at most ``LABELLED``, drawn by class: a class with no more
than half of that many is taken whole, and calibration weighs the classes by their true shares.
Every round scores every other document in Spark; only the few handed over reach the driver.
Rows alike in text, source, language and size count once there. Scoring covers every whole text.

Null texts are empty texts; null source, language or size are values of their own. Labels of
one document that disagree are averaged and rounded down; null labels do not count. Without
labels of both classes every document is kept with the share of good labels as its score (1
without any). Repeated rows get equal scores; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evograph.llm.common import cut, slices, table, tidy, words_of_group
from evograph.llm.text_features import layout, repetition, trigrams

DIMS = 2048
#: Hashed sources and languages, and steps of the recorded size, of the metadata view.
SOURCES, LANGUAGES, SIZES = 256, 64, 24
LABELLED = 2500
ROUNDS = 4
#: Share of the unlabelled documents that a view hands over in a round, and their largest number.
HANDED, MOST_HANDED = 0.05, 125
#: Doubt with which a view may hand over a label, as a part of the share of the other class.
SURE = 0.25
#: A document is kept from this probability of being good on.
KEEP = 0.5


def views(texts: list[str | None], source: list, lang: list, n_chars: list) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of both views."""
    content, record = [], []
    for a, b, data, offsets in slices(texts):
        _, _, h, word_offsets = words_of_group(data, offsets)
        content.append(np.hstack([trigrams(data, offsets, DIMS) * 4, repetition(h, word_offsets) * (4, 4, 0.3), layout(data, offsets) * (0.3, 0.3, 0.3, 6, 12, 6)]))
        meta = np.zeros((b - a, SOURCES + LANGUAGES + SIZES + 2))
        for i in range(a, b):
            at = 0
            for value, dims in ((source[i], SOURCES), (lang[i], LANGUAGES)):
                if value is not None:
                    meta[i - a, at + zlib.crc32(value.encode("utf-8", "surrogatepass")) % dims] = 1
                at += dims
            size = n_chars[i]
            if size is None:
                meta[i - a, -1] = 1
            else:
                meta[i - a, at + min(SIZES - 1, max(int(size), 0).bit_length())] = 1
                meta[i - a, -2] = 0.3 * np.log1p(max(int(size), 0))
        record.append(meta)
    return np.concatenate(content), np.concatenate(record)


def logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1e-3, steps: int = 150) -> np.ndarray:
    """Weights (last: bias) by accelerated gradient steps; classes weigh alike."""
    weight = np.where(y > 0.5, 0.5 / max((y > 0.5).sum(), 1), 0.5 / max((y <= 0.5).sum(), 1))
    rate = 1.0 / (0.25 * float((weight * ((x**2).sum(axis=1) + 1)).sum()) + penalty)
    w = np.zeros(x.shape[1] + 1)
    look, t = w.copy(), 1.0
    for _ in range(steps):
        g = weight * (1 / (1 + np.exp(-(x @ look[:-1] + look[-1]))) - y)
        new = look - rate * (np.append(g @ x, g.sum()) + penalty * np.append(look[:-1], 0))
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return w


def _margin(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return x @ w[:-1] + w[-1]


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def _newton(x: np.ndarray, y: np.ndarray, weight: np.ndarray, penalty: float = 1e-2, steps: int = 30) -> np.ndarray:
    """A small logistic model with true class shares, for calibration; ``weight`` undoes the draw by class."""
    z = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(z.shape[1])
    for _ in range(steps):
        p = _sigmoid(z @ w)
        h = (z * (weight * p * (1 - p))[:, None]).T @ z + penalty * np.eye(z.shape[1])
        step = np.linalg.solve(h, z.T @ (weight * (p - y)) + penalty * w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


@dataclass
class CoModel:
    """Both views, their calibration and their combination."""

    text: np.ndarray
    meta: np.ndarray
    text_scale: np.ndarray
    meta_scale: np.ndarray
    join: np.ndarray
    handed: list[tuple[int, int]]

    def score(self, content: np.ndarray, record: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a = _margin(content, self.text) * self.text_scale[0] + self.text_scale[1]
        b = _margin(record, self.meta) * self.meta_scale[0] + self.meta_scale[1]
        return _sigmoid(a), _sigmoid(b), _sigmoid(a * self.join[0] + b * self.join[1] + self.join[2])


def co_train(content: np.ndarray, record: np.ndarray, y: np.ndarray, weight: np.ndarray, surest: Callable[[list[np.ndarray], list[tuple[float, float]]], list[tuple[np.ndarray, np.ndarray, np.ndarray]]], rounds: int = ROUNDS) -> CoModel:
    """Exchange confident pseudo-labels for some rounds, then calibrate and combine.

    ``surest(models, limits)`` gives, for each view, both feature rows and labels of what it hands over.
    """
    aside = np.arange(len(y)) % 4 == 0
    if min((y[aside] > 0.5).sum(), (y[aside] <= 0.5).sum()) == 0 or min((y[~aside] > 0.5).sum(), (y[~aside] <= 0.5).sum()) == 0:
        aside[:] = False
    base = ~aside
    sets = [(content[base], y[base]), (record[base], y[base])]
    handed = []
    held = aside if aside.any() else np.ones(len(y), dtype=bool)
    good = float(np.average(y, weights=weight))
    models = [logistic(*s) for s in sets]
    for _ in range(rounds):
        given = surest(models, [limits_of(_margin(x[held], m), y[held], weight[held], good) for x, m in zip((content, record), models)])
        for me, other in ((0, 1), (1, 0)):
            label = given[me][2]
            if len(label):
                sets[other] = (np.vstack([sets[other][0], given[me][other]]), np.append(sets[other][1], label))
        handed.append(tuple(len(g[2]) for g in given))
        models = [logistic(*s) for s in sets]
    za, zb = _margin(content[held], models[0]), _margin(record[held], models[1])
    sa, sb = _newton(za[:, None], y[held], weight[held]), _newton(zb[:, None], y[held], weight[held])
    joint = _newton(np.stack([za * sa[0] + sa[1], zb * sb[0] + sb[1]], axis=1), y[held], weight[held])
    return CoModel(models[0], models[1], sa, sb, joint, handed)


def limits_of(z: np.ndarray, y: np.ndarray, weight: np.ndarray, good: float) -> tuple[float, float]:
    """Margins up to which a view is sure of a bad document and from which it is sure of a good one."""
    slope, at = _newton(z[:, None], y, weight)
    if slope <= 1e-3:
        return -np.inf, np.inf
    odds = lambda p: np.log(p / (1 - p))
    bad, fine = SURE * good, 1 - SURE * (1 - good)
    return float((odds(min(bad, 0.5)) - at) / slope), float((odds(max(fine, 0.5)) - at) / slope)


def _print() -> Column:
    """Equal for rows that both views see alike."""
    return F.xxhash64(F.coalesce("text", F.lit("")), F.coalesce("source", F.lit("\0")), F.coalesce("lang", F.lit("\0")), F.coalesce("n_chars", F.lit(-1)))


def sure_rows(docs: DataFrame, models: list[np.ndarray], known: set[int], gone: set[int], most: int, limits: Sequence[tuple[float, float]] = ((-1.0, 1.0), (-1.0, 1.0))) -> list[list[tuple[float, int]]]:
    """The ``most`` surest prints of every view and class (view 0 good, bad, view 1 good, bad), from all rows not known."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: list[dict[int, float]] = [{} for _ in range(4)]
        for batch in batches:
            for k in range(0, batch.num_rows, 128):
                part = batch.slice(k, 128)
                ids, prints = part.column(0).to_pylist(), part.column(5).to_pylist()
                use = [i for i in range(len(ids)) if ids[i] not in known and prints[i] not in gone]
                if not use:
                    continue
                part = part.take(pa.array(use))
                prints = [prints[i] for i in use]
                both = views(*[part.column(i).to_pylist() for i in (1, 2, 3, 4)])
                for me in (0, 1):
                    z = _margin(both[me], models[me])
                    for kind, sure, least in ((2 * me, z, limits[me][1]), (2 * me + 1, -z, -limits[me][0])):
                        for i in np.flatnonzero(sure >= least).tolist():
                            best[kind][prints[i]] = float(sure[i])
            for kind in range(4):
                if len(best[kind]) > 4 * most:
                    best[kind] = dict(sorted(best[kind].items(), key=lambda x: (-x[1], x[0]))[:most])
        rows = [(kind, p, z) for kind in range(4) for p, z in sorted(best[kind].items(), key=lambda x: (-x[1], x[0]))[:most]]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.float64())], ["kind", "print", "z"])
        tidy()

    found = docs.select("doc_id", "text", "source", "lang", "n_chars", _print().alias("print")).mapInArrow(run, "kind int, print long, z double")
    found = found.groupBy("kind", "print").agg(F.max("z").alias("z"))
    place = F.row_number().over(Window.partitionBy("kind").orderBy(F.desc("z"), "print"))
    out: list[list[tuple[float, int]]] = [[], [], [], []]
    for r in found.withColumn("place", place).where(F.col("place") <= most).orderBy("kind", "place").collect():
        out[r["kind"]].append((r["z"], r["print"]))
    return out


def fit(docs: DataFrame, labels: DataFrame, labelled: int = LABELLED, most: int = MOST_HANDED, rounds: int = ROUNDS) -> CoModel | float:
    """The fitted model, or the share of good labels where there are not both classes."""
    ok = labels.where("quality IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.floor(F.avg("quality")).cast("double").alias("y"))
    ok = cut(ok.join(docs.select("doc_id"), "doc_id", "left_semi"))  # labels of other documents teach nothing
    n_of = {r["y"]: r["n"] for r in ok.groupBy("y").agg(F.count("*").alias("n")).collect()}
    total = sum(n_of.values())
    good = sum(y * n for y, n in n_of.items()) / total if total else 1.0
    if len(n_of) < 2:
        return good
    few = min(n_of, key=lambda y: (n_of[y], y))
    quota = {few: min(n_of[few], labelled // 2)}
    quota |= {y: labelled - quota[few] for y in n_of if y != few}
    parts = [ok.where(F.col("y") == y).orderBy(F.xxhash64("doc_id", F.lit("label")), "doc_id").limit(q) for y, q in quota.items()]
    some = parts[0].unionByName(parts[1])
    cols = ["text", "source", "lang", "n_chars"]
    row = F.first(F.struct(*cols)).alias("row")
    drawn = docs.join(F.broadcast(some), "doc_id").groupBy("doc_id", "y", _print().alias("print")).agg(row)
    rows = sorted(((r["doc_id"], r["print"], r["y"], *r["row"]) for r in drawn.collect()), key=lambda r: r[:2])
    y = np.array([r[2] for r in rows])
    weight = np.array([n_of[v] / min(n_of[v], quota[v]) for v in y.tolist()])
    content, record = views(*[[r[i] for r in rows] for i in (3, 4, 5, 6)])
    known, gone = {r[0] for r in rows}, set()
    hand = min(most, max(2, int(HANDED * (docs.count() - len(known)))))
    n_good = max(1, round(hand * good))
    numbers = (n_good, max(1, hand - n_good))

    def surest(models: list[np.ndarray], limits: list[tuple[float, float]]) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        best = sure_rows(docs, models, known, gone, 3 * hand, limits)  # a print goes once: views and classes may both want it
        label: list[dict[int, float]] = [{}, {}]
        for me in (0, 1):
            for kind, value in ((2 * me, 1.0), (2 * me + 1, 0.0)):
                free = [p for _, p in best[kind] if p not in gone]
                label[me] |= dict.fromkeys(free[: numbers[kind % 2]], value)
                gone.update(label[me])
        want = docs.sparkSession.createDataFrame([(p,) for p in sorted(label[0] | label[1])], "print long")
        found = docs.select(*cols, _print().alias("print")).join(F.broadcast(want), "print").groupBy("print").agg(row).collect() if label[0] or label[1] else []
        at = {r["print"]: r["row"] for r in found}
        out = []
        for me in (0, 1):
            prints = sorted(label[me])
            both = views(*[[at[p][c] for p in prints] for c in cols]) if prints else (content[:0], record[:0])
            out.append((*both, np.array([label[me][p] for p in prints])))
        return out

    return co_train(content, record, y, weight / weight.mean(), surest, rounds)


def score(docs: DataFrame, model: CoModel | float, keep: float = KEEP) -> DataFrame:
    """``doc_id, text_score, meta_score, score, kept`` of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, cols in _scored(batches, model):
            yield pa.RecordBatch.from_arrays([part.column(0), *cols, pa.array(cols[2].to_numpy() >= keep if isinstance(model, CoModel) else np.ones(part.num_rows, dtype=bool))], ["doc_id", "text_score", "meta_score", "score", "kept"])

    return docs.select("doc_id", "text", "source", "lang", "n_chars").mapInArrow(run, "doc_id long, text_score double, meta_score double, score double, kept boolean")


def _scored(batches: Iterator[pa.RecordBatch], model: CoModel | float) -> Iterator[tuple[pa.RecordBatch, list[pa.Array]]]:
    for batch in batches:
        for k in range(0, batch.num_rows, 128):
            part = batch.slice(k, 128)
            if isinstance(model, CoModel):
                got = model.score(*views(*[part.column(i).to_pylist() for i in (1, 2, 3, 4)]))
                yield part, [pa.array(x) for x in got]
            else:
                yield part, [pa.array(np.full(part.num_rows, float(model)))] * 3
    tidy()


def keep_good(docs: DataFrame, model: CoModel | float, keep: float = KEEP) -> DataFrame:
    """The documents that the model keeps, all columns as given."""
    names = docs.columns
    first = ["doc_id", "text", "source", "lang", "n_chars"]
    others = [c for c in names if c not in first]
    packed = docs.select(*[F.col(f"`{c}`") for c in first], *[F.col(f"`{c}`").alias(f"o{i}") for i, c in enumerate(others)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, cols in _scored(batches, model):
            yield part.filter(pa.array(cols[2].to_numpy() >= keep)) if isinstance(model, CoModel) else part

    out = packed.mapInArrow(run, packed.schema)
    return out.select(*[F.col(f"o{others.index(c)}").alias(c) if c in others else F.col(c) for c in names])


def op2_co_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, fit(docs, table(spark, sf_dir, "labels")))
