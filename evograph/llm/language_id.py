"""Language identification by hierarchical discrimination.

Texts are rows of hashed character trigrams. Linear support vector machines, one for every
pair of families, vote for a family; machines for every pair of languages of that family then
separate those closely related languages. Margins pass through a logistic curve; the score
is the family's mean winning probability times the language's.

Fitted on about ``PER_LANGUAGE`` labelled texts of each language (a hashed sample, a bound
that is a parameter), however many languages there are, of the documents whose crc32(doc_id as text) mod 5 is not 0. Everything
else covers all rows, whole texts.

Nulls, empty texts and texts without a letter are ``und`` with score 0, as is every text when
nothing is labelled. A null id is not held out and not learned from. With one language known,
it is the prediction for all others. Repeated rows get equal results. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evograph.llm.common import slices, table
from evograph.llm.text_features import trigrams

DIMS = 4096
PER_LANGUAGE = 500

# fixed values: language families by ISO 639-1 code
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af lb fy yi",
    "romance": "fr es it pt ro ca gl oc",
    "slavic": "ru uk be pl cs sk sl hr sr bs mk bg",
    "uralic": "fi et hu",
    "turkic": "tr az kk uz ky tk",
    "semitic": "ar he mt am",
    "indo_aryan": "hi ur bn mr gu pa ne si",
    "iranian": "fa ku ps tg",
    "sinitic": "zh",
    "baltic": "lt lv",
    "celtic": "ga cy br gd",
}
FAMILY_OF = {code: family for family, codes in FAMILIES.items() for code in codes.split()}


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 5 == 0, F.lit(False))


def svm(x: np.ndarray, y: np.ndarray, penalty: float = 1e-4, steps: int = 100) -> np.ndarray:
    """Weights (last: bias) of a linear machine with squared hinge loss; accelerated gradient steps.

    Classes weigh alike whatever their sizes.
    """
    weight = np.where(y > 0, 0.5 / max((y > 0).sum(), 1), 0.5 / max((y < 0).sum(), 1))
    w = np.zeros(x.shape[1] + 1)
    look, t = w.copy(), 1.0
    rate = 1.0 / (4.0 + penalty)  # rows have length one, and the bias adds one
    for _ in range(steps):
        short = np.maximum(0.0, 1 - y * (x @ look[:-1] + look[-1]))
        pull = -2 * weight * y * short
        grad = np.append(pull @ x, pull.sum()) + penalty * np.append(look[:-1], 0)
        new = look - rate * grad
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look = new + (t - 1) / t2 * (new - w)
        w, t = new, t2
    return w


class Hierarchy:
    """Pairwise machines between families and, inside each, between its languages."""

    def __init__(self, x: np.ndarray, langs: list[str]):
        self.families: dict[str, list[str]] = {}
        for lang in sorted(set(langs)):
            self.families.setdefault(FAMILY_OF.get(lang, f"own:{lang}"), []).append(lang)
        y = np.array(langs)
        family = np.array([FAMILY_OF.get(v, f"own:{v}") for v in langs])
        self.top = self._pairs(x, family, sorted(self.families))
        self.inner = {f: self._pairs(x[family == f], y[family == f], ls) for f, ls in self.families.items()}

    @staticmethod
    def _pairs(x: np.ndarray, y: np.ndarray, names: list[str]) -> tuple[list[str], list[tuple[int, int]], np.ndarray]:
        pairs = list(combinations(range(len(names)), 2))
        ws = []
        for a, b in pairs:
            use = (y == names[a]) | (y == names[b])
            ws.append(svm(x[use], np.where(y[use] == names[a], 1.0, -1.0)))
        return names, pairs, np.array(ws).reshape(len(pairs), x.shape[1] + 1)

    @staticmethod
    def _vote(x: np.ndarray, machines: tuple[list[str], list[tuple[int, int]], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Winner and its mean probability, for every row."""
        names, pairs, ws = machines
        if len(names) == 1:
            return np.zeros(len(x), dtype=np.int64), np.ones(len(x))
        p = 1 / (1 + np.exp(-4 * (x @ ws[:, :-1].T + ws[:, -1])))
        votes, mass = np.zeros((len(x), len(names))), np.zeros((len(x), len(names)))
        for k, (a, b) in enumerate(pairs):
            votes[:, a] += p[:, k] >= 0.5
            votes[:, b] += p[:, k] < 0.5
            mass[:, a] += p[:, k]
            mass[:, b] += 1 - p[:, k]
        mass /= len(names) - 1
        win = (votes + mass / 2).argmax(axis=1)  # equal votes: the larger probability
        return win, mass[np.arange(len(x)), win]

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        win, score = self._vote(x, self.top)
        out, score = [""] * len(x), score.copy()
        for k, family in enumerate(self.top[0]):
            rows = np.flatnonzero(win == k)
            if len(rows):
                inner, p = self._vote(x[rows], self.inner[family])
                score[rows] *= p
                for r, i in zip(rows.tolist(), inner.tolist()):
                    out[r] = self.families[family][i]
        return out, np.clip(score, 0.0, 1.0)


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, dims: int = DIMS) -> Hierarchy | None:
    """Machines from a bounded hashed sample of the labelled texts that are not held out."""
    usable = docs.where(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")) & F.col("lang").isNotNull() & (F.length("text") > 0)).select("doc_id", "lang", "text")
    counts = {r["lang"]: r["n"] for r in usable.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return None
    share = F.create_map(*[F.lit(v) for k, n in counts.items() for v in (k, min(1.0, per_language / n))])
    drawn = usable.where(F.pmod(F.xxhash64(F.col("doc_id"), F.lit("sample")), F.lit(1_000_003)) < share[F.col("lang")] * 1_000_003)
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", F.lit("sample")), "doc_id"))
    drawn = drawn.withColumn("place", place).where(F.col("place") <= 2 * per_language)  # repeated ids of one language crowd out no other
    rows = sorted((r["doc_id"], r["lang"], r["text"]) for r in drawn.collect())
    if not rows:
        return None
    texts = [t for _, _, t in rows]
    x = np.concatenate([trigrams(data, offsets, dims) for _, _, data, offsets in slices(texts)])
    return Hierarchy(x, [lang for _, lang, _ in rows])


def identify(docs: DataFrame, model: Hierarchy | None, dims: int = DIMS) -> DataFrame:
    """``doc_id, lang_pred, score`` of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                texts = part.column(1).to_pylist()
                langs, scores = ["und"] * len(texts), [0.0] * len(texts)
                for a, b, data, offsets in slices(texts):
                    if model is None:
                        continue
                    got, p = model.predict(trigrams(data, offsets, dims))
                    for i in range(a, b):
                        if texts[i] and any(map(str.isalpha, texts[i])):
                            langs[i], scores[i] = got[i - a], float(p[i - a])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(langs), pa.array(scores)], ["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs, fit(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
