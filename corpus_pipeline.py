"""A corpus pipeline of five stages, each over all rows that its predecessor kept.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and returns a
DataFrame. All but the last return the columns of ``documents``:

1. quality classifier: documents that the co-trained model rejects go;
2. quality rules: documents that fail the base rules or are depleted go, boilerplate lines are cut;
3. near-duplicates: one document of each class stays;
4. substrings: words in repeated windows are cut;
5. packing: one row per piece with its sequence and place.

The labels that the classifier is fitted on come from ``labels`` in ``sf_dir``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evograph.llm import minhash_dedup, packing, quality_model, quality_rules, substring_dedup
from evograph.llm.common import cut, table


def classify_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_model.keep_good(docs, quality_model.fit(docs, table(spark, sf_dir, "labels")))


def apply_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.filter_documents(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash_dedup.keep_one(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [
    ("quality_classifier", classify_quality),
    ("quality_rules", apply_rules),
    ("near_duplicates", drop_near_duplicates),
    ("substring_dedup", cut_repeats),
    ("best_fit_packing", pack_sequences),
]

#: No SQL: models, sketches and packing are not expressible; tests compare with brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; lineage is cut between them by checkpoints."""
    df = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        df = stage(spark, df, sf_dir)
        if k < len(STAGES) - 1:
            df = cut(df)
    return df
