"""User functions: scalar, grouped and table functions, and their SQL names.

Built-in expressions do the same work in ``ops.scalar``; these are for users who bring
their own numpy code.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udf, udtf
from pyspark.sql.types import DoubleType, LongType, StringType, StructField, StructType

from evograph.registry import cte, query
from evograph.sources import streams
from evograph.sources.tables import table
from evograph.train.engine import auc_of
from evograph.windows.fixed import fixed


@pandas_udf(DoubleType())
def vec_dot(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.dot(np.asarray(x, dtype=float), np.asarray(y, dtype=float))) for x, y in zip(a, b)])


@pandas_udf(DoubleType())
def decay_log(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for dt in batches:
        yield 1 / np.log(np.e + dt.clip(lower=0))


@pandas_udf(DoubleType())
def auc_agg(score: pd.Series, y: pd.Series) -> float:
    a = auc_of(score.to_numpy(dtype=float), y.to_numpy(dtype=float))
    return float("nan") if a is None else a


@udf(StringType(), useArrow=False)
def node_side(node: int) -> str:
    return "left" if node % 2 == 0 else "right"


@udtf(returnType=StructType([StructField("window_id", LongType()), StructField("pos", LongType())]))
class ExpandWindow:
    """Positions of a window."""

    def eval(self, window_id: int, start: int, end: int):
        for p in range(start, end):
            yield window_id, p


def register(spark: SparkSession) -> None:
    """SQL names of all user functions, and SQL-defined ones."""
    spark.udf.register("vec_dot", vec_dot)
    spark.udf.register("decay_log", decay_log)
    spark.udf.register("auc_agg", auc_agg)
    spark.udf.register("node_side", node_side)
    spark.udtf.register("expand_window", ExpandWindow)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION logistic(x DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-x))")


@query("q_o72_scalar_udfs", cte("s1") + "SELECT pos, CASE WHEN dst % 2 = 0 THEN 'left' ELSE 'right' END AS side, round(1 / ln(exp(1) + weight), 6) AS d FROM s1")
def scalar_udfs(s, d):
    return streams.interactions(s, d).select("pos", node_side("dst").alias("side"), F.round(decay_log("weight"), 6).alias("d"))


@query("q_o73_grouped_map", cte("s1") + "SELECT src, count(*) AS n, round(max(weight) - min(weight), 4) AS spread FROM s1 GROUP BY src")
def grouped_map(s, d):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"src": [pdf["src"].iloc[0]], "n": [len(pdf)], "spread": [round(float(pdf["weight"].max() - pdf["weight"].min()), 4)]})

    return streams.interactions(s, d).groupBy("src").applyInPandas(run, "src long, n long, spread double")


@query("q_o73_cogrouped", cte("s1") + "SELECT k AS node_id, sum(a) AS before, sum(b) AS after FROM (SELECT src AS k, CASE WHEN pos < 500 THEN 1 ELSE 0 END AS a, CASE WHEN pos >= 500 THEN 1 ELSE 0 END AS b FROM s1) GROUP BY k")
def cogrouped(s, d):
    e = streams.interactions(s, d).select("pos", "src")
    late = streams.interactions(s, d).select(F.col("pos").alias("p"), F.col("src").alias("src_late"))  # names of its own

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        k = a["src"].iloc[0] if len(a) else b["src_late"].iloc[0]
        return pd.DataFrame({"node_id": [k], "before": [len(a)], "after": [len(b)]})

    return e.where("pos < 500").groupBy("src").cogroup(late.where("p >= 500").groupBy("src_late")).applyInPandas(run, "node_id long, before long, after long")


@query("q_o74_udaf", "SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 5) AS m FROM embeddings GROUP BY label")
def udaf(s, d):
    @pandas_udf("double")
    def first_mean(v: pd.Series) -> float:
        return float(np.mean([x[0] for x in v]))

    return table(s, d, "embeddings").groupBy("label").agg(F.round(first_mean("embedding"), 5).alias("m"))


@query("q_o75_udtf", cte("s1") + ", w AS (SELECT i AS window_id, i * 40 AS a, least(i * 40 + 200, n) AS b FROM (SELECT count(*) AS n, unnest(generate_series(0, CAST(ceil((count(*) - 200) / 40.0) AS BIGINT))) AS i FROM s1)) SELECT window_id, count(*) AS n, min(p) AS first_pos FROM (SELECT window_id, unnest(generate_series(a, b - 1)) AS p FROM w) GROUP BY window_id")
def table_function(s, d) -> DataFrame:
    register(s)
    w = fixed(s, streams.interactions(s, d).count(), 200, 40)
    return s.sql("SELECT e.window_id, count(*) AS n, min(e.pos) AS first_pos FROM {w} w, LATERAL expand_window(w.window_id, w.start_pos, w.end_pos) e GROUP BY e.window_id", w=w)


@query("q_o76_sql_functions", "SELECT vec_id, round(1 / (1 + exp(-list_inner_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])))), 5) AS p FROM embeddings")
def sql_functions(s, d) -> DataFrame:
    register(s)
    return s.sql("SELECT vec_id, round(logistic(vec_dot(embedding, embedding)), 5) AS p FROM {e}", e=table(s, d, "embeddings"))
