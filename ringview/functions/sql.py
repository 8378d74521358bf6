"""Functions for SQL users."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ringview.functions.rings import CovarianceRing


def covariance_columns(*features: str) -> list[Column]:
    """Count, sums and sums of products as aggregate expressions: the fast way."""
    f = sorted(features)
    return [F.count("*").alias("cnt"), *[F.sum(x).alias(f"s_{x}") for x in f], *[F.sum(F.col(x) * F.col(y)).alias(CovarianceRing.q(x, y)) for i, x in enumerate(f) for y in f[i:]]]


@pandas_udf(T.ArrayType(T.DoubleType()))
def cov_agg(x: pd.Series, y: pd.Series) -> list:
    """(count, sum x, sum y, sum xx, sum xy, sum yy) of two columns, for ad-hoc SQL."""
    a, b = x.to_numpy(float), y.to_numpy(float)
    return [float(len(a)), float(a.sum()), float(b.sum()), float(a @ a), float(a @ b), float(b @ b)]


@pandas_udf(T.ArrayType(T.DoubleType()))
def ring_sum(payload: pd.Series) -> list:
    """Element-wise sum of payload arrays."""
    return np.sum(np.stack(payload.to_numpy()), axis=0).tolist() if len(payload) else []


@udtf(returnType=T.StructType([T.StructField("level", T.IntegerType()), T.StructField("view", T.StringType()), T.StructField("keys", T.StringType())]))
class ExplainTree:
    """Rows of a view tree's text."""

    def eval(self, text: str):
        for line in text.split("\n")[1:]:
            name, _, keys = line.strip().partition("[")
            yield (len(line) - len(line.lstrip())) // 2, name.removeprefix("* "), keys.split("]")[0]


def grouping_covariance(df: DataFrame, cat: list[str]) -> DataFrame:
    """Counts of a single relation for all variables and pairs in one job: rows (x, cx, y, cy, v)."""
    sets = [[], *[[x] for x in cat], *[[x, y] for i, x in enumerate(sorted(cat)) for y in sorted(cat)[i + 1 :]]]
    view = "ringview_grouping"
    df.createOrReplaceTempView(view)
    names = ", ".join(sorted(cat))
    text = ", ".join(f"({', '.join(s)})" for s in sets)
    rows = df.sparkSession.sql(f"SELECT {names}, {', '.join(f'grouping({c}) AS g_{c}' for c in sorted(cat))}, COUNT(*) AS v FROM {view} GROUP BY GROUPING SETS ({text})")
    used = F.filter(F.array(*[F.struct((F.col(f"g_{c}") == 0).alias("on"), F.lit(c).alias("x"), F.col(c).cast("string").alias("c")) for c in sorted(cat)]), lambda s: s["on"])
    pick = lambda i, f: F.coalesce(F.get(F.col("u"), F.lit(i))[f], F.lit(""))
    return rows.withColumn("u", used).select(pick(0, "x").alias("x"), pick(0, "c").alias("cx"), pick(1, "x").alias("y"), pick(1, "c").alias("cy"), "v")


def register(spark: SparkSession) -> None:
    spark.udf.register("cov_agg", cov_agg)
    spark.udf.register("ring_sum", ring_sum)
    spark.udtf.register("explain_tree", ExplainTree)
