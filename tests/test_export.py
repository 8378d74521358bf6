"""Learning from the listed join, of any size."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ringview.functions.rings import IntRing
from ringview.operators.baselines import export_train
from ringview.plans.query import NaturalJoinQuery


def test_rows_beyond_two_million_are_learned_from(spark):
    q = NaturalJoinQuery({"r": ("k", "x"), "s": ("k", "y")}, (), IntRing())
    r = spark.range(1_100_000).select((F.col("id") % 1000).alias("k"), F.pmod(F.xxhash64("id"), F.lit(97)).alias("x"))
    s = spark.range(2000).select((F.col("id") % 1000).alias("k"), (F.col("id") * 3).alias("y"))
    got = export_train(q, {"r": r, "s": s}, "y", ["x", "k"])
    x = np.array([tuple(t) for t in r.join(s, "k").groupBy("x", "k", "y").count().collect()], dtype=float)
    w = np.sqrt(x[:, 3:])
    assert x[:, 3].sum() == 2_200_000
    want = np.linalg.lstsq(w * np.column_stack([np.ones(len(x)), x[:, :2]]), w[:, 0] * x[:, 2], rcond=None)[0]
    assert got == pytest.approx(want, rel=1e-6, abs=1e-6)
