"""Mutual information of categorical variables, the dependency tree, discretization."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def counts(rows: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(total), (x, cx, n), (x, cx, y, cy, n) of an all-categorical long covariance."""
    total = rows.where("x = ''").select(F.col("v").alias("n"))
    single = rows.where("x <> '' and y = ''").select("x", "cx", F.col("v").alias("n"))
    pairs = rows.where("x <> '' and y <> '' and x <> y").select("x", "cx", "y", "cy", F.col("v").alias("n"))
    return total, single, pairs


def mutual_information(rows: DataFrame) -> DataFrame:
    """(x, y, mi), x < y, natural logarithm; joins of the counts, no table of categories on the driver."""
    total, single, pairs = counts(rows)
    a = single.select("x", "cx", F.col("n").alias("nx"))
    b = single.select(F.col("x").alias("y"), F.col("cx").alias("cy"), F.col("n").alias("ny"))
    t = F.broadcast(total.select(F.col("n").cast("double").alias("t")))  # one row
    joined = pairs.join(a, ["x", "cx"]).join(b, ["y", "cy"]).crossJoin(t)
    term = F.col("n") / F.col("t") * F.log(F.col("t") * F.col("n") / (F.col("nx").cast("double") * F.col("ny")))
    return joined.groupBy("x", "y").agg(F.sum(term).alias("mi"))


def dependency_tree(mi: Sequence[tuple[str, str, float]], root: str | None = None) -> list[tuple[str, str, float]]:
    """(parent, child, mi): from a root, always the outside variable with the most information about an inside one.
    Ties go to the smaller names."""
    weight = {frozenset((x, y)): w for x, y, w in mi}
    names = sorted({v for x, y, _ in mi for v in (x, y)})
    if not names:
        return []
    inside, out = [root or names[0]], []
    best = {v: (weight.get(frozenset((inside[0], v)), 0.0), inside[0]) for v in names if v != inside[0]}
    while best:
        child = min(best, key=lambda v: (-best[v][0], best[v][1], v))
        w, parent = best.pop(child)
        out.append((parent, child, w))
        inside.append(child)
        for v in best:
            n = weight.get(frozenset((child, v)), 0.0)
            if n > best[v][0]:
                best[v] = (n, child)
    return out


def select_features(mi: DataFrame, label: str, k: int) -> DataFrame:
    """The k variables that tell most about the label."""
    other = F.when(F.col("x") == label, F.col("y")).when(F.col("y") == label, F.col("x"))
    return mi.select(other.alias("feature"), "mi").where("feature is not null").orderBy(F.desc("mi"), "feature").limit(k)


@dataclass(frozen=True)
class Discretizer:
    """Equal-width bins over a column's range at the time of fitting; later values are clamped."""

    bins: int = 100
    low: float = 0.0
    high: float = 1.0

    def fit(self, df: DataFrame, column: str) -> Discretizer:
        r = df.agg(F.min(column).cast("double").alias("a"), F.max(column).cast("double").alias("b")).first()
        return Discretizer(self.bins, r["a"] or 0.0, r["b"] or 0.0)

    def expr(self, column: str | Column) -> Column:
        c = (F.col(column) if isinstance(column, str) else column).cast("double")
        width = (self.high - self.low) or 1.0
        return F.greatest(F.lit(0), F.least(F.floor((c - self.low) * self.bins / width), F.lit(self.bins - 1))).cast("int")


class InformationStream:
    """Mutual information and tree after each batch."""

    def __init__(self, root: str | None = None):
        self.root, self.trees = root, []

    def after_batch(self, rows: DataFrame) -> list[tuple[str, str, float]]:
        mi = [(r["x"], r["y"], r["mi"]) for r in mutual_information(rows).collect()]  # a row for each pair of variables
        self.trees.append(dependency_tree(mi, self.root))
        return self.trees[-1]
