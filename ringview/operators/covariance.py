"""Covariance matrices over joins: continuous, mixed and all-categorical; assembly for learning."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.functions.rings import CovarianceRing, GenCovarianceRing, HybridCovarianceRing, JointCovarianceRing, NumberRing
from ringview.operators.engine import Database, Engine
from ringview.operators.relation import COUNT, KeyedRelation
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder

#: Payload columns from which the wide layout is too much for one generated method.
WIDE = 100


def continuous(q: NaturalJoinQuery, features: Iterable[str], type_name: str = "double", free: Sequence[str] = ()) -> NaturalJoinQuery:
    """The query for count, sums and sums of products of ``features``; per key if ``free`` is given."""
    return replace(q, free=tuple(free), ring=CovarianceRing(tuple(features), NumberRing(type_name)))


def mixed(q: NaturalJoinQuery, cont: Iterable[str], cat: Iterable[str], type_name: str = "long") -> NaturalJoinQuery:
    """The query for the generalized covariance: categories are payload rows."""
    return replace(q, free=(), ring=GenCovarianceRing(tuple(cont), tuple(cat), type_name))


def hybrid(q: NaturalJoinQuery, cont: Iterable[str], cat: Iterable[str], type_name: str = "long") -> NaturalJoinQuery:
    """As ``mixed``, with the continuous part of each payload in columns."""
    return replace(q, free=(), ring=HybridCovarianceRing(tuple(cont), tuple(cat), type_name))


def categorical(q: NaturalJoinQuery, cat: Iterable[str]) -> NaturalJoinQuery:
    return mixed(q, (), cat)


def covariance(db: Database, q: NaturalJoinQuery, features: Sequence[str], order: VariableOrder | None = None, type_name: str = "double", free: Sequence[str] = ()) -> Engine:
    """A loaded engine.  From WIDE slots on, code generation is allowed as many fields."""
    engine = Engine(continuous(q, features, type_name, free), order)
    slots = len(engine.query.ring.slots)
    spark = next(iter(db.values())).sparkSession
    if slots > WIDE:
        spark.conf.set("spark.sql.codegen.maxFields", str(max(slots + 10, int(spark.conf.get("spark.sql.codegen.maxFields")))))
    engine.load(db)
    return engine


@dataclass(frozen=True)
class Moments:
    """Count, sums and symmetric second moments of the named features."""

    names: tuple[str, ...]
    c: float
    s: np.ndarray
    q: np.ndarray

    @classmethod
    def of(cls, rel: KeyedRelation, **key: object) -> Moments:
        """One row of (vars + 1)(vars + 2)/2 numbers comes to the driver."""
        names = tuple(sorted(rel.ring.vars))  # type: ignore[attr-defined]
        row = rel.slice(**key).first()
        get = (lambda k: float(row[k]) if row is not None and k in row and row[k] is not None else 0.0) if row is not None else lambda k: 0.0
        q = np.array([[get(CovarianceRing.q(x, y)) for y in names] for x in names])
        return cls(names, get("cnt"), np.array([get(f"s_{x}") for x in names]), q)

    def matrix(self) -> np.ndarray:
        """With the bias first: [[c, s], [s, q]]."""
        return np.block([[np.array([[self.c]]), self.s[None, :]], [self.s[:, None], self.q]])

    def restrict(self, names: Sequence[str]) -> Moments:
        at = [self.names.index(n) for n in names]
        return Moments(tuple(names), self.c, self.s[at], self.q[np.ix_(at, at)])

    def centered(self) -> np.ndarray:
        """Covariances in the statistical sense."""
        return self.q / self.c - np.outer(self.s, self.s) / self.c**2

    def correlation(self) -> np.ndarray:
        cov = self.centered()
        dev = np.sqrt(np.maximum(np.diag(cov), 1e-300))
        return cov / np.outer(dev, dev)

    def without_onehot(self) -> int:
        return 1 + len(self.names) + len(self.names) * (len(self.names) + 1) // 2


def long_rows(rel: KeyedRelation) -> DataFrame:
    """Slots of the wide layout as rows (x, y, v), the long layout as it is; the hybrid and the joint ones become long."""
    if isinstance(rel.ring, JointCovarianceRing):
        return _joint_rows(rel)
    if isinstance(rel.ring, HybridCovarianceRing):
        return _hybrid_rows(rel)
    if isinstance(rel.ring, GenCovarianceRing):
        return rel.df.select(*rel.keys, "x", "cx", "y", "cy", "v")
    names = [s for s in rel.slots]
    entry = lambda s: F.struct(F.lit(s).alias("slot"), F.col(s).alias("v"))
    return rel.df.select(*rel.keys, F.explode(F.array(*map(entry, names))).alias("e")).select(*rel.keys, "e.slot", "e.v")


def _hybrid_rows(rel: KeyedRelation) -> DataFrame:
    """Each row of the hybrid layout gives its count and the scalars that its number of categories leaves open."""
    cont = sorted(rel.ring.cont)  # type: ignore[attr-defined]
    none = F.lit("")
    entry = lambda x, cx, y, cy, v: F.struct(x.alias("x"), cx.alias("cx"), y.alias("y"), cy.alias("cy"), v.alias("v"))
    own = entry(*(F.col(c) for c in ("x", "cx", "y", "cy")), F.col("v"))
    sums, products, by_category = [], [], []
    for i, x in enumerate(cont):
        sums.append(entry(F.lit(x), none, none, none, F.col(f"s_{x}")))
        products += [entry(F.lit(x), none, F.lit(y), none, F.col(CovarianceRing.q(x, y))) for y in cont[i:]]
        first = F.col("x") < x
        by_category.append(entry(F.when(first, F.col("x")).otherwise(x), F.when(first, F.col("cx")).otherwise(""), F.when(first, F.lit(x)).otherwise(F.col("x")), F.when(first, F.lit("")).otherwise(F.col("cx")), F.col(f"s_{x}")))
    rows = F.when(F.col("x") == "", F.array(own, *sums, *products)).when(F.col("y") == "", F.array(own, *by_category)).otherwise(F.array(own))
    return rel.df.select(*rel.keys, F.explode(rows).alias("e")).select(*rel.keys, "e.x", "e.cx", "e.y", "e.cy", "e.v")


def _joint_rows(rel: KeyedRelation) -> DataFrame:
    """Each combination of categories counts for all pairs of variables; tasks sum before anything is shuffled."""
    ring = rel.ring
    cont, cat = set(ring.cont), set(ring.cat)  # type: ignore[attr-defined]
    names, none = sorted(cont | cat), F.lit("")
    place = lambda x: F.col(f"c_{x}") if x in cat else none
    entry = lambda x, cx, y, cy, v: F.struct(F.lit(x).alias("x"), cx.alias("cx"), F.lit(y).alias("y"), cy.alias("cy"), F.col(v).alias("v"), F.col(COUNT).alias(COUNT))
    rows = [entry("", none, "", none, "v")]
    for i, x in enumerate(names):
        rows.append(entry(x, place(x), "", none, f"s_{x}" if x in cont else "v"))
        for y in names[i:]:
            here = [z for z in (x, y) if z in cont]
            rows.append(entry(x, place(x), y, place(y), CovarianceRing.q(*here) if len(here) == 2 else f"s_{here[0]}" if here else "v"))
    by = [*rel.keys, "x", "cx", "y", "cy"]
    listed = rel.df.select(*rel.keys, F.explode(F.array(*rows)).alias("e")).select(*rel.keys, "e.*")
    summed = listed.groupBy(*by).agg(F.sum("v").cast(ring.type_name).alias("v"), F.sum(COUNT).alias(COUNT))  # type: ignore[attr-defined]
    return summed.where(F.col(COUNT) != 0).select(*by, "v")


def one_hot(df: DataFrame, cont: Sequence[str], cat: dict[str, Sequence[object]], type_name: str = "long") -> DataFrame:
    """The contrast: categories as 0/1 columns, all second moments of all columns, in one aggregation of a joined table."""
    columns = [F.col(c).cast(type_name).alias(c) for c in cont]
    columns += [(F.col(c) == v).cast("int").cast(type_name).alias(f"{c}_{v}") for c, values in cat.items() for v in values]
    wide = df.select(*columns)
    names = wide.columns
    aggs = [F.count("*").alias("cnt")] + [F.sum(n).alias(f"s_{n}") for n in names]
    aggs += [F.sum(F.col(x) * F.col(y)).alias(CovarianceRing.q(x, y)) for i, x in enumerate(names) for y in names[i:]]
    return wide.agg(*aggs)


def result_rows(engine: Engine) -> DataFrame:
    out = engine.result()
    return out.df.drop(COUNT)
