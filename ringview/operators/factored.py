"""Updates that are sums of products of small relations; products are never multiplied out on the way."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.functions.rings import IntRing, Ring
from ringview.operators.relation import COUNT, KeyedRelation, join, marginalize, union
from ringview.plans.viewtree import Leaf, Node, path_to


#: Key that numbers the products of a sum that is kept as one term.
TERM = "__term"


@dataclass(frozen=True)
class Term:
    """A product of relations with disjoint keys; or, with the key TERM in several of them, a sum of such products, one for
    each of its values."""

    factors: tuple[KeyedRelation, ...]

    @property
    def keys(self) -> tuple[str, ...]:
        return tuple(k for f in self.factors for k in f.keys)

    def expand(self) -> KeyedRelation:
        out = self.factors[0]
        for f in self.factors[1:]:
            out = join(out, f)
        return out

    def times(self, siblings: Sequence[KeyedRelation]) -> Term:
        """Factors that a sibling touches are merged with it; the others stay as they are."""
        factors = list(self.factors)
        for s in siblings:
            near = [f for f in factors if set(f.keys) & set(s.keys)]
            merged = s
            for f in near:
                merged = join(f, merged)
            factors = [f for f in factors if not any(f is n for n in near)] + [merged]
        return Term(tuple(factors))

    def sum_away(self, variables: Sequence[str], lifted: bool = True) -> Term:
        """A variable is summed in the one factor that has it."""
        return Term(tuple(marginalize(f, [v for v in variables if v in f.keys], lifted) if set(variables) & set(f.keys) else f for f in self.factors))

    def size(self) -> int:
        return sum(f.size() for f in self.factors)


@dataclass(frozen=True)
class FactoredDelta:
    """A sum of terms."""

    terms: tuple[Term, ...]

    def expand(self, keys: Sequence[str]) -> KeyedRelation:
        parts = [t.expand() for t in self.terms]
        parts = [KeyedRelation(p.df.select(*keys, *p.slots, COUNT), tuple(keys), p.ring) for p in parts]
        return union(*parts)

    def size(self) -> int:
        """Stored values."""
        return sum(t.size() for t in self.terms)


def vector(df: DataFrame, key: str, value: str, ring: Ring | None = None) -> KeyedRelation:
    ring = ring or IntRing()
    kind = getattr(ring, "type_name", "long")
    return KeyedRelation(df.select(key, F.col(value).cast(kind).alias("v"), F.lit(1).cast("long").alias(COUNT)), (key,), ring)


def rank_one(u: DataFrame, v: DataFrame, row: str, column: str, value: str = "v", ring: Ring | None = None) -> FactoredDelta:
    return FactoredDelta((Term((vector(u, row, value, ring), vector(v, column, value, ring))),))


def rank_r(spark: SparkSession, u: np.ndarray, v: np.ndarray, row: str, column: str, ring: Ring | None = None, together: bool = False) -> FactoredDelta:
    """u (p x r) times v (q x r) transposed, as r terms, or ``together`` as one that is keyed by the term's number, so that
    the plan does not grow with r.  u and v are the update itself: small by their nature, and broadcast."""
    kind = lambda x: "double" if x.dtype.kind == "f" else "long"
    if together:
        kept = lambda x, name: KeyedRelation(
            F.broadcast(spark.createDataFrame([(i, t, x[i, t].item(), 1) for i in range(len(x)) for t in range(x.shape[1]) if x[i, t]], f"{name} long, {TERM} long, v {kind(x)}, {COUNT} long")), (name, TERM), ring or IntRing()
        )
        return FactoredDelta((Term((kept(u, row), kept(v, column))),))
    frame = lambda x, name: F.broadcast(spark.createDataFrame([(i, x[i].item()) for i in range(len(x)) if x[i]], f"{name} long, v {kind(x)}"))
    return FactoredDelta(tuple(t for j in range(u.shape[1]) for t in rank_one(frame(u[:, j], row), frame(v[:, j], column), row, column, ring=ring).terms))


def low_rank(delta: np.ndarray, r: int | None = None, most: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """u, v with u @ v.T = delta: the changed rows as unit vectors if they are few, else singular vectors."""
    if max(delta.shape) > most:
        raise ValueError("decompose on the cluster: product_decompose")
    rows = np.flatnonzero(delta.any(axis=1))
    if r is None or len(rows) <= r:
        u = np.zeros((delta.shape[0], len(rows)), dtype=delta.dtype)
        u[rows, np.arange(len(rows))] = 1
        return u, delta[rows].T
    a, s, b = np.linalg.svd(delta.astype(float), full_matrices=False)
    return a[:, :r] * s[:r], b[:r].T


def product_decompose(df: DataFrame, left: Sequence[str], right: Sequence[str], value: str | None = None) -> tuple[DataFrame, DataFrame]:
    """A relation as a sum of products: (left, TERM, v) and (right, TERM, v) whose join on TERM, values multiplied, is it.

    Values of ``left`` whose partners are the same, with values in the same proportion, form one product (if a row's value at
    its first partner divides the others; else the row's own values are the pattern).
    Patterns are compared by their number of partners and two sums of hashes, so no set of partners is ever gathered.
    """
    rows = df.select(*left, *right, (F.col(value).cast("long") if value else F.lit(1).cast("long")).alias("v"))
    rows = (rows.groupBy(*left, *right).agg(F.sum("v").alias("v")) if value else rows.distinct()).where("v <> 0")
    least = rows.groupBy(*left).agg(F.min_by("v", F.struct(*right)).alias("first"), F.count("*").alias("n"))
    odd = rows.join(least, list(left)).groupBy(*left).agg(F.max(F.pmod("v", F.abs("first"))).alias("odd"))
    scale = least.join(odd, list(left)).select(*left, "n", F.when(F.col("odd") == 0, F.col("first")).otherwise(F.lit(1)).alias("scale"))
    whole = rows.join(scale, list(left)).withColumn("v", F.expr("v div scale"))
    digest = lambda salt: F.sum(F.xxhash64(F.lit(salt), *right, "v").cast("decimal(38,0)")).alias(f"d{salt}")
    pattern = whole.groupBy(*left, "n", "scale").agg(digest(1), digest(2)).withColumn(TERM, F.xxhash64("n", "d1", "d2"))
    one = pattern.groupBy(TERM).agg(F.min(F.struct(*left)).alias("l")).select(TERM, "l.*")
    return pattern.select(*left, TERM, F.col("scale").alias("v")), whole.join(one, list(left)).select(*right, TERM, "v")


def cover_with_correction(df: DataFrame, left: str, right: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(left values, right values, missing cells): the whole box less what is not there; better if little is missing."""
    a, b = df.select(left).distinct(), df.select(right).distinct()
    return a, b, a.crossJoin(b).join(df.select(left, right).distinct(), [left, right], "left_anti")


def decomposition_size(parts: tuple[DataFrame, DataFrame]) -> int:
    return sum(p.count() for p in parts)


def apply_factored(engine, relation: str, delta: FactoredDelta, keep_factored: bool = False, at_root: Callable[[Sequence[Term], KeyedRelation], Sequence[Term]] | None = None) -> FactoredDelta:
    """Push a factored change of a relation to the root; stored views get it multiplied out, the root's stays factored
    in the answer.  ``at_root`` takes the change of the root's child and what the other child has, and answers the root's."""
    out: list[Term] = []
    leaves = [x for x in engine.tree.leaves() if x.relation == relation and x.onto is None]
    for leaf in leaves:
        below: Node | Leaf = leaf
        terms = delta.terms
        if leaf.name in engine.stored:
            engine.store.append(leaf.name, FactoredDelta(terms).expand(leaf.keys))
        for n in path_to(engine.tree, leaf):
            siblings = [engine.store.read(c.name) for c in n.children if c is not below]
            if at_root and n in engine.tree.roots:
                terms = tuple(at_root(terms, siblings[0]))
                break
            terms = tuple(t.times(siblings) for t in terms)
            gone = [v for v in (terms[0].keys if terms else ()) if v not in n.keys and v != TERM]
            terms = tuple(t.sum_away(gone) for t in terms)
            if n.name in engine.stored and not (keep_factored and n in engine.tree.roots):
                engine.store.append(n.name, FactoredDelta(terms).expand(n.keys))
            below = n
        out += terms
    engine.store.commit()
    return FactoredDelta(tuple(out))
