"""Strategies to compare with: first-order and fully recursive maintenance, recomputation, left-deep joins, one SQL
aggregate indexed by degree, and the four result modes."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import replace
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.functions.rings import CovarianceRing, IntRing, NumberRing, Ring
from ringview.operators.engine import Database, Engine, evaluate
from ringview.operators.relation import COUNT, SIGN, KeyedRelation, aggregate, join, marginalize, union
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.plans.viewtree import build_free_top_tree, build_tree


def _signed(df: DataFrame) -> DataFrame:
    return df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1))


def joined(q: NaturalJoinQuery, bags: Mapping[str, DataFrame], first: str | None = None) -> DataFrame:
    """Natural join of signed bags, row by row, signs multiplied; starts with ``first`` and stays connected if it can."""
    names = sorted(q.relations, key=lambda r: r != first)
    done, out = [names[0]], _signed(bags[names[0]])
    while len(done) < len(names):
        have = {v for r in done for v in q.relations[r]}
        r = max((n for n in names if n not in done), key=lambda n: len(have & set(q.relations[n])))
        right = _signed(bags[r]).withColumnRenamed(SIGN, "__s")
        shared = [v for v in q.relations[r] if v in have]
        out = (out.join(right, shared) if shared else out.crossJoin(right)).withColumn(SIGN, F.col(SIGN) * F.col("__s")).drop("__s")
        done.append(r)
    return out


def plain_reeval(q: NaturalJoinQuery, db: Database) -> KeyedRelation:
    """Join everything, then aggregate."""
    rows = joined(q, db)
    return aggregate(rows, q.free, {v: F.col(v) for v in q.variables if v not in q.free}, q.ring)


def factorized_reeval(q: NaturalJoinQuery, order: VariableOrder, db: Database) -> KeyedRelation:
    """The view tree from scratch."""
    return evaluate(build_tree(q, order), db)


class FirstOrder:
    """Bases and result only: a change is joined with the other bases."""

    def __init__(self, q: NaturalJoinQuery, db: Database):
        self.q, self.bases = q, {r: _signed(df) for r, df in db.items()}
        self.parts = [plain_reeval(q, self.bases)]

    def apply(self, relation: str, delta: DataFrame) -> None:
        change = joined(self.q, {**self.bases, relation: _signed(delta)}, relation)
        self.parts.append(aggregate(change, self.q.free, {v: F.col(v) for v in self.q.variables if v not in self.q.free}, self.q.ring))
        self.bases[relation] = self.bases[relation].select(*self.q.relations[relation], SIGN).unionByName(_signed(delta).select(*self.q.relations[relation], SIGN))

    def result(self) -> KeyedRelation:
        return union(*self.parts)

    def view_count(self) -> int:
        return 1 + len(self.bases)


def scalar_rings(features: Sequence[str], type_name: str = "long") -> dict[str, Ring]:
    """One ring for each aggregate of a covariance matrix: count, sums, sums of products."""
    f = sorted(features)
    out: dict[str, Ring] = {"cnt": NumberRing(type_name)}
    out |= {f"s_{x}": NumberRing(type_name, (x,)) for x in f}
    out |= {CovarianceRing.q(x, y): _Power(type_name, (x, y)) for i, x in enumerate(f) for y in f[i:]}
    return out


class _Power(NumberRing):
    """Numbers where a variable named twice counts with its square."""

    def lift(self, var, value):
        out = self.one()["v"]
        for x in self.lifts:
            if x == var:
                out = out * value.cast(self.type_name)
        return {"v": out.cast(self.type_name)}


class _Tuples(_Power):
    """Values of single tuples in 64 bits; their sums have 38 digits, from sums of 22 bits each that stay plain numbers."""

    def total(self, slot, column):
        low = (1 << 22) - 1
        parts = [column.bitwiseAND(F.lit(low)), F.shiftright(column, 22).bitwiseAND(F.lit(low)), F.shiftright(column, 44)]
        sums = [F.sum(p).cast("decimal(38,0)") * F.lit(Decimal(1 << 22 * i)) for i, p in enumerate(parts)]
        return (sums[0] + sums[1] + sums[2]).cast("decimal(38,0)")


class _Wide(_Power):
    """Sums of 38 digits over values that fit 64 bits in each tuple."""

    @property
    def of_tuples(self):
        return _Tuples("long", self.lifts)


class FirstOrderScalar:
    """One first-order query for each aggregate."""

    def __init__(self, q: NaturalJoinQuery, db: Database, features: Sequence[str], type_name: str = "long"):
        self.each = {n: FirstOrder(replace(q, free=(), ring=r), db) for n, r in scalar_rings(features, type_name).items()}
        self.relations = len(q.relations)

    def apply(self, relation: str, delta: DataFrame) -> None:
        for e in self.each.values():
            e.apply(relation, delta)

    def result(self) -> DataFrame:
        out = None
        for n, e in self.each.items():
            one = e.result().df.select(F.col("v").alias(n))
            out = one if out is None else out.crossJoin(one)  # one row each
        return out

    def view_count(self) -> int:
        return len(self.each) + self.relations


def recursive_views(q: NaturalJoinQuery, updatable: Sequence[str] | None = None, projections: bool = False) -> dict[frozenset[str], tuple[str, ...]]:
    """Views of fully recursive maintenance: for each view and each relation in it, what connects the rest once that
    relation's variables are fixed.  Relation sets with their keys; base relations only with ``projections``."""
    every = frozenset(q.relations)
    out: dict[frozenset[str], tuple[str, ...]] = {}

    def keys(v: frozenset[str]) -> tuple[str, ...]:
        inside = {x for r in v for x in q.relations[r]}
        other = {x for r in every - v for x in q.relations[r]} | set(q.free)
        return tuple(x for x in q.variables if x in inside & other) if v != every else tuple(q.free)

    def visit(v: frozenset[str]) -> None:
        if v in out:
            return
        out[v] = keys(v)
        for r in v:
            if updatable is None or r in updatable:
                for part in components_without(q, v, r):
                    visit(part)

    visit(every)
    return out if projections else {v: k for v, k in out.items() if len(v) > 1 or set(k) != set(q.relations[next(iter(v))])}


def components_without(q: NaturalJoinQuery, view: frozenset[str], relation: str) -> list[frozenset[str]]:
    """Connected parts of a view without a relation, whose variables no longer connect."""
    fixed, left, out = set(q.relations[relation]), set(view - {relation}), []
    while left:
        part = {min(left)}
        while more := {r for r in left - part for p in part if (set(q.relations[r]) & set(q.relations[p])) - fixed}:
            part |= more
        out.append(frozenset(part))
        left -= part
    return out


class Recursive:
    """Fully recursive maintenance with any ring as payload."""

    def __init__(self, q: NaturalJoinQuery, db: Database):
        self.q = q
        self.keys = recursive_views(q, projections=True)
        self.parts: dict[frozenset[str], list[KeyedRelation]] = {}
        for v, keys in self.keys.items():
            sub = replace(q, relations={r: q.relations[r] for r in q.relations if r in v}, free=keys)
            rows = joined(sub, {r: db[r] for r in v})
            self.parts[v] = [aggregate(rows, keys, {x: F.col(x) for x in sub.variables if x not in keys}, q.ring)]

    def _read(self, v: frozenset[str]) -> KeyedRelation:
        p = self.parts[v]
        return p[0] if len(p) == 1 else union(*p)

    def apply(self, relation: str, delta: DataFrame) -> None:
        """Each view over the relation gets the change times the views of its remaining parts, largest view first."""
        base = aggregate(_signed(delta), self.q.relations[relation], {}, self.q.ring)
        changes = {}
        for v, keys in self.keys.items():
            if relation not in v:
                continue
            change = base
            for part in components_without(self.q, v, relation):
                change = join(change, self._read(part))
            gone = [x for x in change.keys if x not in keys]
            changes[v] = marginalize(change, gone) if gone else change
        for v, c in changes.items():
            self.parts[v].append(KeyedRelation(c.df.select(*self.keys[v], *c.inner, *c.slots, COUNT), self.keys[v], c.ring))

    def result(self) -> KeyedRelation:
        return self._read(frozenset(self.q.relations))

    def view_count(self) -> int:
        return len(recursive_views(self.q))


def recursive_scalar(q: NaturalJoinQuery, db: Database, features: Sequence[str], type_name: str = "long", wide: bool = False) -> dict[str, Recursive]:
    """A recursive query for each aggregate; ``wide``: with sums of 38 digits."""
    rings = {n: _Wide("decimal(38,0)", r.lifts) if wide else r for n, r in scalar_rings(features, type_name).items()}
    return {n: Recursive(replace(q, free=(), ring=r), db) for n, r in rings.items()}


def recursive_scalar_view_count(q: NaturalJoinQuery, features: Sequence[str]) -> int:
    """Views of the scalar variant: each relation set once for each aggregate restricted to its own features."""
    out = 0
    for v in recursive_views(q):
        own = sum(any(f in q.relations[r] for r in v) for f in features)
        out += aggregate_count(own)
    return out


def aggregate_count(n: int) -> int:
    """Scalar aggregates of a covariance matrix over n features."""
    return 1 + n + n * (n + 1) // 2


def groupby_count(n_cont: int, n_cat: int) -> int:
    """Distinct group-by clauses of the mixed case: none, each category, each pair of categories."""
    return 1 + n_cat + n_cat * (n_cat - 1) // 2 if n_cont >= 0 else 0


def degree_sql(q: NaturalJoinQuery, order: VariableOrder, features: Sequence[str], tables: Mapping[str, str] | None = None, type_name: str = "BIGINT") -> str:
    """One SQL text: each partial result is a table of (keys, degree of each feature, value) with total degree at most 2;
    joins add degrees, sums multiply by powers.  Its rows are the aggregates."""
    tables = tables or {r: r for r in q.relations}
    feats = sorted(f for f in features)
    deg = {f: f"d_{f}" for f in feats}

    def at(x: str) -> tuple[str, list[str], list[str]]:
        """(SQL, keys, features with a degree) of the part below and at x."""
        parts = [at(c) for c in order.children(x)]
        for r, s in q.relations.items():
            if order.place(q, r) == x:
                parts.append((f"SELECT {', '.join(s)}, CAST(COUNT(*) AS {type_name}) AS val FROM {tables[r]} GROUP BY {', '.join(s)}", list(s), []))
        keys = list(dict.fromkeys(k for _, ks, _ in parts for k in ks))
        have = [f for _, _, fs in parts for f in fs]
        names = [f"t{i}" for i in range(len(parts))]
        source = f"({parts[0][0]}) {names[0]}"
        seen = list(parts[0][1])
        where = []
        for (sql, ks, _), n in zip(parts[1:], names[1:], strict=True):
            on = [f"{names[next(i for i, p in enumerate(parts) if k in p[1])]}.{k} = {n}.{k}" for k in ks if k in seen]
            source += f" JOIN ({sql}) {n} ON {' AND '.join(on) or '1 = 1'}"
            seen += [k for k in ks if k not in seen]
        owner = {k: names[next(i for i, p in enumerate(parts) if k in p[1])] for k in keys}
        value = " * ".join(f"{n}.val" for n in names)
        degree = {f: f"{names[next(i for i, p in enumerate(parts) if f in p[2])]}.{deg[f]}" for f in have}
        total = " + ".join(degree.values())
        if total and len(parts) > 1:
            where.append(f"{total} <= 2")
        out_keys = [k for k in keys if k != x]
        if x in deg:
            source += " CROSS JOIN (SELECT 0 AS p UNION ALL SELECT 1 UNION ALL SELECT 2) pw"
            where.append(f"{total + ' + ' if total else ''}p <= 2")
            value += f" * CASE p WHEN 0 THEN 1 WHEN 1 THEN CAST({owner[x]}.{x} AS {type_name}) ELSE CAST({owner[x]}.{x} AS {type_name}) * CAST({owner[x]}.{x} AS {type_name}) END"
            degree[x] = "p"
        cols = [f"{owner[k]}.{k} AS {k}" for k in out_keys] + [f"{e} AS {deg[f]}" for f, e in degree.items()]
        by = [f"{owner[k]}.{k}" for k in out_keys] + list(degree.values())
        sql = f"SELECT {''.join(c + ', ' for c in cols)}CAST(SUM({value}) AS {type_name}) AS val FROM {source}{' WHERE ' + ' AND '.join(where) if where else ''}{' GROUP BY ' + ', '.join(by) if by else ''}"
        return sql, out_keys, list(degree)

    sql, _, have = at(order.roots[0])
    return f"SELECT {', '.join(deg[f] for f in sorted(have))}, val FROM ({sql}) result"


class LeftDeep:
    """Left-deep joins of rows; columns are cut as early as possible but nothing is aggregated before the root."""

    def __init__(self, q: NaturalJoinQuery, db: Database, order: Sequence[str] | None = None):
        self.q, self.names = q, list(order or q.relations)
        self.bases = {r: _signed(df).select(*q.relations[r], SIGN) for r, df in db.items()}
        self.levels = self._build(self.bases)
        self.parts = [self._total(self.levels[-1])]

    def _needed(self, i: int) -> set[str]:
        return {v for r in self.names[i + 1 :] for v in self.q.relations[r]} | set(self.q.free) | {v for v in self.q.variables if self.q.ring.lift(v, F.lit(1)).keys() != self.q.ring.one().keys() or v in getattr(self.q.ring, "lifts", ())}

    def _step(self, left: DataFrame, right: DataFrame, i: int) -> DataFrame:
        r = right.withColumnRenamed(SIGN, "__s")
        shared = [c for c in right.columns if c in left.columns and c != SIGN]
        out = (left.join(r, shared) if shared else left.crossJoin(r)).withColumn(SIGN, F.col(SIGN) * F.col("__s")).drop("__s")
        return out.select(*[c for c in out.columns if c in self._needed(i) or c == SIGN])

    def _build(self, bases) -> list[DataFrame]:
        out = [bases[self.names[0]]]
        for i, r in enumerate(self.names[1:], 1):
            out.append(self._step(out[-1], bases[r], i))
        return out

    def _total(self, rows: DataFrame) -> KeyedRelation:
        return aggregate(rows, self.q.free, {v: F.col(v) for v in self.q.variables if v not in self.q.free and v in rows.columns}, self.q.ring)

    def apply(self, relation: str, delta: DataFrame) -> None:
        at = self.names.index(relation)
        d = _signed(delta).select(*self.q.relations[relation], SIGN)
        change = d if at == 0 else self._step(self.levels[at - 1], d, at)
        self.bases[relation] = self.bases[relation].unionByName(d)
        for i in range(at, len(self.names)):
            if i > at:
                change = self._step(change, self.bases[self.names[i]], i)
            self.levels[i] = self.levels[i].unionByName(change.select(*self.levels[i].columns))
        self.parts.append(self._total(change))

    def result(self) -> KeyedRelation:
        return union(*self.parts)


class ResultMode:
    """Eager or lazy, list or factorized: the same updates and requests for each of the four."""

    def __init__(self, q: NaturalJoinQuery, db: Database, eager: bool, factorized: bool):
        self.q, self.eager, self.factorized = q, eager, factorized
        self.bases = {r: _signed(df).select(*q.relations[r], SIGN) for r, df in db.items()}
        if eager and factorized:
            self.engine = Engine(q, free_top=True)
            self.engine.load(db)
        elif eager:
            self.engine = Recursive(q, db)

    @property
    def name(self) -> str:
        return f"{'eager' if self.eager else 'lazy'}_{'fact' if self.factorized else 'list'}"

    def apply(self, relation: str, delta: DataFrame) -> None:
        d = _signed(delta).select(*self.q.relations[relation], SIGN)
        if self.eager:
            self.engine.apply(relation, d)
        else:
            self.bases[relation] = self.bases[relation].unionByName(d)

    def result(self) -> KeyedRelation:
        if self.eager:
            return self.engine.result()
        if self.factorized:
            e = Engine(self.q, free_top=True)
            e.load(self.bases)
            return e.result()
        return plain_reeval(self.q, self.bases)


def export_train(q: NaturalJoinQuery, db: Database, label: str, features: Sequence[str]) -> np.ndarray:
    """The contrast: list the join row by row and learn from the rows.  Each task learns from its own, batch by batch, and
    hands on a triangle of as many rows as there are columns; the triangles are united in the same way (twice in tasks).
    Rows with a null are passed over."""
    n, names = len(features) + 2, [*features, label]
    rows = joined(q, db).select(*[F.col(c).cast("double") for c in names]).dropna()

    def triangles(columns):
        def run(batches):
            held = np.zeros((0, n))
            for p in batches:
                held = np.linalg.qr(np.vstack([held, columns(p)]), mode="r")
            if len(held):
                yield pd.DataFrame({"r": [np.ascontiguousarray(held).tobytes()]})

        return run

    first = rows.mapInPandas(triangles(lambda p: np.column_stack([np.ones(len(p)), p[names].to_numpy()])), "r binary")
    again = triangles(lambda p: np.vstack([np.frombuffer(x).reshape(-1, n) for x in p["r"]]))
    few = first.repartition(8).mapInPandas(again, "r binary").collect()  # eight triangles at most
    r = np.vstack([np.zeros((1, n)), *[np.frombuffer(x["r"]).reshape(-1, n) for x in few]])
    return np.linalg.lstsq(r[:, :-1], r[:, -1], rcond=None)[0]


def evaluate_free_top(q: NaturalJoinQuery, order: VariableOrder) -> int:
    """Views of the factorized form."""
    return len(build_free_top_tree(q, order).nodes())


__all__ = ["FirstOrder", "FirstOrderScalar", "IntRing", "LeftDeep", "Recursive", "ResultMode", "aggregate_count", "degree_sql", "export_train", "factorized_reeval", "groupby_count", "plain_reeval", "recursive_scalar", "recursive_views"]
