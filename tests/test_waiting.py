"""Batches that wait are taken in the same jobs; each keeps its own change, as one after another."""

import random

import pytest
from pyspark.sql import functions as F

from ringview.experiments import _Shears, apply_waiting, stream, waiting
from ringview.functions.rings import CovarianceRing, IntRing, JointCovarianceRing
from ringview.operators.engine import Engine
from ringview.operators.relation import AT, SIGN
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.sources import workloads as w
from ringview.sources.io import shared_path
from ringview.sources.store import ParquetStore, ViewStore

RELATIONS = {"r": ("a", "b"), "s": ("a", "c", "e"), "t": ("c", "d")}
ORDER = "a - {b, c - {d, e}}"


def _changes(n, seed):
    """(number, relation, rows with a sign) of ``n`` batches; rows that came may go again."""
    rnd, seen = random.Random(seed), {r: [] for r in RELATIONS}
    for i in range(n):
        r = rnd.choice(list(RELATIONS))
        rows = [(*[rnd.randrange(3) for _ in RELATIONS[r]], 1) for _ in range(4)]
        if seen[r] and rnd.random() < 0.5:
            rows.append((*rnd.choice(seen[r])[:-1], -1))
        seen[r] += rows[:4]
        yield i, r, rows


def _of(rows, keys):
    return sorted((tuple(round(x, 6) if isinstance(x, float) else str(x) for x in r) for r in rows), key=repr)


@pytest.mark.parametrize("ring, disk", [(IntRing("e"), True), (CovarianceRing(("b", "e")), False), (JointCovarianceRing(("b",), ("d",)), True)], ids=["number", "moments", "rows"])
def test_each_batch_keeps_its_change(spark, ring, disk):
    q, order = NaturalJoinQuery(RELATIONS, (), ring), VariableOrder.parse(ORDER)
    store = lambda: ParquetStore(spark, shared_path(spark, "waiting"), ring, buckets=2, prune=0) if disk else ViewStore(ring)
    frame = lambda r, rows, *more: spark.createDataFrame(rows, ", ".join(f"{c} long" for c in (*RELATIONS[r], *more)) + f", {SIGN} int")
    changes = list(_changes(7, 5))
    single, both = (Engine(q, order, store=store()) for _ in range(2))
    root = single.tree.roots[0].name
    want = {}
    for e in (single, both):
        e.load({r: frame(r, [(0,) * len(c) + (1,)]).drop(SIGN) for r, c in RELATIONS.items()})
    for i, r, rows in changes:
        single.apply(r, frame(r, rows), ("all", i))
        last = single.store.latest(root)
        columns = sorted(c for c in last.df.columns)
        want[i] = _of(last.df.select(columns).collect(), columns)
        if i < 2:
            both.apply(r, frame(r, rows), ("all", i))
    tables = {r: frame(r, [(*row[:-1], i, row[-1]) for i, x, rows in changes if x == r for row in rows], AT) for r in RELATIONS}
    version = both.store.version
    assert both.apply_together(tables, ("all", 3)) and both.apply_together(tables, ("all", 6))
    assert not both.apply_together(tables, ("all", 6)) and both.store.version == version + 2 and both.store.has("all", 6)
    last = both.store.latest(root)
    for i in range(4, 7):
        assert _of(last.df.where(F.col(AT) == i).select(columns).collect(), columns) == want[i], i
    columns = sorted(single.result().df.columns)
    assert _of(both.result().df.select(columns).collect(), columns) == _of(single.result().df.select(columns).collect(), columns)


def test_factors_keep_their_order(spark):
    """A product that does not commute: the same with changes on the left, in the middle and on the right."""
    relations = {"r": ("a", "suppkey"), "s": ("a", "c"), "t": ("a", "custkey")}
    ring = _Shears(2)
    q, order = NaturalJoinQuery(relations, (), ring), VariableOrder.parse("a - {suppkey, c, custkey}")
    frame = lambda r, rows: spark.createDataFrame(rows, f"a long, {relations[r][1]} long, {AT} long")
    rows = {"r": [(0, 2, 0), (1, 3, 4)], "s": [(0, 5, 1), (1, 1, 3)], "t": [(1, 7, 2), (0, 4, 5)]}
    got = []
    for together in (True, False):
        e = Engine(q, order)
        e.load({r: frame(r, rows[r]).drop(AT) for r in relations})
        if together:
            e.apply_together({r: frame(r, rows[r]) for r in relations}, ("all", 5))
        else:
            for i in range(6):
                r = next(r for r in relations for row in rows[r] if row[-1] == i)
                e.apply(r, frame(r, rows[r]).where(F.col(AT) == i).drop(AT))
        df = e.result().df
        got.append(df.select(sorted(df.columns)).collect())
    assert got[0] == got[1]


def test_numbers_of_the_stream(spark, sf):
    db = w.NATIONS.build(spark, sf)
    tables, order = waiting(w.NATIONS, db, 7)
    one = list(stream(w.NATIONS, db, 7))
    assert [r for r, _ in one] == order
    for i in (0, 1, 2, 3, 8, len(order) - 2, len(order) - 1):
        r, delta = one[i]
        assert sorted(tables[r].where(F.col(AT) == i).drop(AT).collect()) == sorted(delta.collect()), i


def test_jobs_do_not_grow_with_the_batches(spark, sf):
    work = w.NATIONS
    q, db, jobs, found = work.query(IntRing("custkey")), work.build(spark, sf), [], []
    for size in (60, 4):
        e = Engine(q, work.variable_order, store=ParquetStore(spark, shared_path(spark, "waiting"), q.ring, buckets=1))
        e.load({r: df.select(*work.relations[r]).limit(0) for r, df in db.items()})
        tables, order = waiting(work, db, size)
        spark.sparkContext.setJobGroup(f"waiting-{size}", "")
        apply_waiting(e, tables, order)
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"waiting-{size}")))
        found.append(e.result().df.collect())
    assert found[0] == found[1] and len(order) > 40 and jobs[1] <= jobs[0] + 10
