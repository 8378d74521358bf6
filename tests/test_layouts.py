"""Payload layouts and contrasts: each gives what the plain form gives, under inserts and deletes."""

import random

import pytest

from ringview.functions.rings import CovarianceRing, GenCovarianceRing, HybridCovarianceRing, IntRing, NumberRing, RelationalRing
from ringview.operators.covariance import hybrid, long_rows
from ringview.operators.engine import Engine
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder, free_top_order
from ringview.sources import workloads as w
from ringview.sources.store import ParquetStore
from ringview.sources.updates import signed


@pytest.fixture(scope="module")
def toy(spark):
    return {r: df.cache() for r, df in w.TOY.build(spark, "").items()}


def _rows(df):
    return sorted(tuple(map(str, r)) for r in df.collect())


def _changes(spark, toy):
    """Inserts with repeats, then deletes of all rows of one key."""
    rng = random.Random(5)
    new = [(rng.randint(1, 3), rng.randint(1, 4), 1) for _ in range(6)]
    gone = [(r["c"], r["d"], -1) for r in toy["t"].collect() if r["c"] == 2]
    yield "t", spark.createDataFrame(new, "c long, d long, __m int")
    yield "t", spark.createDataFrame(gone, "c long, d long, __m int")
    yield "r", spark.createDataFrame([(9, 9, 1), (1, 5, 1)], "a long, b long, __m int")


def test_hybrid_layout_holds_what_the_long_one_holds(spark, toy):
    q = w.TOY.query(IntRing())
    engines = [Engine(w.TOY.query(GenCovarianceRing(("b", "d", "e"), ("a", "c"))), w.TOY.variable_order), Engine(hybrid(q, ("b", "d", "e"), ("a", "c")), w.TOY.variable_order)]
    for e in engines:
        e.load(toy)
    for relation, delta in _changes(spark, toy):
        for e in engines:
            e.apply(relation, delta)
    long, short = (e.result() for e in engines)
    # a long row without derivations is gone; the hybrid one gives it as a zero until its whole row is gone
    assert [r for r in _rows(long_rows(short)) if r[4] != "0"] == [r for r in _rows(long_rows(long)) if r[4] != "0"]
    assert short.df.count() < long.df.count()


def test_hybrid_layout_of_continuous_variables_is_one_row(toy):
    e = Engine(w.TOY.query(HybridCovarianceRing(("b", "d", "e"), ())), w.TOY.variable_order)
    wide = Engine(w.TOY.query(CovarianceRing(("b", "d", "e"), NumberRing("long"))), w.TOY.variable_order)
    e.load(toy)
    wide.load(toy)
    row, other = e.result().df.collect(), wide.result().df.first()
    assert len(row) == 1 and row[0]["v"] == other["cnt"]
    assert all(row[0][s] == other[s] for s in wide.query.ring.slots if s != "cnt")


@pytest.mark.parametrize(("ring", "on_disk"), [(CovarianceRing(("d", "e"), NumberRing("long")), True), (RelationalRing(("d",)), False)], ids=["covariance", "relational"])
def test_multiplicities_above_the_payloads(spark, toy, ring, on_disk, tmp_path):
    q = w.TOY.query(ring, ("a", "b", "c"))
    store = ParquetStore(spark, str(tmp_path), ring, buckets=2, prune=0) if on_disk else None
    full = Engine(q, free_top_order(q), free_top=True)
    lean = Engine(q, free_top_order(q), free_top=True, count_only_above=True, store=store)
    full.load(toy)
    lean.load(toy)
    assert lean.counts and lean.counts < {n.name for n in lean.tree.nodes()}
    for relation, delta in _changes(spark, toy):
        full.apply(relation, delta)
        lean.apply(relation, delta)
    a, b = full.result().df, lean.result().df
    assert _rows(a.select(sorted(a.columns))) == _rows(b.select(sorted(a.columns)))
    kept = [n for n in lean.counts if n in lean.stored]
    assert kept and all(lean.store.read(n).ring == IntRing() for n in kept)


def test_multiplicities_above_need_an_enumerated_result():
    with pytest.raises(ValueError, match="free_top"):
        Engine(w.TOY.query(IntRing()), w.TOY.variable_order, count_only_above=True)


def test_indicators_by_difference_and_by_support(spark):
    """Tuples come in twice and leave once, leave for good, and come back."""
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")}, ring=IntRing())
    order = VariableOrder.parse("a - b - c")
    rng = random.Random(3)
    edges = lambda: [(rng.randint(1, 4), rng.randint(1, 4)) for _ in range(10)]
    db = {r: spark.createDataFrame(edges(), "{} long, {} long".format(*v)) for r, v in q.relations.items()}
    engines = [Engine(q, order, indicators=True, by_difference=d) for d in (False, True)]
    for e in engines:
        e.load(db)
    first = [(x, y, 1) for x, y in edges()]
    now = {r: signed(df) for r, df in db.items()}
    for relation, rows in (("r", first * 2), ("r", [(x, y, -1) for x, y, _ in first]), ("t", first), ("r", [(x, y, -1) for x, y, _ in first])):
        delta = spark.createDataFrame(rows, "{} long, {} long, __m int".format(*q.relations[relation]))
        now[relation] = now[relation].unionByName(delta)
        for e in engines:
            e.apply(relation, delta)
    plain = Engine(q, order)
    plain.load(now)
    got = [_rows(e.result().df.select("v")) for e in (*engines, plain)]
    assert got[0] == got[1] == got[2] != []
