"""Stores across restarts, work that does not grow with the database, products, copies of a relation, maintained factors."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ringview.functions.rings import BigIntRing, IntRing
from ringview.operators.conjunctive import Factorized
from ringview.operators.engine import Engine
from ringview.operators.factored import TERM, product_decompose
from ringview.operators.matrix_chain import BlockMatrix
from ringview.operators.metrics import rows_touched
from ringview.operators.relation import COUNT, KeyedRelation
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.plans.viewtree import build_tree
from ringview.sources.store import ParquetStore, ViewStore


def pairs(spark, rows, names):
    return spark.createDataFrame(rows, ", ".join(f"{n} long" for n in names.split()))


def star(spark, n):
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("a", "c")}, ("a",), IntRing("b", "c"))
    return q, {"r": spark.range(n).selectExpr("id as a", "id % 7 as b"), "s": spark.range(n).selectExpr("id as a", "id % 5 as c")}


def test_update_cost_does_not_grow(spark, tmp_path):
    """A change of one key opens one bucket of its sibling, however large the tables are (for a bucket of fixed size)."""
    touched = {}
    for n, buckets in ((2_000, 4), (16_000, 32)):
        q, db = star(spark, n)
        store = ParquetStore(spark, f"{tmp_path}/{n}", q.ring, buckets=buckets, prune=0)
        e = Engine(q, VariableOrder.parse("a - {b, c}"), store=store)
        e.load(db)
        seen = []
        write = store._write
        store._write = lambda name, rel, seen=seen, write=write: (seen.append(rows_touched(rel.df)), write(name, rel))
        e.apply("r", pairs(spark, [(11, 3, 1)], "a b __m"))
        touched[n] = sum(seen)
        assert e.result().slice(a=11).first()["v"] == (11 % 7 + 3) * (11 % 5)
    assert touched[16_000] < 2 * touched[2_000], touched


def test_restart_counts_batches_once(spark, tmp_path):
    q, db = star(spark, 50)
    order, path = VariableOrder.parse("a - {b, c}"), str(tmp_path / "v")
    first = Engine(q, order, store=ParquetStore(spark, path, q.ring, buckets=2, fold=2))
    assert not first.resumed
    first.load(db)
    delta = pairs(spark, [(1, 9, 1), (2, 2, -1)], "a b __m")
    assert first.apply("r", delta, ("r", 0)) and not first.apply("r", delta, ("r", 0))
    first.store.append("V_b_r" if "V_b_r" in first.stored else sorted(first.stored)[0], first.store.read(sorted(first.stored)[0]))  # killed before the commit
    again = Engine(q, order, store=ParquetStore(spark, path, q.ring, buckets=2, fold=2))
    assert again.resumed and not again.apply("r", delta, ("r", 0)) and again.apply("r", delta, ("r", 1))
    got = {r["a"]: r["v"] for r in again.result().df.collect()}
    want = {a: (a % 7) * (a % 5) for a in range(50)}
    want[1] = (1 + 18) * 1
    want[2] = (2 - 4) * 2
    assert {a: v for a, v in got.items() if v} == {a: v for a, v in want.items() if v}
    assert again.store.vacuum() > 0
    last = Engine(q, order, store=ParquetStore(spark, path, q.ring, buckets=2))
    assert {r["a"]: r["v"] for r in last.result().df.collect()} == got


def test_memory_log_is_folded(spark):
    q, db = star(spark, 20)
    e = Engine(q, VariableOrder.parse("a - {b, c}"), store=ViewStore(q.ring, fold=2))
    e.load(db)
    for i in range(5):
        e.apply("s", pairs(spark, [(i, 100, 1)], "a c __m"))
    assert max(len(p) for p in e.store.parts.values()) <= 3
    assert e.result().slice(a=4).first()["v"] == 4 * 104


@pytest.mark.parametrize("seed", [1, 2])
def test_products_with_values(spark, seed):
    rng = np.random.default_rng(seed)
    u, v = rng.integers(-3, 4, (12, 3)), rng.choice([-1, 0, 1], (9, 3))
    cells = [(i, j, int(u[i, i % 3] * v[j, i % 3])) for i in range(12) for j in range(9) if u[i, i % 3] * v[j, i % 3]]
    left, right = product_decompose(pairs(spark, cells, "i j v"), ["i"], ["j"], "v")
    got = left.join(right.withColumnRenamed("v", "w"), TERM).groupBy("i", "j").agg(F.sum(F.col("v") * F.col("w")).alias("v"))
    assert sorted(tuple(r) for r in got.collect()) == sorted(cells)
    assert left.count() + right.count() < len(cells)


def test_factorized_result_is_maintained(spark):
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("a", "c")}, ("a", "b", "c"), IntRing())
    _, db = star(spark, 30)
    f = Factorized(q, VariableOrder.parse("a - {b, c}"), db)
    f.apply("r", pairs(spark, [(3, 50, 1), (4, 4, -1)], "a b __m"))
    f.apply("s", pairs(spark, [(3, 60, 1), (99, 1, 1)], "a c __m"))
    r = [(a, a % 7) for a in range(30) if a != 4] + [(3, 50)]
    s = [(a, a % 5) for a in range(30)] + [(3, 60), (99, 1)]
    want = sorted((a, b, c, 1) for a, b in r for x, c in s if a == x)
    assert sorted(tuple(x) for x in f.expand().collect()) == want and f.aggregate() == len(want)


def test_relation_moved_lower(spark):
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")})
    order = VariableOrder.parse("a - b - c")
    tree = build_tree(q, order, {"r": "c"})
    assert {x.relation for n in tree.nodes() if len(n.children) == 3 for x in n.leaves()} == {"r", "s", "t"}
    with pytest.raises(ValueError, match="not below"):
        build_tree(q, order, {"t": "b"})


def test_counts_wider_than_64_bits(spark):
    q = NaturalJoinQuery({"r": ("a",), "s": ("a",)}, (), BigIntRing())
    e = Engine(q, VariableOrder.parse("a"))
    e.load({r: spark.createDataFrame([(1, 2**40)], "a long, __m long") for r in ("r", "s")})
    assert int(e.result().df.first()["v"]) == 2**80 and COUNT in e.result().df.columns


def test_block_products_of_many_parts(spark):
    rng = np.random.default_rng(3)
    a, b = rng.integers(-5, 6, (10, 700)), rng.integers(-5, 6, (700, 6))
    coo = lambda m: spark.createDataFrame([(int(i), int(j), float(m[i, j])) for i, j in zip(*np.nonzero(m), strict=True)], "i long, j long, v double")
    got = np.zeros((10, 6))
    for r in (BlockMatrix.of(coo(a), 8) @ BlockMatrix.of(coo(b), 8)).cells().collect():
        got[r["i"], r["j"]] = r["v"]
    assert np.array_equal(got, a @ b)


def test_relation_of_membership(spark):
    rel = KeyedRelation.from_bag(pairs(spark, [(1, 2), (1, 2), (3, 4)], "a b"), ("a", "b"), IntRing())
    assert rel.contains(a=1, b=2) and not rel.contains(a=1, b=4) and rel.slice(a=3).first()["v"] == 1 and sum(r["v"] for r in rel.enumerate()) == 3


def test_measures_of_runs(spark):
    from ringview import experiments
    from ringview.sources import workloads as w

    sf = "/root/testdata/sf0.001"
    got = experiments.strategies(spark, sf, w.NATIONS, limit=30)
    assert set(got) == {"view_tree", "first_order", "recursive", "plain_reeval"} and all(x["tuples_per_s"] > 0 for x in got.values())
    assert got["view_tree"]["views"] == 4 and len(got["view_tree"]["tenths"]) >= 1
    assert set(experiments.enumeration_costs(spark, sf, (2,))) == {"eager_fact", "eager_list", "lazy_fact", "lazy_list"}
    assert set(experiments.rank_costs(spark, sf, (1, 8))) == {"rank_1", "rank_8"}
