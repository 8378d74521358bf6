"""Engine on the toy database and on small random ones: incremental equals recomputed."""

import random

import numpy as np
import pytest

from ringview.functions.laws import check
from ringview.functions.rings import BigIntRing, ComplexRing, CovarianceRing, GenCovarianceRing, IntRing, MatrixRing, MaxProductSemiring, NumberRing, RealRing, RelationalRing
from ringview.operators import baselines, metrics
from ringview.operators.conjunctive import Factorized
from ringview.operators.covariance import Moments, long_rows
from ringview.operators.engine import Engine, evaluate
from ringview.operators.factored import low_rank
from ringview.operators.mutual_info import dependency_tree
from ringview.operators.regression import loss, solve, train
from ringview.operators.relation import COUNT, support_change
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.plans.viewtree import build_tree
from ringview.sources import workloads as w
from ringview.sources.store import ParquetStore
from ringview.sources.updates import deletes, inserts, round_robin, signed


def entries(rel, *columns):
    return {tuple(r[c] for c in columns[:-1]): r[columns[-1]] for r in rel.df.collect()}


@pytest.fixture(scope="module")
def toy(spark):
    return {r: df.cache() for r, df in w.TOY.build(spark, "").items()}


def loaded(toy, ring, free=(), **how):
    e = Engine(w.TOY.query(ring, free), w.TOY.variable_order, **how)
    e.load(toy)
    return e


def delta_t(spark):
    return spark.createDataFrame([(1, 1, -1), (2, 2, 3)], "c long, d long, __m int")


def test_count_and_its_views(spark, toy):
    e = loaded(toy, IntRing())
    assert entries(e.result(), "v") == {(): 10}
    keys = {n.name: n.keys for n in e.tree.nodes()}
    by = {keys[n]: entries(e.store.read(n), *keys[n], "v") for n in e.stored if n in keys and keys[n] != ("a",)}
    assert by[("a", "c")] == {(1, 1): 2, (1, 2): 1, (2, 2): 1} and by[("c",)] == {(1,): 1, (2,): 2, (3,): 1}
    v_b = next(n for n in e.stored if n.startswith("V_b"))
    v_c = next(n for n in e.stored if n.startswith("V_c"))
    assert entries(e.store.read(v_b), "a", "v") == {(1,): 2, (2,): 1, (3,): 1} and entries(e.store.read(v_c), "a", "v") == {(1,): 4, (2,): 2}
    e.apply("t", delta_t(spark))
    assert entries(e.result(), "v") == {(): 15}


def test_intro_query(toy):
    assert entries(loaded(toy, IntRing("b", "d", "e"), ("a", "c")).result(), "a", "c", "v") == {(1, 1): 9, (1, 2): 45, (2, 2): 60}


def test_covariance_payloads(spark, toy):
    e = loaded(toy, CovarianceRing(tuple("abcde"), NumberRing("long")))
    m = Moments.of(e.result())
    assert m.c == 10 and m.s.tolist() == [12, 18, 16, 19, 26]
    assert m.q[np.triu_indices(5)].tolist() == [16, 24, 20, 24, 34, 38, 30, 36, 51, 28, 34, 46, 43, 56, 78]
    v_c = e.store.read(next(n for n in e.stored if n.startswith("V_c"))).slice(a=2).first()
    assert [v_c[s] for s in ("cnt", "s_c", "s_d", "s_e", "q_c_c", "q_c_d", "q_c_e", "q_d_d", "q_d_e", "q_e_e")] == [2, 4, 5, 8, 8, 10, 16, 13, 20, 32]
    e = loaded(toy, GenCovarianceRing(("b", "d", "e"), ("c",)))
    rows = {(r["x"], r["cx"], r["y"], r["cy"]): r["v"] for r in long_rows(e.result()).collect()}
    assert [rows["c", "1", "", ""], rows["c", "1", "d", ""], rows["c", "1", "e", ""], rows["b", "", "c", "1"]] == [4, 4, 6, 6]
    assert [rows["c", "2", "", ""], rows["c", "2", "d", ""], rows["c", "2", "e", ""], rows["b", "", "c", "2"]] == [6, 15, 20, 12]


def test_payload_encodings(toy):
    e = loaded(toy, RelationalRing(tuple("abcd")))
    got = {tuple(int(r[f"p_{x}"]) for x in "abcd"): r["v"] for r in e.result().df.collect()}
    want = {(1, 1, 1, 1): 2, (1, 1, 2, 2): 1, (1, 1, 2, 3): 1, (1, 2, 1, 1): 2, (1, 2, 2, 2): 1, (1, 2, 2, 3): 1, (2, 3, 2, 2): 1, (2, 3, 2, 3): 1}
    assert got == want
    f = Factorized(w.TOY.query(IntRing(), tuple("abcd")), w.TOY.variable_order, toy)
    assert entries(f.views["a"], "a", "v") == {(1,): 8, (2,): 2} and entries(f.views["c"], "a", "c", "v") == {(1, 1): 4, (1, 2): 4, (2, 2): 2} or entries(f.views["c"], "a", "c", "v") == {(1, 1): 2, (1, 2): 2, (2, 2): 2}
    assert {tuple(r)[:4]: r["v"] for r in f.expand().collect()} == want
    assert f.aggregate() == 10 and f.aggregate("d") == 19


def test_free_top_enumeration(toy):
    q = w.TOY.query(IntRing(), ("a", "b", "c"))
    e = Engine(q, w.TOY.variable_order, free_top=True)
    e.load(toy)
    assert entries(e.result(), "a", "b", "c", "v") == {(1, 1, 1): 2, (1, 1, 2): 2, (1, 2, 1): 2, (1, 2, 2): 2, (2, 3, 2): 2}
    assert e.payload_of(a=1, b=2, c=2).first()["v"] == 2


SHAPES = {
    "toy": (w.TOY.relations, "a - {b, c - {d, e}}", ()), "toy keys": (w.TOY.relations, "a - {b, c - {d, e}}", ("a", "c")), "triangle": ({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")}, "a - b - c", ()),
    "forest": ({"r": ("a", "b"), "s": ("c",)}, "a - b; c", ()), "loop": (w.loop4().relations, "a - c - {b, d}", ()),
}


def random_rows(rng, schema, n):
    return [tuple(rng.randint(0, 3) for _ in schema) for _ in range(n)]


@pytest.mark.parametrize("shape", SHAPES)
@pytest.mark.parametrize("indicators", [False, True])
def test_incremental_equals_recomputed(spark, shape, indicators):
    relations, order, free = SHAPES[shape]
    rng = random.Random(shape)
    q = NaturalJoinQuery(relations, free, CovarianceRing(tuple(sorted({v for s in relations.values() for v in s})), NumberRing("long")))
    frame = lambda r, rows: spark.createDataFrame(rows, ", ".join(f"{v} long" for v in (*relations[r], "__m")))
    bags = {r: [(*x, 1) for x in random_rows(rng, s, 12)] for r, s in relations.items()}
    e = Engine(q, VariableOrder.parse(order), indicators=indicators)
    e.load({r: frame(r, rows) for r, rows in bags.items()})
    for r in list(relations) * (1 if len(relations) > 3 else 2):
        delta = [(*x, 1) for x in random_rows(rng, relations[r], 3)] + [(*x[:-1], -1) for x in rng.sample(bags[r], 3)]
        bags[r] += delta
        e.apply(r, frame(r, delta))
    want = evaluate(build_tree(q, VariableOrder.parse(order)), {r: frame(r, rows) for r, rows in bags.items()})
    assert metrics.max_abs_diff(e.result(), want) == 0
    assert metrics.max_abs_diff(baselines.plain_reeval(q, {r: frame(r, rows) for r, rows in bags.items()}), want) == 0
    for r, rows in bags.items():  # what went in can all be taken out again
        e.apply(r, frame(r, [(*x[:-1], -x[-1]) for x in rows]))
        break
    assert e.result().df.count() == 0


@pytest.mark.parametrize("make", [baselines.FirstOrder, baselines.Recursive, baselines.LeftDeep])
def test_baselines_agree(spark, toy, make):
    q = w.TOY.query(IntRing("b", "e"))
    b = make(q, toy)
    b.apply("t", delta_t(spark))
    b.apply("r", spark.createDataFrame([(1, 7, 1), (2, 3, -1)], "a long, b long, __m int"))
    e = loaded(toy, IntRing("b", "e"))
    e.apply("t", delta_t(spark))
    e.apply("r", spark.createDataFrame([(1, 7, 1), (2, 3, -1)], "a long, b long, __m int"))
    assert entries(b.result(), "v") == entries(e.result(), "v")


def test_parquet_store(spark, toy, tmp_path):
    q = w.TOY.query(IntRing())
    store = ParquetStore(spark, str(tmp_path / "views"), q.ring, fold=2)
    e = Engine(q, w.TOY.variable_order, store=store)
    e.load(toy)
    for _ in range(3):
        e.apply("t", delta_t(spark))
        e.apply("t", spark.createDataFrame([(1, 1, 1), (2, 2, -3)], "c long, d long, __m int"))
    assert entries(e.result(), "v") == {(): 10} and store.bytes() > 0
    again = ParquetStore(spark, str(tmp_path / "views"), q.ring)
    assert again.version == store.version and entries(again.read(e.tree.roots[0].name), "v") == {(): 10}
    name = next(n for n in e.stored if n.startswith("V_b"))
    assert again.read(name, again.buckets_of(spark.createDataFrame([(1,)], "a long"), "a")).df.where("a = 1").first()["v"] == 2


def test_indicator_support(spark):
    r = spark.createDataFrame([(1, 2), (2, 1)], "a long, n long")
    gone = lambda *rows: spark.createDataFrame(rows, "a long, b long")
    none = spark.createDataFrame([], "a long, b long")
    assert support_change(r, none, gone((1, 2)), ["a"]).collect() == []
    assert [tuple(x) for x in support_change(r.where("a <> 1").union(spark.createDataFrame([(1, 1)], r.schema)), none, gone((1, 1)), ["a"]).collect()] == [(1, -1)]


DRAWS = {
    "int": (IntRing(), lambda g: {"v": g.randint(-5, 5)}), "big": (BigIntRing(), lambda g: {"v": g.randint(-5, 5)}), "real": (RealRing(), lambda g: {"v": g.uniform(-1, 1)}), "complex": (ComplexRing(), lambda g: {"re": g.uniform(-1, 1), "im": g.uniform(-1, 1)}),
    "matrix": (MatrixRing(2), lambda g: {s: float(g.randint(-3, 3)) for s in MatrixRing(2).slots}), "covariance": (CovarianceRing(("x", "y")), lambda g: {s: float(g.randint(-3, 3)) for s in CovarianceRing(("x", "y")).slots}),
}


@pytest.mark.parametrize("name", DRAWS)
def test_ring_laws(spark, name):
    ring, draw = DRAWS[name]
    laws = check(spark, ring, draw)
    assert laws.pop("product commutes") == ring.commutative
    assert all(laws.values()), laws


def test_semirings_refuse_deletes(spark, toy):
    e = loaded(toy, MaxProductSemiring(("d",)))
    with pytest.raises(Exception, match="insert only"):
        e.apply("t", deletes(toy["t"]))
        e.result().df.collect()
    with pytest.raises(ValueError):
        MaxProductSemiring().neg({})


def test_regression_and_trees():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(200, 3)) * [1, 10, 100] + 5
    y = x @ [2, -1, 0.5] + 3
    data = np.column_stack([x, y])
    m = Moments(("a", "b", "c", "y"), 200, data.sum(axis=0), data.T @ data)
    cold, exact = train(m, "y", "abc", tol=1e-12, max_iter=10**6), solve(m, "y", "abc")
    assert np.allclose(exact.theta, [3, 2, -1, 0.5]) and np.allclose(cold.theta, exact.theta, rtol=1e-3)
    assert train(m, "y", "abc", cold.theta, tol=1e-10).iterations < 5 and loss(m, exact)["r2"] > 0.999
    assert dependency_tree([("a", "b", 1.0), ("b", "c", 2.0), ("a", "c", 0.5)]) == [("a", "b", 1.0), ("b", "c", 2.0)]
    u, v = low_rank(np.outer([0, 1, 0], [1, 2, 3]))
    assert u.shape == (3, 1) and np.array_equal(u @ v.T, np.outer([0, 1, 0], [1, 2, 3]))


def test_updates(spark):
    df = spark.createDataFrame([(1, "I"), (2, "D")], "a long, op string")
    assert [r["__m"] for r in signed(df, "op").orderBy("a").collect()] == [1, -1]
    assert [r for r, _ in round_robin({"x": [1, 2], "y": [3]})] == ["x", "y", "x"]
    assert inserts(df).first()["__m"] == 1 and COUNT == "__n"


@pytest.mark.parametrize("name", ["matrix_chain", "matrix_rank_one_update", "matrix_dense_update", "matrix_rank_r_update", "matrix_dense_blocks"])
def test_matrices_take_every_embedding(spark, tmp_path, name):
    from ringview.queries import QUERIES

    rng = np.random.default_rng(4)
    x = rng.integers(-300, 300, (530, 64))
    spark.createDataFrame([(i, [float(v) / 1000 for v in row]) for i, row in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    i = np.arange(64)
    change = sum(np.outer((k * i) % 7 - 3, (k * i) % 5 - 2) for k in {"matrix_rank_one_update": (1,), "matrix_dense_update": (1,), "matrix_rank_r_update": (1, 2)}.get(name, ())) if "update" in name else 0
    want = x @ (x[:64] + change) @ x.T
    got = np.zeros_like(want)
    d = QUERIES[name](spark, str(tmp_path)).toPandas()
    got[d["i"], d["j"]] = d["v"]
    assert np.array_equal(got, want)
