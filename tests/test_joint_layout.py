"""The layout of joint categories gives what the long one gives, with a row for each tuple at most."""

from ringview.functions.rings import GenCovarianceRing, IntRing, JointCovarianceRing
from ringview.operators.covariance import long_rows
from ringview.operators.engine import Engine
from ringview.operators.relation import KeyedRelation
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder


def test_joint_rows_under_changes_and_null_categories(spark):
    relations, order = {"r": ("k", "p", "a", "b"), "s": ("k", "n", "c")}, "k - {p - a - b, n - c}"
    db = {
        "r": spark.createDataFrame([(i % 3, i - 4, None if i % 5 == 0 else f"a{i % 2}", f"b{i % 4}") for i in range(20)], "k long, p long, a string, b string"),
        "s": spark.createDataFrame([(i % 3, 2 * i, f"c{i % 2}") for i in range(6)], "k long, n long, c string"),
    }
    delta = spark.createDataFrame([(0, -4, None, "b0", -1), (1, 7, "new", "b1", 2), (2, -2, "a0", "b2", -1)], "k long, p long, a string, b string, __m int")
    out = []
    for ring in (GenCovarianceRing, JointCovarianceRing):
        e = Engine(NaturalJoinQuery(relations, (), ring(("p", "n"), ("a", "b", "c"))), VariableOrder.parse(order))
        e.load(db)
        e.apply("r", delta)
        out.append((sorted(tuple(map(str, r)) for r in long_rows(e.result()).collect()), {n: e.store.size(n) for n in e.stored}))
        rows = e
    assert out[0][0] == out[1][0] and len(out[0][0]) > 50
    views = [n for n in rows.stored if "V_" in n and n != rows.tree.roots[0].name]
    tuples = KeyedRelation.from_bag(db["r"], relations["r"], IntRing()).size() + 1
    assert views and all(out[1][1][n] <= tuples for n in views) and sum(out[1][1][n] for n in views) * 4 < sum(out[0][1][n] for n in views)
