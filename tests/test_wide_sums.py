"""Sums beyond 64 bits of values that fit."""

from ringview.functions.rings import IntRing
from ringview.operators.baselines import recursive_scalar
from ringview.plans.query import NaturalJoinQuery
from ringview.queries import QUERIES
from ringview.sources.updates import SIGN


def test_a_sum_of_squares_beyond_64_bits(spark, tmp_path):
    keys = [3_000_000_000 - i for i in range(12)]
    spark.createDataFrame([(k, k % 2) for k in keys], "c_custkey long, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(s, s % 2) for s in range(6)], "s_suppkey long, s_nationkey int").write.parquet(f"{tmp_path}/supplier.parquet")
    spark.createDataFrame([(n, 0) for n in range(2)], "n_nationkey int, n_regionkey int").write.parquet(f"{tmp_path}/nation.parquet")
    out = QUERIES["baseline_recursive_scalar"](spark, str(tmp_path))
    assert [tuple(r) for r in out.collect()] == [(36, 3 * sum(keys), 3 * sum(k * k for k in keys))]
    assert [t for _, t in out.dtypes] == ["bigint", "bigint", "decimal(38,0)"]  # BIGINT where it fits, as in SQL


def test_changes_meet_wide_views(spark):
    big, q = 2**31 - 1, NaturalJoinQuery({"r": ("a", "x"), "s": ("a", "y")})
    rows = lambda *r, c: spark.createDataFrame(list(r), f"a long, {c} long")
    db = {"r": rows((1, -big), (1, big), (2, 5), c="x"), "s": rows((1, 7), (2, 8), (2, 9), c="y")}
    each = recursive_scalar(q, db, ("x",), wide=True)
    for e in each.values():
        e.apply("r", spark.createDataFrame([(1, big, 1), (1, big - 1, 1), (2, 5, -1)], f"a long, x long, {SIGN} int"))
        e.apply("s", spark.createDataFrame([(1, 10, 1), (1, 11, 1)], f"a long, y long, {SIGN} int"))
    left = [-big, big, big, big - 1]
    want = {"cnt": 12, "s_x": 3 * sum(left), "q_x_x": 3 * sum(x * x for x in left)}
    assert {n: e.result().df.first()["v"] for n, e in each.items()} == want and want["q_x_x"] > 1 << 63
    assert each["cnt"].q.ring.of_tuples.type_name == "long" and IntRing().of_tuples == IntRing()
