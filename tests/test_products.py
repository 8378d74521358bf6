"""Products that are kept as factors: no cell of the product crosses a shuffle, sums are exact, zeros are left out."""

import numpy as np
import pytest

from ringview.functions.rings import NumberRing
from ringview.operators import matrix_chain as mc
from ringview.operators.factored import rank_one
from ringview.operators.matrix_chain import BlockMatrix, MatrixChain


def coo(spark, m):
    return spark.createDataFrame([(i, j, m[i, j].item()) for i in range(m.shape[0]) for j in range(m.shape[1])], f"i long, j long, v {'double' if m.dtype.kind == 'f' else 'long'}")


def dense(df, shape):
    out, rows = np.zeros(shape, dtype=object), df.collect()
    assert len({(r[0], r[1]) for r in rows}) == len(rows) and all(r[2] != 0 for r in rows)
    for r in rows:
        out[r[0], r[1]] = r[2]
    return out


def test_changes_of_each_matrix_are_kept_as_factors(spark, monkeypatch):
    monkeypatch.setattr(mc, "WAITING", 2)  # folded on the way
    rng = np.random.default_rng(1)
    a, b, c = (rng.integers(-4, 5, s) for s in ((9, 3), (3, 4), (4, 7)))
    chain = MatrixChain([coo(spark, m) for m in (a, b, c)], [9, 3, 4, 7])
    b[1] += [5, 6, 7, 8]
    chain.update_row(1, 1, spark.createDataFrame([(j, 5 + j) for j in range(4)], "j long, v long"))
    a[:, 2] += np.arange(9)
    chain.update_column(0, 2, spark.range(9).selectExpr("id", "id AS v"))
    c[3, 6] += 11
    chain.update_entry(2, 3, 6, 11)
    d = rng.integers(-2, 3, b.shape)
    b += d
    chain.update_dense(1, coo(spark, d))
    assert np.array_equal(dense(chain.product(), (9, 7)), a @ b @ c)
    assert chain.root.name not in chain.engine.store.names() and len(chain.terms) <= 3


@pytest.mark.parametrize("limit", [1 << 14, 1], ids=["strips", "cells"])
def test_cells_that_cancel_are_left_out(spark, monkeypatch, limit):
    monkeypatch.setattr(mc, "INNER", limit)
    a, b = np.array([[1, 1], [2, 3]]), np.array([[1, 4], [-1, 4]])
    chain = MatrixChain([coo(spark, a), coo(spark, b)], [2, 2, 2])
    assert np.array_equal(dense(chain.product(), (2, 2)), a @ b)
    chain.update(0, rank_one(spark.createDataFrame([(0, 1)], "x1 long, v long"), spark.createDataFrame([(0, 2)], "x2 long, v long"), "x1", "x2"))
    a[0, 0] += 2
    assert np.array_equal(dense(chain.product(), (2, 2)), a @ b)


def test_large_numbers_stay_exact(spark):
    a, b = np.array([[2**40 + 1, 3]]), np.array([[2**21 + 1], [-5]])
    assert dense(MatrixChain([coo(spark, a), coo(spark, b)], [1, 2, 1]).product(), (1, 1))[0, 0] == (2**40 + 1) * (2**21 + 1) - 15
    with pytest.raises(Exception, match="leaves 64 bits"):
        MatrixChain([coo(spark, a * 2**10), coo(spark, b * 2**10)], [1, 2, 1]).product().collect()
    real = MatrixChain([coo(spark, a / 2), coo(spark, b / 2)], [1, 2, 1], ring=NumberRing("double")).product()
    assert real.first()["v"] == pytest.approx(float(a[0].astype(float) @ b[:, 0]) / 4)


@pytest.mark.parametrize("which", ["chain", "blocks"])
def test_no_cell_of_a_product_is_shuffled(spark, which):
    rng = np.random.default_rng(2)
    a, b = rng.integers(1, 5, (40, 3)), rng.integers(1, 5, (3, 50))
    if which == "chain":
        out = MatrixChain([coo(spark, a), coo(spark, b)], [40, 3, 50]).product()
    else:
        out = (BlockMatrix.of(coo(spark, a), 8) @ BlockMatrix.of(coo(spark, b), 8)).cells()
    assert np.array_equal(dense(out, (40, 50)), a @ b)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    top = plan[: plan.index("Join")]
    assert "Aggregate" not in top and "Repartition" not in top
