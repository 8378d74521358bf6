"""Cells on their way to a product: one shuffle a side, as pieces without keys."""

import re

import numpy as np
import pytest

from ringview.operators import matrix_chain as mc
from ringview.operators.matrix_chain import BlockMatrix, MatrixChain, _piece, _whole


def coo(spark, cells):
    return spark.createDataFrame([(int(i), int(j), int(v)) for i, j, v in cells], "i long, j long, v long")


def every(m):
    return [(i, j, m[i, j]) for i in range(m.shape[0]) for j in range(m.shape[1])]


def found(df):
    return {(r[0], r[1]): r[2] for r in df.collect()}


def exchanges(df):
    plan = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"(?<!Broadcast)Exchange (?:hash|range|RoundRobin|Single)", plan))


@pytest.mark.parametrize("v", [[1, -2, 3], [40_000, -1, 0], [2**40, -(2**62), 5], [0.5, -3.0, 1e300], [2.0, -3.0, 4.0]], ids=["two", "four", "eight", "real", "whole"])
def test_pieces_keep_each_number(v):
    v = np.array(v)
    p = _piece(np.array([0, 3, 2]), np.array([1, 0, 1]), v)
    m = _whole([p, p], 4, 2, "<f8" if v.dtype.kind == "f" else "<i8")
    assert [m[0, 1], m[3, 0], m[2, 1]] == [2 * x for x in v.tolist()] and np.count_nonzero(m) == np.count_nonzero(v)


def test_a_side_of_a_product_is_shuffled_once(spark):
    rng = np.random.default_rng(3)
    a, b = rng.integers(1, 5, (40, 3)), rng.integers(1, 5, (3, 50))
    out = MatrixChain([coo(spark, every(a)), coo(spark, every(b))], [40, 3, 50]).product()
    assert exchanges(out) == 2
    blocks = BlockMatrix.of(coo(spark, every(a)), 8) @ BlockMatrix.of(coo(spark, every(b)), 8)
    assert exchanges(blocks.cells()) == 4  # one for the blocks, one for their rows
    want = {(i, j): v for i, j, v in every(a @ b)}
    assert found(out) == want and found(blocks.cells()) == want


def test_pairs_of_partitions_are_bounded(spark, monkeypatch):
    """Also where a repartition by a key gets more partitions than it asks for."""
    frame = type(spark.range(0))
    monkeypatch.setattr(frame, "repartition", lambda self, n, *by, f=frame.repartition: f(self, max(n, 211), *by))
    a = np.arange(1, 13).reshape(4, 3)
    monkeypatch.setattr(mc, "STRIP_ROWS", 1)
    out = MatrixChain([coo(spark, every(a)), coo(spark, every(a.T))], [4, 3, 4]).product()
    assert out.rdd.getNumPartitions() <= max(32, 4 * spark.sparkContext.defaultParallelism) ** 2
    assert found(out) == {(i, j): v for i, j, v in every(a @ a.T)}


def test_cells_that_are_there_twice_and_negative_places(spark):
    a, b = [(-9, 0, 2), (-9, 0, 3), (7, 0, 1), (7, 5, 4)], [(0, -1, 10), (5, 1, 1), (5, 1, 1)]
    want = {(-9, -1): 50, (7, -1): 10, (7, 1): 8}
    assert found(MatrixChain([coo(spark, a), coo(spark, b)], [2, 2, 2]).product()) == want
    assert found((BlockMatrix.of(coo(spark, a), 4) @ BlockMatrix.of(coo(spark, b), 4)).cells()) == want
