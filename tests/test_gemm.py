"""Products and narrow operations, held against numpy and the library's block matrix."""

import numpy as np
import pytest

from quadinv.operators import ops
from quadinv.operators.blocks import crop, from_numpy, pad, reblock, to_numpy
from quadinv.operators.gemm import STRATEGIES, cell_shape, multiply
from quadinv.plans import expr
from quadinv.plans.expr import Assemble, Fused, Inverse, Matrix, Mul, Quad, Scale, Transpose, evaluate, simplify
from quadinv.sources import io


@pytest.fixture(scope="module")
def pair(spark):
    draw = np.random.default_rng(1)
    a, b = draw.random((8, 8)), draw.random((8, 8))
    return a, b, from_numpy(spark, a, 2), from_numpy(spark, b, 2)


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_product(pair, strategy):
    a, b, x, y = pair
    assert np.allclose(to_numpy(multiply(x, y, strategy)), a @ b)
    assert np.allclose(to_numpy(multiply(x, y, strategy, alpha=-2.0, beta=3.0, c=x)), 3 * a - 2 * a @ b)


@pytest.mark.parametrize("cells", [1, 2, 3, 4])
def test_coarse_cells(pair, cells):
    a, b, x, y = pair
    assert np.allclose(to_numpy(multiply(x, y, cells=cells)), a @ b)


def test_rectangular(spark):
    a, b = np.arange(12.0).reshape(3, 4), np.arange(20.0).reshape(4, 5)
    for strategy in ("grid3d", "replicate", "contract", "broadcast", "cells"):
        assert np.allclose(to_numpy(multiply(from_numpy(spark, a, 2), from_numpy(spark, b, 2), strategy)), a @ b)


def test_against_library(spark, pair):
    from pyspark.mllib.linalg import Matrices
    from pyspark.mllib.linalg.distributed import BlockMatrix

    a, b, x, y = pair

    def theirs(m):
        return BlockMatrix(spark.sparkContext.parallelize([((i, j), Matrices.dense(2, 2, m[2 * i : 2 * i + 2, 2 * j : 2 * j + 2].ravel(order="F"))) for i in range(4) for j in range(4)]), 2, 2)

    assert np.allclose(theirs(a).multiply(theirs(b)).toLocalMatrix().toArray(), to_numpy(multiply(x, y)))
    assert np.allclose(theirs(a).subtract(theirs(b)).toLocalMatrix().toArray(), to_numpy(ops.subtract(x, y)))


def test_narrow_operations_do_not_shuffle(pair):
    x = pair[2]
    for made in (ops.split(x), ops.quadrant(x, 1, 2).df, ops.scale(x, 2.0).df, ops.assemble(*(ops.quadrant(x, i, j) for i in (1, 2) for j in (1, 2))).df):
        assert "Exchange" not in made._jdf.queryExecution().executedPlan().toString()


def test_products_have_no_cross_join(pair):
    for strategy in ("grid3d", "replicate", "contract", "cells"):
        plan = multiply(pair[2], pair[3], strategy).df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan
    assert multiply(pair[2], pair[3], "replicate").df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 2


def test_cells_fit_memory(pair):
    assert cell_shape(4, 4, 4, 2, cell_bytes=3 * 8 * 4 * 4) == (2, 2, 2) and cell_shape(4, 4, 4, 512, parallelism=8) == (1, 2, 4) and cell_shape(1, 1, 1, 512, parallelism=8) == (1, 1, 1)
    with pytest.raises(ValueError):
        multiply(pair[2], pad(pair[3], 8))


def test_shapes(spark, pair):
    a, _, x, _ = pair
    assert np.allclose(to_numpy(reblock(x, 3)), a)
    assert np.allclose(to_numpy(crop(x, 5)), a[:5, :5])
    wide = to_numpy(pad(x, 8).of(pad(x, 8).df, logical_rows=16, logical_cols=16))
    assert np.allclose(wide[:8, :8], a) and np.allclose(wide[8:, 8:], np.eye(8)) and not wide[:8, 8:].any()
    with pytest.raises(ValueError):
        ops.quadrant(from_numpy(spark, np.eye(3), 1), 1, 1)
    with pytest.raises(ValueError):
        to_numpy(x, max_bytes=8)


@pytest.mark.parametrize("form", ["parquet", "csv", "json"])
def test_files(spark, pair, tmp_path, form):
    a, _, x, _ = pair
    io.save(x, str(tmp_path / "m"))
    assert np.allclose(to_numpy(io.load(spark, str(tmp_path / "m"))), a)
    io.save_coo(x, str(tmp_path / form), form)
    assert {(r.i, r.j): r.x for r in io.load_coo(spark, str(tmp_path / form), form).collect()} == {(i, j): a[i, j] for i in range(8) for j in range(8)}
    io.noop(x.df)


def test_rules(spark, pair):
    a, b, x, y = pair
    p, q, one = Matrix(x), Matrix(y), Matrix(from_numpy(spark, np.eye(8), 2), identity=True)
    assert simplify(p.T.T) is p and simplify(-(-p)) is p and simplify(Inverse(Inverse(p))) is p
    assert simplify(one @ p) is p and simplify(p @ one) is p
    assert simplify(Transpose(Mul(p, q))) == Mul(Transpose(q), Transpose(p))
    assert simplify(Quad(Assemble(p, q, q, p), 1, 2)) is q
    assert isinstance(simplify(p @ q - p), Fused) and simplify((2.0 * p) @ q) == Scale(Mul(p, q), 2.0)
    assert np.allclose(to_numpy(evaluate(p - 3.0 * (p @ q))), a - 3 * a @ b)
    assert np.allclose(to_numpy(evaluate((p @ q).T)), (a @ b).T)
    assert expr.choose_mul(x, y) == "grid3d"
