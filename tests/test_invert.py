"""Inverses: algebraic invariants, closed forms, options, failures."""

from fractions import Fraction

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from quadinv import apps
from quadinv.functions.local import SOLVERS, inverse, lu_unpivoted, probed, quad_invert
from quadinv.operators import baselines, blocklu, ops, verify
from quadinv.operators.blocks import from_coo, from_numpy, to_coo, to_numpy
from quadinv.operators.gemm import precise_difference
from quadinv.operators.invert import InvertOptions, quad_inverse
from quadinv.plans import costmodel
from quadinv.sources import matrices


def dominant(n, seed=0):
    return np.random.default_rng(seed).random((n, n)) + n * np.eye(n)


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 20), st.integers(1, 8), st.integers(0, 99), st.sampled_from(SOLVERS))
def test_serial_quadrant_inversion(n, threshold, seed, solver):
    a = dominant(n, seed)
    if solver == "cholesky":  # the complement's sign is turned, so only the whole matrix is a leaf
        a, threshold = a @ a.T, n
    assert np.abs(a @ quad_invert(a, threshold, solver) - np.eye(n)).max() < 1e-9


@pytest.mark.parametrize("solver", SOLVERS)
def test_solvers_reject_singular(solver):
    with pytest.raises(np.linalg.LinAlgError):
        inverse(np.zeros((3, 3)), solver)


def test_lu_unpivoted():
    a = dominant(6)
    lower, upper = lu_unpivoted(a)
    assert np.allclose(lower @ upper, a) and np.allclose(np.triu(lower, 1), 0) and np.allclose(np.tril(upper, -1), 0)


@settings(max_examples=6, deadline=None, suppress_health_check=list(HealthCheck))
@given(st.integers(1, 21), st.integers(2, 9), st.integers(0, 99))
def test_inverse_of_any_order(spark, n, block, seed):
    a = dominant(n, seed)
    x = to_numpy(quad_inverse(from_numpy(spark, a, block)))
    assert np.abs(a @ x - np.eye(n)).max() < 1e-9 and np.abs(x @ a - np.eye(n)).max() < 1e-9


def test_invariants(spark):
    a = dominant(16)
    x = quad_inverse(from_numpy(spark, a, 4))
    assert np.allclose(to_numpy(quad_inverse(x)), a)
    assert np.allclose(to_numpy(quad_inverse(ops.transpose(from_numpy(spark, a, 4)))), to_numpy(x).T)
    assert np.allclose(to_numpy(quad_inverse(ops.scale(from_numpy(spark, a, 4), 2.0))), to_numpy(x) / 2)
    s = a + a.T
    y = to_numpy(quad_inverse(from_numpy(spark, s, 4, symmetric=True)))
    assert np.allclose(y, y.T) and np.allclose(y, np.linalg.inv(s))


@pytest.mark.parametrize("opts", [dict(leaf_blocks=2), dict(split_mode="tagged"), dict(schur="plain"), dict(fuse=False), dict(timed=True), dict(parallel_panels=True), dict(materialize="parquet"), dict(materialize="persist"), dict(strategy="contract"), dict(strategy="replicate"), dict(leaf_site="driver"), dict(refine=1), dict(leaf_solver="svd"), dict(cells=2), dict(tiles=2), dict(tiles=4, leaf_blocks=2)])
def test_options_agree(spark, opts):
    a = dominant(16)
    assert np.allclose(to_numpy(quad_inverse(from_numpy(spark, a, 4), InvertOptions(**opts))), np.linalg.inv(a))


def test_closed_forms(spark):
    x = to_numpy(quad_inverse(matrices.min_ij(spark, 8, 2)))
    assert np.allclose(x, np.diag([2.0] * 7 + [1.0]) - np.eye(8, k=1) - np.eye(8, k=-1))
    h = matrices.hadamard(spark, 8, 2)
    assert np.allclose(to_numpy(quad_inverse(h)), to_numpy(h).T / 8)
    assert np.allclose(to_numpy(quad_inverse(matrices.ones_shift(spark, 6, 2))), (np.eye(6) - 2 / 15) / 3)
    s = matrices.swap(spark, 8, 2)
    assert np.allclose(to_numpy(quad_inverse(s)), to_numpy(s))


def test_singular(spark):
    with pytest.raises(ArithmeticError):
        quad_inverse(matrices.swap(spark, 8, 2), InvertOptions(on_singular="raise"))
    with pytest.raises(ArithmeticError):
        quad_inverse(from_numpy(spark, np.zeros((4, 4)), 2))
    with pytest.raises(ArithmeticError):
        blocklu.lu_inverse(matrices.swap(spark, 8, 2))


def nearly_singular(n, seed):
    """A well-conditioned matrix whose leading quadrant lacks one rank, but for rounding."""
    draw, h = np.random.default_rng(seed), n // 2
    a = draw.standard_normal((n, n))
    u, s, v = np.linalg.svd(a[:h, :h])
    s[-1] = 0.0
    a[:h, :h] = (u * s) @ v
    return a


@pytest.mark.parametrize("n, b, seed", [(64, 2, 0), (64, 4, 1), (128, 2, 2), (128, 4, 3)])
def test_nearly_singular_leading_block(spark, n, b, seed):
    a = nearly_singular(n, seed)
    frame = from_numpy(spark, a, n // b)
    opts = InvertOptions()
    x = to_numpy(quad_inverse(frame, opts))
    assert np.abs(a @ x - np.eye(n)).max() < 1e-6 and np.abs(x - inverse(a, "gauss_jordan")).max() < 1e-6 * np.abs(x).max()
    for way in (lambda f: quad_inverse(f, InvertOptions(on_singular="raise")), blocklu.lu_inverse, baselines.gauss_jordan_blocks, apps.logdet):
        with pytest.raises(ArithmeticError):
            way(frame)
    with pytest.raises(np.linalg.LinAlgError):
        quad_invert(a, n // b)


def test_small_pivot_is_mended(spark):
    """A leading quadrant that is badly conditioned, but regular: Newton steps bring the residual under the tolerance."""
    a = nearly_singular(16, 5)
    u, s, v = np.linalg.svd(a[:8, :8])
    s[-1] = 1e-6
    a[:8, :8] = (u * s) @ v
    opts = InvertOptions(on_singular="raise", tolerance=1e-11)
    x = to_numpy(quad_inverse(from_numpy(spark, a, 4), opts))
    assert opts.trace.residual <= 1e-11 and np.abs(a @ x - np.eye(16)).max() < 1e-10


def test_too_badly_conditioned_for_any_way(spark):
    with pytest.raises(ArithmeticError):
        quad_inverse(matrices.hilbert(spark, 16, 4))


@pytest.mark.parametrize("driver_bytes, broadcast_bytes", [(1 << 30, 1 << 30), (0, 1 << 30), (0, 0)])
def test_probed_residual(spark, monkeypatch, driver_bytes, broadcast_bytes):
    monkeypatch.setattr(verify, "DRIVER_BYTES", driver_bytes)
    monkeypatch.setattr(verify, "BROADCAST_BYTES", broadcast_bytes)
    a = dominant(12)
    x = np.linalg.inv(a)
    good = verify.probed_residual(from_numpy(spark, a, 4), from_numpy(spark, x, 4))
    assert good < 1e-12
    x[7, 3] += 1e-3
    off = verify.probed_residual(from_numpy(spark, a, 4), from_numpy(spark, x, 4))
    assert np.isclose(off, probed(a, x)) and off > 1e-4
    x[0, 0] = np.nan
    assert verify.probed_residual(from_numpy(spark, a, 4), from_numpy(spark, x, 4)) == float("inf")


@pytest.mark.parametrize("b", [1, 2, 4, 8])
def test_logdet_of_leaves(spark, b):
    for seed in range(2):
        a = np.random.default_rng(seed).standard_normal((8, 8)) + np.diag([3, -3, 3, 3, -3, 3, 3, 3])
        sign, log = np.linalg.slogdet(a)
        for opts in (InvertOptions(), InvertOptions(schur="plain")):
            got = apps.logdet(from_numpy(spark, a, 8 // b), opts)
            assert got[0] == sign and abs(got[1] - log) < 1e-8


def test_not_square(spark):
    with pytest.raises(ValueError):
        quad_inverse(from_numpy(spark, np.ones((4, 6)), 2))


def cells(spark, rows):
    return spark.createDataFrame(rows, "i long, j long, x double")


@pytest.mark.parametrize("rows, fill", [([(0, 0, 1.0), (0, 0, 2.0), (1, 1, 1.0)], 0.0), ([(0, 0, 1.0)], None), ([(0, 0, float("nan"))], 0.0), ([(0, 0, None)], 0.0), ([(5, 0, 1.0)], 0.0), ([(None, 0, 1.0), (None, 0, 1.0)], 0.0), ([], None)])
def test_cells_refused(spark, rows, fill):
    with pytest.raises(Exception):
        from_coo(cells(spark, rows), 2, 2, fill=fill).df.collect()


def test_empty_cells_with_fill_and_order_one(spark):
    assert not to_numpy(from_coo(cells(spark, []), 3, 2, fill=0.0)).any()
    assert to_numpy(quad_inverse(from_coo(cells(spark, [(0, 0, 4.0)]), 1, 1)))[0, 0] == 0.25


def test_baselines_agree(spark):
    a = dominant(16)
    a = a + a.T
    want, frame = np.linalg.inv(a), from_numpy(spark, a, 4)
    for way in (blocklu.lu_inverse, baselines.gauss_jordan_blocks, baselines.cholesky_blocks, baselines.local_inverse):
        assert np.allclose(to_numpy(way(frame)), want), way
    lower, upper = blocklu.lu_factors(frame)
    assert np.allclose(to_numpy(lower) @ to_numpy(upper), a)


@pytest.mark.parametrize("b", [1, 2, 4, 8])
def test_counts(spark, b):
    opts, lu = InvertOptions(), InvertOptions()
    a = from_numpy(spark, dominant(2 * b), 2)
    quad_inverse(a, opts)
    for op, n in costmodel.expected_counts(b).items():
        assert opts.trace.count(op) == n, op
    if b > 1:
        blocklu.lu_inverse(a, lu)
        for op, n in costmodel.expected_lu_counts(b).items():
            assert lu.trace.count(op) == n, op


def test_plan_stays_small(spark):
    sizes = [len(quad_inverse(from_numpy(spark, dominant(2 * b), 2)).df._jdf.queryExecution().toString()) for b in (2, 8)]
    assert sizes[1] < 2 * sizes[0]


def test_applications(spark):
    a = dominant(8)
    frame = from_numpy(spark, a, 4)
    sign, log = apps.logdet(frame)
    want = np.linalg.slogdet(a)
    assert sign == want[0] and abs(log - want[1]) < 1e-9
    got = dict(apps.matvec(frame, spark.createDataFrame([(k, float(k)) for k in range(8)], "j long, x double")).collect())
    assert np.allclose([got[k] for k in range(8)], a @ np.arange(8))
    assert np.allclose(to_numpy(apps.solve(frame, from_numpy(spark, np.ones((8, 4)), 4))), np.linalg.solve(a, np.ones((8, 4))))
    assert to_coo(frame).count() == 64


def test_counts_of_few_types_are_mended(spark):
    """C C' + 25 I of rank 6 but for the 25 I: the leading blocks lose digits and the probed residual comes near 1."""
    counts = np.random.default_rng(2).integers(7600, 8400, (25, 6)).astype(float)
    cells = counts @ counts.T + 25 * np.eye(25)
    x = to_numpy(quad_inverse(from_numpy(spark, cells, 8)))
    inner = np.linalg.inv(25 * np.eye(6) + counts.T @ counts)
    assert np.abs(x - (np.eye(25) - counts @ inner @ counts.T) / 25).max() < 1e-6


def exact_inverse(a):
    """By elimination in fractions."""
    n = len(a)
    rows = [[Fraction(float(v)) for v in row] + [Fraction(int(i == j)) for j in range(n)] for i, row in enumerate(a)]
    for k in range(n):
        rows[k] = [v / rows[k][k] for v in rows[k]]
        for i in range(n):
            if i != k:
                rows[i] = [x - rows[i][k] * y for x, y in zip(rows[i], rows[k])]
    return np.array([[float(v) for v in row[n:]] for row in rows])


def test_counts_far_larger_than_the_shift(spark):
    """As above at condition 2.4e9, where Newton steps from the first inverse diverge; digits past those of a residual in doubles count too."""
    counts = np.random.default_rng(1).poisson(20000, (25, 6)).astype(float)
    cells = counts @ counts.T + 25 * np.eye(25)
    assert np.abs(to_numpy(quad_inverse(from_numpy(spark, cells, 8))) - exact_inverse(cells)).max() < 1e-11


def test_precise_difference(spark):
    draw = np.random.default_rng(3)
    a, b = draw.standard_normal((11, 11)) * 1e8, draw.standard_normal((11, 11))
    c = np.array([[float(sum(Fraction(x) * Fraction(y) for x, y in zip(row, col))) for col in b.T.tolist()] for row in a.tolist()])
    want = np.array([[float(Fraction(c[i, j]) - sum(Fraction(x) * Fraction(y) for x, y in zip(a[i].tolist(), b[:, j].tolist()))) for j in range(11)] for i in range(11)])
    frames = [from_numpy(spark, x, 4) for x in (a, b, c)]
    for cell_bytes in (1, 1 << 20):  # inner blocks apart, and together
        assert np.abs(to_numpy(precise_difference(*frames, cell_bytes=cell_bytes)) - want).max() < 1e-18
