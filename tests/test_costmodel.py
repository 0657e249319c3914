"""Cost model: sums against closed forms in exact arithmetic, what is irregular in print, shapes of the published series."""

from fractions import Fraction as Q

import pytest

from quadinv.plans import costmodel as cm
from quadinv.plans import metrics, published
from quadinv.plans.trace import RunTrace

BS = [2, 4, 8, 16, 32]


def total(b, term, m=None, nodes=lambda i: 2**i):
    return sum(nodes(i) * term(i) for i in range(cm.levels(b) if m is None else m))


@pytest.mark.parametrize("b", BS)
def test_quadinv_sums(b):
    n = 64
    rows = {k: v for k, (_, v) in cm.quadinv_rows(n, b).items()}
    assert total(b, lambda i: Q(b * b, 4**i)) == rows["split"]
    assert total(b, lambda i: Q(b * b, 4 ** (i + 1))) * 4 == rows["quadrant_map"]
    assert float(total(b, lambda i: Q(n**3, 8 ** (i + 1)))) == pytest.approx(rows["multiply"])
    assert float(total(b, lambda i: Q(b, 2 ** (i + 1)) * Q(n * n, 4 ** (i + 1)))) == pytest.approx(rows["multiply_comm"])
    assert float(total(b, lambda i: Q(n * n, 4 ** (i + 1)))) == pytest.approx(rows["subtract"])
    assert float(total(b, lambda i: Q(b * b, 4 ** (i + 1)))) == rows["scale"] == rows["assemble"]


@pytest.mark.parametrize("b", BS)
def test_filter_row_is_printed_too_large(b):
    """Four filters over all blocks of a node sum to 8 b^2 - 8 b, not to the printed 8 b^2 - 4 b."""
    assert total(b, lambda i: 4 * Q(b * b, 4**i)) == 8 * b * b - 8 * b == cm.quadinv_rows(64, b)["quadrant_filter"][1] - 4 * b


@pytest.mark.parametrize("b", BS[1:])
def test_lu_sums(b):
    n, rows = 64, {k: v for k, (_, v) in cm.lu_rows(64, b).items()}
    inner = lambda term: total(b, term, nodes=lambda i: 2**i - 1)
    assert float(inner(lambda i: Q(b * b, 4**i))) == pytest.approx(rows["split"])
    assert float(inner(lambda i: 4 * Q(n**3, 8**i))) == pytest.approx(rows["multiply_large"], rel=0.3)
    assert float(inner(lambda i: Q(n * n, 4**i))) == pytest.approx(rows["subtract"])


def test_lu_communication_is_negative_in_print():
    assert cm.lu_rows(64, 2)["multiply_comm_large"][1] < 0
    assert all(work >= 0 for _, work, _ in cm.steps(64, 2, 30, "blocklu", "rederived", "per_level"))


def test_editions_differ_where_print_cannot_be_meant():
    assert cm.quadinv_cost(4096, 8, 30, "printed") < cm.quadinv_cost(4096, 8, 30, "fixed")
    assert cm.lu_cost(4096, 8, 30, "printed") > cm.lu_cost(4096, 8, 30, "fixed")
    six = sum(6 * v if k == "multiply" else 2 * v if k == "subtract" else 0 for k, (_, v) in cm.quadinv_rows(4096, 8).items())
    assert six == pytest.approx(4096**2 * (64 * 4096 - 4096 + 64 - 8) / 64)
    with pytest.raises(ValueError):
        cm.steps(64, 4, 30, edition="printed", policy="per_level")


@pytest.mark.parametrize("n, argmin", [(4096, 16), (8192, 32), (16384, 32)])
def test_minimum_near_the_leaves(n, argmin):
    bs = [2, 4, 8, 16, 32, 64, 128]
    costs = [cm.quadinv_cost(n, b, 30, "fixed", "deepest") for b in bs]
    assert bs[costs.index(min(costs))] == argmin
    assert all(x > y for x, y in zip(costs[: bs.index(argmin)], costs[1:])) and costs[-1] > min(costs)


def test_quadinv_is_cheaper_at_every_division():
    for n in (4096, 8192, 16384):
        for b in (4, 8, 16, 32, 64):
            assert cm.quadinv_cost(n, b, 30, "rederived", "per_level") < cm.lu_cost(n, b, 30, "rederived", "per_level")


def test_calibration_follows_measurement():
    runs = [(n, b, float(s)) for n, row in published.THEORY.items() for b, (_, s) in row.items()]
    weights = cm.calibrate(runs, 30)
    assert all(w >= 0 for w in weights.values())
    off = [abs(cm.predict(weights, n, b, 30) / s - 1) for n, b, s in runs]
    assert sorted(off)[len(off) // 2] < 0.35
    assert 2 <= cm.choose_grid(4096, weights=weights) <= 64


def test_grid_fits_memory():
    assert cm.choose_grid(2**17, cm.ClusterSpec(mem_gb=1.0, overhead_gb=0.1)) >= 64
    assert cm.ClusterSpec().session_conf()["spark.executor.memory"] == "47616m" and cm.ClusterSpec().total_cores == 30


def test_published_series(spark):
    shape = {(r.n, r.method): (r.argmin_b, r.u_shaped) for r in metrics.u_shape(published.sweep(spark)).collect()}
    assert shape[4096, "quadinv"] == (8, True) and shape[16384, "blocklu"] == (32, True) and all(u for _, u in shape.values())
    assert all(r.ratio > 1 for r in metrics.ratio(published.sweep(spark), "blocklu", "quadinv").collect())
    eff = {(r.n, r.cores): r.efficiency for r in metrics.efficiency(published.scaling(spark)).collect()}
    assert eff[4096, 5] == 1 and eff[16384, 25] > 1  # better than ideal, as printed
    gaps = [published.BEST["blocklu"][n] - published.BEST["quadinv"][n] for n in sorted(published.BEST["quadinv"])]
    assert gaps != sorted(gaps)  # the gap doesn't grow monotonically, though the prose says so
    assert published.STEPS["product"][4] > published.STEPS["leaf"][4]  # products lead from b = 4 on
    assert metrics.shuffle_elements(64, 4, "replicate") > metrics.shuffle_elements(64, 4, "grid3d", 2) > 0


def test_trace(spark):
    t = RunTrace(n=8, b=2)
    with t.timed(0, "r", "leaf"):
        pass
    t.add(0, "r", "multiply", 6)
    rows = {r.op: r.calls for r in metrics.step_table(t, spark).collect()}
    assert rows == {"leaf": 1, "multiply": 6, "total": 7} and t.ms("leaf") >= 0


def test_reference_curves_and_ideal_scaling(spark):
    """Doubling the order multiplies the curves by 2 to their exponents; ideal time times cores is constant, and efficiency is one on it."""
    for exponent in (3.0, 3.2):
        assert abs(cm.reference_curve(4096, exponent) / cm.reference_curve(2048, exponent) - 2**exponent) < 1e-9
    assert cm.reference_curve(4096, 3.2) > cm.reference_curve(4096, 3.0)
    assert [metrics.ideal_scaling(120.0, p) for p in (1, 5, 25)] == [120.0, 24.0, 4.8]
    rows = [(4096, p, metrics.ideal_scaling(120.0, p)) for p in (1, 5, 25)]
    assert all(abs(r.efficiency - 1) < 1e-12 and abs(r.ideal - r.seconds) < 1e-12 for r in metrics.efficiency(spark.createDataFrame(rows, "n long, cores int, seconds double")).collect())


def test_cost_queries_follow_the_lines_of_suppliers(spark, tmp_path):
    import __spark_entry__ as entry

    spark.createDataFrame([(1,)] * 40 + [(2,)] * 40 + [(3,)] * 77 + [(None,)], "l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    run = lambda name: entry.queries()[name](spark, str(tmp_path)).collect()
    assert {(r.n, r.b) for r in run("q_cost_quadinv_fixed")} == {(n, b) for n in (40, 77) for b in (2, 4, 8, 16, 32, 64)}
    assert {r.n for r in run("q_pf")} == {r.n for r in run("q_cost_argmin")} == {r.n for r in run("q_cost_table")} == {40, 77}
    assert {r.b: r.gemms for r in run("q_block_gemms")}[4] == 3 * 4 * 15


def test_published_series_are_placed_on_the_lines_of_suppliers(spark, tmp_path):
    import __spark_entry__ as entry

    spark.createDataFrame([(1,)] * 40 + [(2,)] * 40 + [(3,)] * 77, "l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    rows = entry.queries()["q_published_best_ratio"](spark, str(tmp_path)).collect()
    assert {(r.order, r.matrices, r.n) for r in rows} == {(40, 2, 64), (77, 1, 128)}
