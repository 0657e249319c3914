"""Measures: accuracy of an inverse, norms, and what a series of run times shows."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.blocks import BlockFrame, to_coo
from ..operators.invert import check_residual
from ..plans.trace import RunTrace


def norms(a: BlockFrame) -> DataFrame:
    """One row: trace, norm_fro, norm_max, norm_1 (largest column sum), norm_inf (largest row sum)."""
    cells = to_coo(a)
    whole = cells.agg(F.sum(F.when(F.col("i") == F.col("j"), F.col("x")).otherwise(0.0)).alias("trace"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm_fro"), F.max(F.abs("x")).alias("norm_max"))
    by = lambda key, name: cells.groupBy(key).agg(F.sum(F.abs("x")).alias("s")).agg(F.max("s").alias(name))
    return whole.crossJoin(by("j", "norm_1")).crossJoin(by("i", "norm_inf"))  # of one row each


def cond1(a: BlockFrame, x: BlockFrame) -> DataFrame:
    """One row: condition number in the 1-norm from a and its inverse x."""
    one = lambda m, name: to_coo(m).groupBy("j").agg(F.sum(F.abs("x")).alias("s")).agg(F.max("s").alias(name))
    return one(a, "p").crossJoin(one(x, "q")).select((F.col("p") * F.col("q")).alias("cond1"))


def residual(a: BlockFrame, x: BlockFrame) -> DataFrame:
    """One row: max_abs of a x - I, and its Frobenius norm over the root of the order."""
    off = to_coo(check_residual(a, x))
    return off.agg(F.max(F.abs("x")).alias("max_abs"), (F.sqrt(F.sum(F.col("x") * F.col("x"))) / F.lit(float(a.meta.logical_rows) ** 0.5)).alias("fro_scaled"))


def difference(x: BlockFrame, y: BlockFrame) -> DataFrame:
    """One row: largest absolute difference of two matrices."""
    other = to_coo(y).withColumnRenamed("x", "z")
    return to_coo(x).join(other, ["i", "j"]).agg(F.max(F.abs(F.col("x") - F.col("z"))).alias("max_abs"))


def timed_run(work: Callable[[], object]) -> float:
    began = time.perf_counter()
    work()
    return time.perf_counter() - began


def step_table(trace: RunTrace, spark) -> DataFrame:
    """(op, calls, elements, ms) of a run, steps and their total."""
    sums = trace.frame(spark).rollup("op").agg(F.sum("calls").alias("calls"), F.sum("elements").alias("elements"), F.sum("ms").alias("ms"))
    return sums.withColumn("op", F.coalesce("op", F.lit("total")))


def shuffle_elements(n: int, b: int, strategy: str, cells: int = 1) -> int:
    """Matrix elements that one product of two n x n matrices in b x b blocks sends, partial sums included."""
    if strategy == "replicate":
        return 2 * b * n * n
    if strategy == "grid3d":
        return 2 * cells * n * n + (cells * n * n if cells > 1 else 0)
    if strategy == "contract":
        return 2 * n * n + b * n * n
    if strategy == "broadcast":
        return b * n * n
    raise ValueError(f"unknown strategy {strategy!r}")


def best(times: DataFrame) -> DataFrame:
    """(n, method, best_b, seconds): the fastest b of each n and method of (n, method, b, seconds)."""
    w = Window.partitionBy("n", "method").orderBy("seconds", "b")
    return times.withColumn("r", F.row_number().over(w)).filter("r = 1").select("n", "method", F.col("b").alias("best_b"), "seconds")


def ratio(times: DataFrame, over: str, under: str) -> DataFrame:
    """(n, b, ratio): time of one method over that of another at the same n and b."""
    a = times.filter(F.col("method") == over).select("n", "b", F.col("seconds").alias("p"))
    c = times.filter(F.col("method") == under).select("n", "b", F.col("seconds").alias("q"))
    return a.join(c, ["n", "b"]).select("n", "b", (F.col("p") / F.col("q")).alias("ratio"))


def efficiency(times: DataFrame) -> DataFrame:
    """(n, cores, seconds, ideal, efficiency) of (n, cores, seconds), against the run with the fewest cores."""
    w = Window.partitionBy("n").orderBy("cores").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    work = F.first("seconds").over(w) * F.first("cores").over(w)
    return times.select("n", "cores", "seconds", (work / F.col("cores")).alias("ideal"), (work / (F.col("seconds") * F.col("cores"))).alias("efficiency"))


def ideal_scaling(t1: float, p: int) -> float:
    return t1 / p


def u_shape(times: DataFrame) -> DataFrame:
    """(n, method, argmin_b, u_shaped): whether seconds fall strictly up to their minimum and rise strictly after it."""
    low = best(times)
    w = Window.partitionBy("n", "method").orderBy("b")
    step = times.withColumn("change", F.col("seconds") - F.lag("seconds").over(w)).join(low.select("n", "method", "best_b"), ["n", "method"])
    fits = F.col("change").isNull() | F.when(F.col("b") <= F.col("best_b"), F.col("change") < 0).otherwise(F.col("change") > 0)
    return step.groupBy("n", "method").agg(F.first("best_b").alias("argmin_b"), F.bool_and(fits).alias("u_shaped"))


def compare_curves(predicted: DataFrame, measured: DataFrame) -> DataFrame:
    """(n, b, predicted, measured, quotient) of two series (n, b, seconds)."""
    return predicted.withColumnRenamed("seconds", "predicted").join(measured.withColumnRenamed("seconds", "measured"), ["n", "b"]).withColumn("quotient", F.col("predicted") / F.col("measured"))
