"""Uses of an inverse: systems of equations, regression, Markov chains, input-output tables, distances, determinants."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.blocks import BlockFrame, arrays, from_coo, to_coo, to_numpy
from .operators.gemm import BROADCAST_BYTES, multiply
from .operators.invert import InvertOptions, quad_inverse
from .plans.lineage import materialize
from .plans.trace import RunTrace


def matvec(a: BlockFrame, x: DataFrame) -> DataFrame:
    """(i, y) with y = a x for x of (j, x); the vector is sent to all tasks if it is small, else joined."""
    vector = x.select("j", F.col("x").alias("w"))
    if 16 * a.meta.logical_cols <= BROADCAST_BYTES:
        vector = F.broadcast(vector)
    return to_coo(a).join(vector, "j").groupBy("i").agg(F.sum(F.col("x") * F.col("w")).alias("y"))


def solve(a: BlockFrame, rhs: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """The X with a X = rhs."""
    return multiply(quad_inverse(a, opts), rhs)


def linear_regression(df: DataFrame, features: list[str], target: str, block: int = 2) -> DataFrame:
    """(i, y): coefficients of the least-squares fit, the constant first; one pass over the rows, then a small inverse."""
    cols = [F.lit(1.0), *[F.col(f).cast("double") for f in features]]
    y, k = F.col(target).cast("double"), len(cols)
    sums = df.agg(*[F.sum(cols[i] * cols[j]).alias(f"s{i}_{j}") for i in range(k) for j in range(i, k)], *[F.sum(cols[i] * y).alias(f"t{i}") for i in range(k)])
    sums = materialize(sums)
    long = lambda v: F.lit(v).cast("long")
    cells = sums.select(F.explode(F.array(*[F.struct(long(i).alias("i"), long(j).alias("j"), F.col(f"s{min(i, j)}_{max(i, j)}").alias("x")) for i in range(k) for j in range(k)])).alias("c")).select("c.*")
    right = sums.select(F.explode(F.array(*[F.struct(long(i).alias("j"), F.col(f"t{i}").alias("x")) for i in range(k)])).alias("c")).select("c.*")
    return matvec(quad_inverse(from_coo(cells, k, min(block, k))), right)


def markov_fundamental(damped: DataFrame, n: int, block: int = 2) -> DataFrame:
    """Inverse of I - c P as cells: expected discounted visits of j from i."""
    return to_coo(quad_inverse(from_coo(damped, n, block)))


def leontief(damped: DataFrame, demand: DataFrame, n: int, block: int = 8) -> DataFrame:
    """(i, y): output that meets the demand (j, x), for cells of I - c T."""
    return matvec(quad_inverse(from_coo(damped, n, block)), demand)


def mahalanobis(vectors: DataFrame, key: str, column: str, inverse: BlockFrame, max_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """(key, d2): x' M x for every row's vector x and a small inverse M, which is sent to all tasks."""
    m = vectors.sparkSession.sparkContext.broadcast(to_numpy(inverse, max_bytes))

    def run(batches):
        for batch in batches:
            rows = np.asarray(batch.column(1).flatten().to_numpy(), dtype=float).reshape(batch.num_rows, -1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.einsum("ni,ij,nj->n", rows, m.value, rows))], names=[key, "d2"])

    kind = vectors.schema[key].dataType.simpleString()
    return vectors.filter(F.col(column).isNotNull()).select(key, column).mapInArrow(run, f"{key} {kind}, d2 double")


def logdet(a: BlockFrame, opts: InvertOptions | None = None) -> tuple[float, float]:
    """(sign, log of the absolute determinant), a by-product of the inverse: its leaves' determinants, inverted, and the sign of
    each complement that was turned. The inverse is probed like any other; an ArithmeticError where a leading block is singular or nearly so.
    """
    trace = RunTrace()
    quad_inverse(a, replace(opts or InvertOptions(), leaf_blocks=1, keep_leaves=True, on_singular="raise", trace=trace))

    def run(batches):
        for batch in batches:
            found = [np.linalg.slogdet(b) for b in arrays(batch)]
            yield pa.RecordBatch.from_arrays([pa.array([float(f[0]) for f in found]), pa.array([float(f[1]) for f in found])], names=["sign", "log"])

    leaves = reduce(DataFrame.unionByName, [leaf.df for leaf in trace.leaves])
    row = leaves.mapInArrow(run, "sign double, log double").agg(F.product("sign").alias("sign"), F.sum("log").alias("log")).first()
    return row.sign * (-1.0) ** trace.turned, -row.log
