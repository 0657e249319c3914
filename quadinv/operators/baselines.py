"""Other ways to invert: block Gauss-Jordan, block Cholesky, and one task for the whole matrix."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.local import inverse_or_nan
from ..plans.lineage import materialize
from . import ops
from .blocks import BLOCK_DDL, BlockFrame, arrays, pad, record
from .gemm import BROADCAST_BYTES, multiply
from .invert import InvertOptions, _cropped
from .leaf import invert_leaf
from .verify import verified


def local_inverse(a: BlockFrame, solver: str = "lu") -> BlockFrame:
    """Inverse of a in one task of one executor."""
    return invert_leaf(a, solver)


def _strip(df: DataFrame, condition, key: str, name: str, bytes_: int) -> DataFrame:
    """Blocks that meet the condition, as (key, name), sent to all tasks if they are few enough."""
    part = df.filter(condition).select(key, F.col("v").alias(name))
    return F.broadcast(part) if bytes_ <= BROADCAST_BYTES else part


def gauss_jordan_blocks(a: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """In-place elimination by one pivot block after another: as many rounds as there are block rows, each over all blocks."""
    opts = opts or InvertOptions()
    n, size = a.meta.logical_rows, a.meta.block
    if not a.meta.square:
        raise ValueError("only a square matrix has an inverse")
    now = materialize(a.df, opts.materialize)
    source = a.of(now, logical_rows=a.meta.rows, logical_cols=a.meta.rows)
    for k in range(a.meta.grid_rows):
        strip = 8 * size * a.meta.rows
        pivot = now.filter((F.col("bi") == k) & (F.col("bj") == k)).select(F.col("v").alias("p"))
        both = now.join(_strip(now, F.col("bi") == k, "bj", "row", strip), "bj").join(_strip(now, F.col("bj") == k, "bi", "col", strip), "bi")
        both = both.crossJoin(F.broadcast(pivot)).select("bi", "bj", "nr", "nc", "v", "row", "col", "p")  # one row: the pivot block

        def run(batches, k=k):
            for batch in batches:
                keys = list(zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist()))
                out = []
                for (i, j), block, row, col, p in zip(keys, *(arrays(batch, name) for name in ("v", "row", "col", "p"))):
                    inner = inverse_or_nan(p)
                    if i == k:
                        out.append(inner if j == k else inner @ row)
                    else:
                        out.append(-col @ inner if j == k else block - col @ (inner @ row))
                yield record(keys, out)

        now = materialize(both.mapInArrow(run, BLOCK_DDL), opts.materialize)
    out = a.of(now)
    verified(source, out, opts.tolerance, "a leading block of the matrix is singular or nearly so")
    return _cropped(out, n, a)


def cholesky_factor(a: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """Lower factor of a symmetric positive definite a, block column by block column."""
    opts = opts or InvertOptions()
    size, grid = a.meta.block, a.meta.grid_rows
    now = materialize(a.df.filter("bi >= bj"), opts.materialize)
    columns = []
    for k in range(grid):
        pivot = now.filter((F.col("bi") == k) & (F.col("bj") == k)).select(F.col("v").alias("p"))
        panel = now.filter(F.col("bj") == k).crossJoin(F.broadcast(pivot)).select("bi", "bj", "nr", "nc", "v", "p")

        def column(batches, k=k):
            for batch in batches:
                keys = list(zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist()))
                out = []
                for (i, _), block, p in zip(keys, arrays(batch), arrays(batch, "p")):
                    try:
                        lower = np.linalg.cholesky(p)
                    except np.linalg.LinAlgError:
                        lower = np.full(p.shape, np.nan)
                    out.append(lower if i == k else np.linalg.solve(lower, block.T).T)
                yield record(keys, out)

        done = materialize(panel.mapInArrow(column, BLOCK_DDL), opts.materialize)
        columns.append(done)
        strip = 8 * size * a.meta.rows
        rest = now.filter(F.col("bj") > k).join(_strip(done, F.lit(True), "bi", "left", strip), "bi")
        across = _strip(done.select(F.col("bi").alias("bj"), "v"), F.lit(True), "bj", "right", strip)

        def trailing(batches):
            for batch in batches:
                keys = list(zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist()))
                yield record(keys, [b - x @ y.T for b, x, y in zip(arrays(batch), arrays(batch, "left"), arrays(batch, "right"))])

        if k + 1 < grid:
            now = materialize(rest.join(across, "bj").select("bi", "bj", "nr", "nc", "v", "left", "right").mapInArrow(trailing, BLOCK_DDL), opts.materialize)
    upper = a.df.filter("bi < bj").withColumn("v", F.transform("v", lambda x: F.lit(0.0))).select(ops.BLOCK)
    return a.of(reduce(DataFrame.unionByName, columns).unionByName(upper), symmetric=False)


def lower_inverse(a: BlockFrame, opts: InvertOptions) -> BlockFrame:
    """Inverse of a lower triangular a: two half-size inverses and two products a level."""
    if a.meta.grid_rows == 1:
        return invert_leaf(a)
    first, low, second = ops.quadrant(a, 1, 1), ops.quadrant(a, 2, 1), ops.quadrant(a, 2, 2)
    one, two = (x.of(materialize(lower_inverse(x, opts).df, opts.materialize)) for x in (first, second))
    corner = multiply(multiply(two, low), one, alpha=-1.0)
    return ops.assemble(one, ops.quadrant(a, 1, 2), corner, two)


def cholesky_blocks(a: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """Inverse of a symmetric positive definite a by its Cholesky factor."""
    opts = opts or InvertOptions()
    n = a.meta.logical_rows
    padded = pad(a)
    padded = padded.of(padded.df, logical_rows=padded.meta.rows, logical_cols=padded.meta.rows)
    inner = lower_inverse(padded.of(materialize(cholesky_factor(padded, opts).df, opts.materialize)), opts)
    inner = inner.of(materialize(inner.df, opts.materialize))
    out = multiply(ops.transpose(inner), inner)
    out = out.of(materialize(out.df, opts.materialize))
    verified(padded, out, opts.tolerance, "the matrix is not positive definite, or badly conditioned")
    return _cropped(out, n, a)
