"""Inversion of a leaf of the recursion, on the executor that holds it (or, to compare, on the driver)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..functions.local import inverse_or_nan
from .blocks import BLOCK_DDL, BlockFrame, arrays, from_numpy, record, to_numpy


def invert_leaf(a: BlockFrame, solver: str = "lu", site: str = "executor") -> BlockFrame:
    """Inverse of a small a in one task; NaN throughout where it is singular.

    A single block is inverted where it lies, without a shuffle; several blocks are gathered in one task first.
    """
    if not a.meta.square:
        raise ValueError("only a square matrix has an inverse")
    if site == "driver":
        return from_numpy(a.spark, inverse_or_nan(to_numpy(a), solver), a.meta.block, a.meta.symmetric)
    if a.meta.grid_rows == 1:

        def one(batches):
            for batch in batches:
                keys = list(zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist()))
                yield record(keys, [inverse_or_nan(b, solver) for b in arrays(batch)])

        return a.of(a.df.mapInArrow(one, BLOCK_DDL))
    return a.of(a.df.withColumn("all", F.lit(0)).groupBy("all").applyInArrow(_gathered(a.meta.grid_rows, lambda whole: [inverse_or_nan(whole, solver)]), BLOCK_DDL))


def _gathered(grid: int, work):
    """A group function: the whole matrix of a grid of blocks goes to work, whose one array comes back in blocks."""

    def run(key, group):
        found = dict(zip(zip(group.column("bi").to_pylist(), group.column("bj").to_pylist()), arrays(group)))
        (out,) = work(np.block([[found[i, j] for j in range(grid)] for i in range(grid)]))
        size = len(out) // grid
        keys = [(i, j) for i in range(grid) for j in range(grid)]
        return pa.Table.from_batches([record(keys, [out[i * size : (i + 1) * size, j * size : (j + 1) * size] for i, j in keys])])

    return run
