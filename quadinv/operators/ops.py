"""Narrow operations on block matrices, and those that join two of them block by block.

The recursion builds hundreds of small plans, so that expressions are given as SQL text: one call to the JVM each, not one a term.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import BLOCK_DDL, BlockFrame, arrays, record

KEYS = ["bi", "bj"]
BLOCK = ["bi", "bj", "nr", "nc", "v"]


def _half(a: BlockFrame) -> int:
    if not a.meta.square or a.meta.grid_rows % 2:
        raise ValueError(f"a grid of {a.meta.grid_rows} x {a.meta.grid_cols} blocks has no four equal quadrants")
    return a.meta.grid_rows // 2


def split(a: BlockFrame) -> DataFrame:
    """Every block with its quadrant q (0 to 3, row by row) and its place inside of it; a projection, nothing moves."""
    h = _half(a)
    return a.df.select(
        (2 * F.floor(F.col("bi") / h) + F.floor(F.col("bj") / h)).cast("int").alias("q"),
        (F.col("bi") % h).alias("bi"),
        (F.col("bj") % h).alias("bj"),
        "nr",
        "nc",
        "v",
    )


def quadrant(a: BlockFrame, x: int, y: int, mode: str = "direct") -> BlockFrame:
    """Quadrant in row x and column y (1 or 2) of a.

    mode: `tagged` filters the result of split; `direct` filters by the block numbers, so that the predicate can reach a scan.
    """
    if x not in (1, 2) or y not in (1, 2):
        raise ValueError("quadrants are numbered 1 and 2 each way")
    h = _half(a)
    if mode == "tagged":
        part = split(a).filter(F.col("q") == 2 * (x - 1) + y - 1).drop("q")
    else:
        side = lambda key, z: f"{key} >= {h}" if z == 2 else f"{key} < {h}"
        part = a.df.filter(f"{side('bi', x)} and {side('bj', y)}")
        if x == 2 or y == 2:
            part = part.selectExpr(f"bi - {(x - 1) * h} as bi", f"bj - {(y - 1) * h} as bj", "nr", "nc", "v")
    size = h * a.meta.block
    return a.of(part, logical_rows=size, logical_cols=size, grid_rows=h, grid_cols=h, symmetric=a.meta.symmetric and x == y)


def assemble(q11: BlockFrame, q12: BlockFrame, q21: BlockFrame, q22: BlockFrame) -> BlockFrame:
    """The matrix of four quadrants; projections and a union."""
    h = q11.meta.grid_rows
    moved = [q.df.selectExpr(f"bi + {dx * h} as bi", f"bj + {dy * h} as bj", "nr", "nc", "v") for q, dx, dy in ((q11, 0, 0), (q12, 0, 1), (q21, 1, 0), (q22, 1, 1))]
    size = 2 * h * q11.meta.block
    return q11.of(reduce(DataFrame.union, moved), logical_rows=size, logical_cols=size, grid_rows=2 * h, grid_cols=2 * h, symmetric=False)


def scale(a: BlockFrame, s: float) -> BlockFrame:
    return a.of(a.df.selectExpr("bi", "bj", "nr", "nc", f"transform(v, x -> x * double('{float(s)!r}')) as v"))


def negate(a: BlockFrame) -> BlockFrame:
    return a.of(a.df.selectExpr("bi", "bj", "nr", "nc", "transform(v, x -> -x) as v"))


def _zipped(a: BlockFrame, b: BlockFrame, combine) -> BlockFrame:
    if (a.meta.grid_rows, a.meta.grid_cols, a.meta.block) != (b.meta.grid_rows, b.meta.grid_cols, b.meta.block):
        raise ValueError("matrices of different shape")
    other = b.df.select(*KEYS, F.col("v").alias("w"))
    both = a.df.join(other, KEYS).select("bi", "bj", "nr", "nc", F.zip_with("v", "w", combine).alias("v"))
    return a.of(both, symmetric=a.meta.symmetric and b.meta.symmetric)


def subtract(a: BlockFrame, b: BlockFrame) -> BlockFrame:
    return _zipped(a, b, lambda x, y: x - y)


def add(a: BlockFrame, b: BlockFrame) -> BlockFrame:
    return _zipped(a, b, lambda x, y: x + y)


def transpose(a: BlockFrame) -> BlockFrame:
    def run(batches):
        for batch in batches:
            keys = zip(batch.column("bj").to_pylist(), batch.column("bi").to_pylist())
            yield record(list(keys), [b.T for b in arrays(batch)])

    m = a.meta
    return a.of(a.df.mapInArrow(run, BLOCK_DDL), logical_rows=m.logical_cols, logical_cols=m.logical_rows, grid_rows=m.grid_cols, grid_cols=m.grid_rows)


def tiled(a: BlockFrame, t: int) -> BlockFrame:
    """a in blocks of a t-th of the size; narrow."""
    size = a.meta.block // t

    def run(batches):
        for batch in batches:
            for bi, bj, block in zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist(), arrays(batch)):
                yield record([(bi * t + i, bj * t + j) for i in range(t) for j in range(t)], [block[i * size : (i + 1) * size, j * size : (j + 1) * size] for i in range(t) for j in range(t)])

    m = a.meta
    return a.of(a.df.mapInArrow(run, BLOCK_DDL), block=size, grid_rows=m.grid_rows * t, grid_cols=m.grid_cols * t)


def merged(a: BlockFrame, t: int) -> BlockFrame:
    """Each t x t blocks of a as one; every block moves once."""

    def run(key, group):
        found = dict(zip(zip(group.column("bi").to_pylist(), group.column("bj").to_pylist()), arrays(group)))
        rows, cols = sorted({k[0] for k in found}), sorted({k[1] for k in found})
        return pa.Table.from_batches([record([(key[0].as_py(), key[1].as_py())], [np.block([[found[i, j] for j in cols] for i in rows])])])

    m = a.meta
    placed = a.df.selectExpr(f"bi div {t} as mi", f"bj div {t} as mj", "*")
    return a.of(placed.groupBy("mi", "mj").applyInArrow(run, BLOCK_DDL), block=m.block * t, grid_rows=m.grid_rows // t, grid_cols=m.grid_cols // t)
