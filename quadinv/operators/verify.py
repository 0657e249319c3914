"""Whether a computed inverse is one: what its product with the matrix does to a few random sign vectors.

Without pivoting between blocks, a leading block that is singular, or nearly so, rarely gives NaN in floating point; it gives
a finite matrix that is far from the inverse. For E = A X - I and a vector v of random signs, entry i of E v is the size of
row i of E on average, so that a handful of vectors shows a wrong row almost surely, for two passes over n^2 cells.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..functions.local import PROBES, signs
from .blocks import BlockFrame, arrays

#: Up to this size the products with the vectors are added up on the driver, which spares a shuffle; beyond it by the executors.
DRIVER_BYTES = 32 << 20
#: Largest size of the vectors that is broadcast; beyond it they are joined.
BROADCAST_BYTES = 64 << 20
STRIP_DDL = "bi long, y array<double>"
STRIP = pa.schema([("bi", pa.int64()), ("y", pa.list_(pa.float64()))])


def _strips(found: dict[int, np.ndarray]) -> pa.RecordBatch:
    values = np.concatenate([s.ravel() for s in found.values()]) if found else np.empty(0)
    offsets = np.arange(len(found) + 1, dtype=np.int32) * (len(values) // max(1, len(found)))
    return pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))], schema=STRIP)


def _products(batches, strip):
    """Of each partition's blocks, the sum by block row of block times strip(block column, batch, row of it)."""
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for k, (bi, bj, block) in enumerate(zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist(), arrays(batch))):
            with np.errstate(all="ignore"):
                part = block @ strip(bj, batch, k)
            total[bi] = total[bi] + part if bi in total else part
    if total:
        yield _strips(total)


def _sum(key, group):
    rows = np.stack([np.asarray(v.values.to_numpy()) for v in group.column("y")])
    return pa.Table.from_batches([_strips({key[0].as_py(): rows.sum(axis=0)})])


def probed_residual(a: BlockFrame, x: BlockFrame) -> float:
    """Largest absolute entry of A (X V) - V for PROBES sign vectors V; infinite where X isn't finite."""
    size, n = a.meta.block, a.meta.rows
    drawn = lambda bj, batch, k: signs(bj * size, size)
    first = x.df.mapInArrow(lambda batches: _products(batches, drawn), STRIP_DDL)
    if 8 * PROBES * n * a.meta.grid_cols <= DRIVER_BYTES:
        y = _gathered(first, a)
        second = a.df.mapInArrow(lambda batches: _products(batches, lambda bj, batch, k: y[bj]), STRIP_DDL)
        z = _gathered(second, a)
        return _worst(max((np.abs(z[k] - signs(k * size, size)).max() for k in z), default=0.0))
    y = first.groupBy("bi").applyInArrow(_sum, STRIP_DDL).select(F.col("bi").alias("bj"), F.col("y").alias("w"))
    if 8 * PROBES * n <= BROADCAST_BYTES:
        y = F.broadcast(y)

    def joined(bj, batch, k):
        column = batch.column("w")
        at = column.offsets.to_numpy()
        return column.values.to_numpy()[at[k] : at[k + 1]].reshape(size, PROBES)

    def off(key, group):
        (row,) = _sum(key, group).column("y").to_pylist()
        away = np.abs(np.asarray(row).reshape(size, PROBES) - signs(key[0].as_py() * size, size)).max()
        return pa.table({"off": pa.array([_worst(away)], pa.float64())})

    second = a.df.join(y, "bj").select("bi", "bj", "nr", "nc", "v", "w").mapInArrow(lambda batches: _products(batches, joined), STRIP_DDL)
    return second.groupBy("bi").applyInArrow(off, "off double").agg(F.max("off")).first()[0]


def probed_size(r: BlockFrame) -> float:
    """Largest absolute entry of R V for the sign vectors V: what probed_residual gives for R = I - A X, without the rounding of A (X V)."""
    size = r.meta.block
    strips = r.df.mapInArrow(lambda batches: _products(batches, lambda bj, batch, k: signs(bj * size, size)), STRIP_DDL)

    def most(key, group):
        (row,) = _sum(key, group).column("y").to_pylist()
        return pa.table({"off": pa.array([_worst(np.abs(np.asarray(row)).max(initial=0.0))], pa.float64())})

    return strips.groupBy("bi").applyInArrow(most, "off double").agg(F.max("off")).first()[0]


def _worst(value: float) -> float:
    return float(value) if np.isfinite(value) else float("inf")


def _gathered(strips, a: BlockFrame) -> dict[int, np.ndarray]:
    total = {k: np.zeros((a.meta.block, PROBES)) for k in range(a.meta.grid_rows)}
    table = strips.toArrow()
    for bi, y in zip(table.column("bi").to_pylist(), table.column("y")):
        total[bi] += np.asarray(y.values.to_numpy()).reshape(a.meta.block, PROBES)
    return total


def verified(a: BlockFrame, x: BlockFrame, tolerance: float, what: str) -> float:
    """The probed residual, or an ArithmeticError where it is over tolerance."""
    off = probed_residual(a, x)
    if not off <= tolerance:
        raise ArithmeticError(f"{what}: the residual of the inverse is {off:.3g}, over {tolerance:g}")
    return off
