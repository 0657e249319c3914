"""Products of block matrices: C <- alpha A B + beta C, by several plans.

`grid3d`     coarse cells over (block row, block column, inner block); each cell is one task's local product, the cells of one
             output block are summed. Bounded memory and traffic; the default. One cell is the plan for small operands.
`replicate`  each block goes to every output block that it feeds, and an output block is computed in one group.
`contract`   join on the inner block number, one local product a pair, sums by output block.
`broadcast`  the smaller operand goes to all tasks, the larger isn't shuffled; refused beyond a size.
`cells`      join and sum of single cells in SQL; for small or sparse matrices.
`seven_product`  one level of the seven-product scheme over quadrants, each product by `grid3d`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.local import precise_product, two_sum
from . import ops
from .blocks import BLOCK_DDL, BlockFrame, arrays, from_coo, record, to_coo

STRATEGIES = ("grid3d", "replicate", "contract", "broadcast", "cells", "seven_product")
#: Bytes of both operands and the output that one task of grid3d may hold.
CELL_BYTES = 192 << 20
#: Largest operand that is broadcast.
BROADCAST_BYTES = 64 << 20
#: Multiplications below which a task isn't divided for the sake of idle cores.
LEAST_WORK = 1 << 27


def _product_meta(a: BlockFrame, b: BlockFrame) -> dict:
    if a.meta.grid_cols != b.meta.grid_rows or a.meta.block != b.meta.block or a.meta.logical_cols != b.meta.logical_rows:
        raise ValueError(f"no product of {a.meta} and {b.meta}")
    return {"logical_cols": b.meta.logical_cols, "grid_cols": b.meta.grid_cols, "symmetric": False}


def _summed(parts: DataFrame) -> DataFrame:
    """Partial blocks of one place added up; each partition's own first, so that a place sends one block a partition."""

    def local(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        size = 0
        for batch in batches:
            for key, block in zip(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()), arrays(batch)):
                if key in total:
                    total[key] += block
                else:
                    total[key] = block.copy(order="F")
                    size += block.nbytes
                if size > CELL_BYTES:
                    yield record(list(total), list(total.values()))
                    total, size = {}, 0
        if total:
            yield record(list(total), list(total.values()))

    def final(key, group):
        blocks = arrays(group)
        total = blocks[0].copy(order="F")
        for block in blocks[1:]:
            total += block
        return pa.Table.from_batches([record([(key[0].as_py(), key[1].as_py())], [total])])

    return parts.mapInArrow(local, BLOCK_DDL).groupBy("bi", "bj").applyInArrow(final, BLOCK_DDL)


def cell_shape(rows: int, cols: int, inner: int, block: int, cell_bytes: int = CELL_BYTES, parallelism: int = 1) -> tuple[int, int, int]:
    """Blocks of a cell in rows, columns and inner blocks: as many as a task's memory bears, but fewer where that would leave cores idle.

    Halving rows or columns sends one operand once more, halving the inner blocks sends partial results: the last resort.
    """
    h, w, d = rows, cols, inner
    while h * w * d > 1 and 8 * block**2 * (h * d + d * w + h * w) > cell_bytes:
        h, w, d = (-(-h // 2), w, d) if h >= max(w, d) else (h, -(-w // 2), d) if w >= d else (h, w, -(-d // 2))
    while -(-rows // h) * -(-cols // w) * -(-inner // d) < parallelism and h * w * d * block**3 > LEAST_WORK and max(h, w, d) > 1:
        h, w, d = (-(-h // 2), w, d) if h >= w and h > 1 else (h, -(-w // 2), d) if w > 1 else (h, w, -(-d // 2))
    return h, w, d


def _spread(name: str, n: int) -> str:
    """name over 0 .. n - 1, one row each."""
    return f"explode(sequence(0L, {n - 1}L)) as {name}" if n > 1 else f"0L as {name}"


def _grid3d(a: BlockFrame, b: BlockFrame, shape: tuple[int, int, int], alpha: float, beta: float, c: BlockFrame | None) -> DataFrame:
    h, w, d = shape
    high, wide, deep = -(-a.meta.grid_rows // h), -(-b.meta.grid_cols // w), -(-a.meta.grid_cols // d)
    block = ("bi", "bj", "nr", "nc", "v")
    keyed = a.df.selectExpr(f"bi div {h} as ci", _spread("cj", wide), f"bj div {d} as ct", "0 as side", *block)
    keyed = keyed.union(b.df.selectExpr(_spread("ci", high), f"bj div {w} as cj", f"bi div {d} as ct", "1 as side", *block))
    if c is not None:
        keyed = keyed.union(c.df.selectExpr(f"bi div {h} as ci", f"bj div {w} as cj", "0L as ct", "2 as side", *block))

    def cell(key, group):
        found: dict[int, dict[tuple[int, int], np.ndarray]] = {0: {}, 1: {}, 2: {}}
        for which, bi, bj, block in zip(*(group.column(n).to_pylist() for n in ("side", "bi", "bj")), arrays(group)):
            found[which][bi, bj] = block
        row, col = sorted({k[0] for k in found[0]}), sorted({k[1] for k in found[1]})
        inner = sorted({k[1] for k in found[0]} & {k[0] for k in found[1]})
        out: dict[tuple[int, int], np.ndarray] = {}
        if inner:
            # One product of the cell's strips, so that the library works on large arrays.
            strip = np.block([[found[0][r, k] for k in inner] for r in row]) @ np.block([[found[1][k, s] for s in col] for k in inner])
            y = 0
            for r in row:
                x, height = 0, found[0][r, inner[0]].shape[0]
                for s in col:
                    width = found[1][inner[0], s].shape[1]
                    out[r, s] = alpha * strip[y : y + height, x : x + width]
                    x += width
                y += height
        for where, block in found[2].items():
            out[where] = beta * block + out[where] if where in out else beta * block
        return pa.Table.from_batches([record(list(out), list(out.values()))])

    parts = keyed.groupBy("ci", "cj", "ct").applyInArrow(cell, BLOCK_DDL)
    return parts if deep == 1 else _summed(parts)


def precise_difference(a: BlockFrame, b: BlockFrame, c: BlockFrame, cell_bytes: int = CELL_BYTES) -> BlockFrame:
    """c - a b, rounded once: products and sums carry about twice the digits of a double.

    One output block and as many inner blocks as a task's memory bears make a cell; each sends its sum in two parts.
    """
    meta = _product_meta(a, b)
    d = max(1, min(a.meta.grid_cols, cell_bytes // (8 * a.meta.block**2) // 10))
    deep = -(-a.meta.grid_cols // d)
    block = ("bi", "bj", "nr", "nc", "v")
    keyed = a.df.selectExpr("bi as ci", _spread("cj", b.meta.grid_cols), f"bj div {d} as ct", "0 as side", *block)
    keyed = keyed.union(b.df.selectExpr(_spread("ci", a.meta.grid_rows), "bj as cj", f"bi div {d} as ct", "1 as side", *block))
    keyed = keyed.union(c.df.selectExpr("bi as ci", "bj as cj", "0L as ct", "2 as side", *block))

    def cell(key, group):
        found: dict[int, dict[int, np.ndarray]] = {0: {}, 1: {}, 2: {}}
        for which, bi, bj, x in zip(*(group.column(n).to_pylist() for n in ("side", "bi", "bj")), arrays(group)):
            found[which][bj if which == 0 else bi] = x
        inner, where = sorted(found[0]), (key[0].as_py(), key[1].as_py())
        with np.errstate(all="ignore"):
            hi, lo = precise_product(np.hstack([-found[0][k] for k in inner]), np.vstack([found[1][k] for k in inner]))
            for x in found[2].values():
                hi, lo = two_sum(hi, lo, x)
        return pa.Table.from_batches([record([where], [hi + lo])] if deep == 1 else [record([where, where], [hi, lo])])

    def final(key, group):
        blocks = arrays(group)
        hi, lo = np.zeros_like(blocks[0]), np.zeros_like(blocks[0])
        with np.errstate(all="ignore"):
            for x in blocks:
                hi, lo = two_sum(hi, lo, x)
        return pa.Table.from_batches([record([(key[0].as_py(), key[1].as_py())], [hi + lo])])

    parts = keyed.groupBy("ci", "cj", "ct").applyInArrow(cell, BLOCK_DDL)
    return a.of(parts if deep == 1 else parts.groupBy("bi", "bj").applyInArrow(final, BLOCK_DDL), **meta)


def _replicate(a: BlockFrame, b: BlockFrame, alpha: float) -> DataFrame:
    over = lambda k: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(k - 1).cast("long")))
    own = lambda *names: [F.col(n).alias(n) for n in names]  # noqa: E731  columns of their own where a is b
    left = a.df.select(*own("bi"), F.col("bj").alias("t"), over(b.meta.grid_cols).alias("bj"), *own("nr", "nc", "v"))
    right = b.df.select(over(a.meta.grid_rows).alias("bi"), F.col("bi").alias("t"), *own("bj", "nr", "nc", "v"))

    def product(key, x, y):
        other = dict(zip(y.column("t").to_pylist(), arrays(y)))
        total = None
        for t, block in sorted(zip(x.column("t").to_pylist(), arrays(x)), key=lambda p: p[0]):
            part = block @ other[t]
            total = part if total is None else total + part
        return pa.Table.from_batches([record([(key[0].as_py(), key[1].as_py())], [alpha * total])])

    return left.groupBy("bi", "bj").cogroup(right.groupBy("bi", "bj")).applyInArrow(product, BLOCK_DDL)


def _paired(pairs: DataFrame, alpha: float) -> DataFrame:
    def run(batches):
        for batch in batches:
            keys = zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist())
            yield record(list(keys), [alpha * (x @ y) for x, y in zip(arrays(batch), arrays(batch, "w", "mr", "mc"))])

    return _summed(pairs.select("bi", "bj", "nr", "nc", "v", "mr", "mc", "w").mapInArrow(run, BLOCK_DDL))


def _contract(a: BlockFrame, b: BlockFrame, alpha: float, small: str | None = None) -> DataFrame:
    left = a.df.select("bi", F.col("bj").alias("t"), "nr", "nc", "v")
    right = b.df.select(F.col("bi").alias("t"), "bj", F.col("nr").alias("mr"), F.col("nc").alias("mc"), F.col("v").alias("w"))
    if small == "left":
        left = F.broadcast(left)
    elif small == "right":
        right = F.broadcast(right)
    return _paired(left.join(right, "t"), alpha)


def _cells(a: BlockFrame, b: BlockFrame, alpha: float) -> DataFrame:
    x = to_coo(a).select("i", F.col("j").alias("t"), F.col("x").alias("y"))
    y = to_coo(b).select(F.col("i").alias("t"), "j", F.col("x").alias("z"))
    return x.join(y, "t").groupBy("i", "j").agg((F.lit(alpha) * F.sum(F.col("y") * F.col("z"))).alias("x"))


def _seven(a: BlockFrame, b: BlockFrame, **options) -> BlockFrame:
    """Seven products of sums and differences of quadrants in place of eight."""
    q = lambda m, x, y: ops.quadrant(m, x, y)
    a11, a12, a21, a22 = (q(a, x, y) for x in (1, 2) for y in (1, 2))
    b11, b12, b21, b22 = (q(b, x, y) for x in (1, 2) for y in (1, 2))
    times = lambda x, y: multiply(x, y, **options)
    m1 = times(ops.add(a11, a22), ops.add(b11, b22))
    m2 = times(ops.add(a21, a22), b11)
    m3 = times(a11, ops.subtract(b12, b22))
    m4 = times(a22, ops.subtract(b21, b11))
    m5 = times(ops.add(a11, a12), b22)
    m6 = times(ops.subtract(a21, a11), ops.add(b11, b12))
    m7 = times(ops.subtract(a12, a22), ops.add(b21, b22))
    c11 = ops.add(ops.subtract(ops.add(m1, m4), m5), m7)
    c22 = ops.add(ops.subtract(ops.add(m1, m3), m2), m6)
    return ops.assemble(c11, ops.add(m3, m5), ops.add(m2, m4), c22)


def multiply(a: BlockFrame, b: BlockFrame, strategy: str = "grid3d", alpha: float = 1.0, beta: float = 0.0, c: BlockFrame | None = None, cells: int | None = None) -> BlockFrame:
    """alpha a b + beta c. cells: for grid3d, how many cells a side, instead of what memory and parallelism suggest."""
    meta = _product_meta(a, b)
    if strategy not in STRATEGIES:
        raise ValueError(f"unknown strategy {strategy!r}")
    if strategy == "grid3d":
        size = (a.meta.grid_rows, b.meta.grid_cols, a.meta.grid_cols)
        shape = tuple(-(-x // cells) for x in size) if cells else cell_shape(*size, a.meta.block, parallelism=a.spark.sparkContext.defaultParallelism)
        return a.of(_grid3d(a, b, shape, alpha, beta, c if beta else None), **meta)
    if strategy == "replicate":
        out = a.of(_replicate(a, b, alpha), **meta)
    elif strategy == "contract":
        out = a.of(_contract(a, b, alpha), **meta)
    elif strategy == "broadcast":
        small, size = min((("left", a.meta.bytes), ("right", b.meta.bytes)), key=lambda p: p[1])
        if size > BROADCAST_BYTES:
            raise ValueError(f"{size} bytes are too many to broadcast; take grid3d")
        out = a.of(_contract(a, b, alpha, small), **meta)
    elif strategy == "cells":
        out = from_coo(_cells(a, b, alpha), a.meta.logical_rows, a.meta.block, b.meta.logical_cols, fill=0.0)
    else:
        if a.meta.grid_rows % 2 or b.meta.grid_cols % 2 or not (a.meta.square and b.meta.square):
            raise ValueError("seven_product takes two square matrices of an even number of blocks a side")
        made = _seven(a, b)
        out = a.of((ops.scale(made, alpha) if alpha != 1.0 else made).df, **meta)
    if c is not None and beta:
        more = ops.scale(c, beta) if beta != 1.0 else c
        out = a.of(ops.add(out, more).df, **meta)
    return out
