"""Distributed block matrices: a DataFrame of dense blocks of one size, and what is known about the whole.

A block is a row (bi, bj, nr, nc, v): block row and column (long, from 0), its size, and its cells column by column. Blocks at
the lower and right border of a matrix whose order is no multiple of the block size are padded when they are built, so that
every block of a frame has the same size; `logical_rows` and `logical_cols` remember the size without padding.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK_DDL = "bi long, bj long, nr int, nc int, v array<double>"
COO_DDL = "i long, j long, x double"
BLOCK_ARROW = pa.schema([("bi", pa.int64()), ("bj", pa.int64()), ("nr", pa.int32()), ("nc", pa.int32()), ("v", pa.list_(pa.float64()))])


@dataclass(frozen=True)
class MatrixMeta:
    logical_rows: int
    logical_cols: int
    block: int
    grid_rows: int
    grid_cols: int
    symmetric: bool = False

    @property
    def rows(self) -> int:
        return self.grid_rows * self.block

    @property
    def cols(self) -> int:
        return self.grid_cols * self.block

    @property
    def square(self) -> bool:
        return self.grid_rows == self.grid_cols

    @property
    def bytes(self) -> int:
        return 8 * self.rows * self.cols


@dataclass(frozen=True)
class BlockFrame:
    df: DataFrame
    meta: MatrixMeta

    @property
    def spark(self) -> SparkSession:
        return self.df.sparkSession

    def of(self, df: DataFrame, **changes) -> BlockFrame:
        return BlockFrame(df, replace(self.meta, **changes))


def meta_for(rows: int, cols: int, block: int, symmetric: bool = False) -> MatrixMeta:
    if rows < 1 or cols < 1 or block < 1:
        raise ValueError(f"no matrix of {rows} x {cols} in blocks of {block}")
    return MatrixMeta(rows, cols, block, -(-rows // block), -(-cols // block), symmetric)


def arrays(batch: pa.RecordBatch | pa.Table, column: str = "v", rows: str = "nr", cols: str = "nc") -> list[np.ndarray]:
    """The blocks of a batch as two-dimensional arrays, views of its values (column-major)."""
    values = batch.column(column)
    if isinstance(values, pa.ChunkedArray):
        values = values.combine_chunks()
    flat, offsets = values.values.to_numpy(), values.offsets.to_numpy()
    sizes = zip(batch.column(rows).to_pylist(), batch.column(cols).to_pylist())
    return [flat[a:b].reshape((r, c), order="F") for a, b, (r, c) in zip(offsets[:-1], offsets[1:], sizes)]


def record(keys: list[tuple[int, int]], blocks: list[np.ndarray]) -> pa.RecordBatch:
    """Rows of BLOCK_DDL."""
    flat = np.concatenate([b.ravel(order="F") for b in blocks]) if blocks else np.empty(0)
    offsets = np.concatenate(([0], np.cumsum([b.size for b in blocks]))).astype(np.int32)
    return pa.RecordBatch.from_arrays(
        [
            pa.array([k[0] for k in keys], pa.int64()),
            pa.array([k[1] for k in keys], pa.int64()),
            pa.array([b.shape[0] for b in blocks], pa.int32()),
            pa.array([b.shape[1] for b in blocks], pa.int32()),
            pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)),
        ],
        schema=BLOCK_ARROW,
    )


def grid_keys(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    return spark.range(rows * cols).select(F.floor(F.col("id") / cols).alias("bi"), (F.col("id") % cols).alias("bj"))


def from_coo(df: DataFrame, n: int, block: int, cols: int | None = None, fill: float | None = None, symmetric: bool = False) -> BlockFrame:
    """Blocks of the n x cols (n x n) matrix with the cells (i, j, x), counted from 0.

    Cells that are missing get `fill`; without a fill they are an error, as are cells given twice or outside of the matrix,
    and values that are null, NaN or infinite. Padding is zero, and one on the diagonal of a square matrix.
    """
    meta = meta_for(n, cols or n, block, symmetric)
    square = meta.logical_rows == meta.logical_cols
    cells = df.select(
        F.floor(F.col("i") / block).cast("long").alias("bi"),
        F.floor(F.col("j") / block).cast("long").alias("bj"),
        F.col("i").cast("long").alias("i"),
        F.col("j").cast("long").alias("j"),
        F.col("x").cast("double").alias("x"),
    )
    # One marker a block, without a cell, so that blocks of which no cell is given exist too.
    none = grid_keys(df.sparkSession, meta.grid_rows, meta.grid_cols).select("bi", "bj", F.lit(None).cast("long").alias("i"), F.lit(None).cast("long").alias("j"), F.lit(0.0).alias("x"))
    rows_, cols_ = meta.logical_rows, meta.logical_cols

    def build(key, group):
        bi, bj = key[0].as_py(), key[1].as_py()
        i, j, x = (group.column(c) for c in ("i", "j", "x"))
        if bi is None or bj is None or i.null_count > 1 or i.null_count != j.null_count or x.null_count:
            raise ValueError("a cell without row, column or value")
        some = i.is_valid()
        i, j, x = (c.filter(some).to_numpy() for c in (i, j, x))
        if not np.isfinite(x).all():
            raise ValueError("a value that is not finite")
        if len(i) and not (0 <= i.min() and i.max() < rows_ and 0 <= j.min() and j.max() < cols_):
            raise ValueError("a cell outside of the matrix")
        out = np.zeros((block, block), order="F")
        height, width = min(block, rows_ - bi * block), min(block, cols_ - bj * block)
        if fill is None and len(i) < height * width:
            raise ValueError("cells are missing and no fill is given")
        out[:height, :width] = fill or 0.0
        at = (j - bj * block) * block + (i - bi * block)
        if len(np.unique(at)) < len(at):
            raise ValueError("a cell is given twice")
        out.ravel(order="K")[at] = x
        if square and bi == bj:
            for k in range(min(height, width), block):
                out[k, k] = 1.0
        return pa.Table.from_batches([record([(bi, bj)], [out])])

    return BlockFrame(cells.unionByName(none).groupBy("bi", "bj").applyInArrow(build, BLOCK_DDL), meta)


def to_coo(a: BlockFrame) -> DataFrame:
    """Cells (i, j, x) of a without its padding; narrow."""
    size = a.meta.block
    cells = a.df.select("bi", "bj", "nr", F.posexplode("v").alias("at", "x"))
    out = cells.select((F.col("bi") * size + F.col("at") % F.col("nr")).alias("i"), (F.col("bj") * size + F.floor(F.col("at") / F.col("nr"))).cast("long").alias("j"), "x")
    m = a.meta
    return out.filter(f"i < {m.logical_rows} and j < {m.logical_cols}") if (m.rows, m.cols) != (m.logical_rows, m.logical_cols) else out


def from_rows(df: DataFrame, n: int, block: int, cols: int | None = None) -> BlockFrame:
    """Blocks of the matrix whose rows are (i, r: array of values)."""
    return from_coo(df.select("i", F.posexplode("r").alias("j", "x")), n, block, cols)


def from_array_column(df: DataFrame, key: str, values: str, n: int, cols: int, block: int) -> BlockFrame:
    """Like from_rows, for any names; key counts the rows from 0."""
    return from_rows(df.select(F.col(key).cast("long").alias("i"), F.col(values).cast("array<double>").alias("r")), n, block, cols)


def to_rows(a: BlockFrame) -> DataFrame:
    """(i, r) for each row of a."""
    return to_coo(a).groupBy("i").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda c: c["x"]).alias("r"))


def reblock(a: BlockFrame, block: int) -> BlockFrame:
    """a in blocks of another size."""
    return from_coo(to_coo(a), a.meta.logical_rows, block, a.meta.logical_cols, symmetric=a.meta.symmetric)


def pad(a: BlockFrame, grid: int | None = None) -> BlockFrame:
    """A square a extended to diag(a, I) with `grid` blocks a side, by default the next power of two."""
    side = a.meta.grid_rows
    if not a.meta.square:
        raise ValueError("only a square matrix is padded")
    grid = grid or 1 << (side - 1).bit_length()
    if grid == side:
        return a
    size = a.meta.block
    keys = grid_keys(a.spark, grid, grid).filter(f"bi >= {side} or bj >= {side}")

    def run(batches):
        for batch in batches:
            found = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
            yield record(found, [np.eye(size) if i == j else np.zeros((size, size)) for i, j in found])

    return a.of(a.df.unionByName(keys.mapInArrow(run, BLOCK_DDL)), grid_rows=grid, grid_cols=grid)


def crop(a: BlockFrame, rows: int, cols: int | None = None) -> BlockFrame:
    """The upper left rows x cols of a; blocks that lie outside go."""
    cols = cols or rows
    size = a.meta.block
    high, wide = -(-rows // size), -(-cols // size)
    return a.of(a.df.filter(f"bi < {high} and bj < {wide}"), logical_rows=rows, logical_cols=cols, grid_rows=high, grid_cols=wide)


def generated(spark: SparkSession, rows: int, block: int, cell, cols: int | None = None, symmetric: bool = False) -> BlockFrame:
    """Blocks of cell(i, j) for arrays of row and column numbers, made where they are needed; padded like from_coo."""
    meta = meta_for(rows, cols or rows, block, symmetric)

    def run(batches):
        for batch in batches:
            for bi, bj in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                i, j = np.arange(bi * block, (bi + 1) * block)[:, None], np.arange(bj * block, (bj + 1) * block)[None]
                inside = (i < meta.logical_rows) & (j < meta.logical_cols)
                value = np.where(inside, cell(i, j), ((i == j) & (meta.logical_rows == meta.logical_cols)).astype(float))
                yield record([(bi, bj)], [value.astype(float)])

    return BlockFrame(grid_keys(spark, meta.grid_rows, meta.grid_cols).mapInArrow(run, BLOCK_DDL), meta)


def identity(spark: SparkSession, n: int, block: int) -> BlockFrame:
    return generated(spark, n, block, lambda i, j: (i == j).astype(float), symmetric=True)


def diag(df: DataFrame, n: int, block: int) -> BlockFrame:
    """The diagonal matrix of the values (i, x)."""
    return from_coo(df.select("i", F.col("i").alias("j"), "x"), n, block, fill=0.0, symmetric=True)


def to_numpy(a: BlockFrame, max_bytes: int = 256 << 20) -> np.ndarray:
    """a without padding as an array on the driver; refused beyond max_bytes."""
    if a.meta.bytes > max_bytes:
        raise ValueError(f"{a.meta.bytes} bytes are too many for the driver")
    out = np.zeros((a.meta.rows, a.meta.cols))
    table, size = a.df.toArrow(), a.meta.block
    for bi, bj, block in zip(table.column("bi").to_pylist(), table.column("bj").to_pylist(), arrays(table)):
        out[bi * size : (bi + 1) * size, bj * size : (bj + 1) * size] = block
    return out[: a.meta.logical_rows, : a.meta.logical_cols]


def from_numpy(spark: SparkSession, a: np.ndarray, block: int, symmetric: bool = False) -> BlockFrame:
    """Blocks of a small array of the driver's (tests)."""
    held = np.array(a, dtype=float)
    return generated(spark, held.shape[0], block, lambda i, j: held[np.minimum(i, held.shape[0] - 1), np.minimum(j, held.shape[1] - 1)], held.shape[1], symmetric)
