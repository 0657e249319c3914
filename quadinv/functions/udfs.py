"""Block kernels under SQL names: block_inverse(v, n), block_gemm(a, b, m, k, n), and the table function block_cells(v, nr)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType

from .local import inverse_or_nan


def _payloads(column: pa.Array) -> list[np.ndarray]:
    flat, offsets = column.values.to_numpy(), column.offsets.to_numpy()
    return [flat[a:b] for a, b in zip(offsets[:-1], offsets[1:])]


def _lists(values: list[np.ndarray]) -> pa.Array:
    return pa.array([v.ravel(order="F") for v in values], pa.list_(pa.float64()))


def block_inverse(v: pa.Array, n: pa.Array) -> pa.Array:
    return _lists([inverse_or_nan(x.reshape((k, k), order="F")) for x, k in zip(_payloads(v), n.to_pylist())])


def block_gemm(a: pa.Array, b: pa.Array, m: pa.Array, k: pa.Array, n: pa.Array) -> pa.Array:
    sizes = zip(m.to_pylist(), k.to_pylist(), n.to_pylist())
    return _lists([x.reshape((p, q), order="F") @ y.reshape((q, r), order="F") for x, y, (p, q, r) in zip(_payloads(a), _payloads(b), sizes)])


class BlockCells:
    """Rows (r, c, x) of a block given by its cells, column by column, and its number of rows."""

    def eval(self, v: list, nr: int):
        for at, x in enumerate(v):
            yield at % nr, at // nr, x


def register(spark: SparkSession) -> None:
    kind = ArrayType(DoubleType())
    spark.udf.register("block_inverse", arrow_udf(block_inverse, kind))
    spark.udf.register("block_gemm", arrow_udf(block_gemm, kind))
    spark.udtf.register("block_cells", udtf(BlockCells, returnType="r int, c int, x double"))
