"""Inversion by recursive block LU (BlockLU), the baseline of QuadInv.

Only its operation counts are published, so this is a reconstruction that follows them: two LU factorizations, four triangular
inversions and three products in a base call of 2 x 2 blocks; compositions of four products and two scalings; seven half-size
products at the end. An inner node needs three products of its own here, one less than the published four, whose use is not
given. No pivoting between blocks; the result is probed, and an error raised where a leading block was singular or nearly so.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..functions.local import inverse_or_nan, lu_unpivoted
from ..plans.lineage import materialize
from . import ops
from .blocks import BLOCK_DDL, BlockFrame, arrays, pad, record
from .gemm import multiply
from .invert import InvertOptions, _cropped, _tagged
from .leaf import invert_leaf
from .verify import verified

#: What a base call gives, by the number under which its blocks are sent.
PIECES = ("l1i", "u1i", "l21", "u12", "l2i", "u2i", "l1", "u1", "l2", "u2")


@dataclass(frozen=True)
class LUPieces:
    """Of one 2 x 2 division of a matrix: inverse factors of both diagonal parts, panels, and the factors themselves."""

    l1i: BlockFrame
    u1i: BlockFrame
    l21: BlockFrame
    u12: BlockFrame
    l2i: BlockFrame
    u2i: BlockFrame
    l1: BlockFrame | None = None
    u1: BlockFrame | None = None
    l2: BlockFrame | None = None
    u2: BlockFrame | None = None


class _Run:
    def __init__(self, opts: InvertOptions, factors: bool = False):
        self.opts, self.trace, self.factors = opts, opts.trace, factors

    def product(self, level: int, node: str, a: BlockFrame, b: BlockFrame, **fused) -> BlockFrame:
        self.trace.add(level, node, "multiply", 1, a.meta.rows * b.meta.cols)
        return multiply(a, b, self.opts.strategy, cells=self.opts.cells, **fused)

    def scaled(self, level: int, node: str, a: BlockFrame) -> BlockFrame:
        self.trace.add(level, node, "scale", 1, a.meta.rows * a.meta.cols)
        return ops.negate(a)

    def keep(self, a: BlockFrame) -> BlockFrame:
        return a.of(materialize(a.df, self.opts.materialize))

    def pieces(self, a: BlockFrame, level: int, node: str) -> LUPieces:
        if a.meta.grid_rows == 2:
            return self.base(a, level, node)
        e, f, g, h = (ops.quadrant(a, x, y, self.opts.split_mode) for x in (1, 2) for y in (1, 2))
        first = self.pieces(e, level + 1, node + "0")
        l1i, u1i = self.composed(first, level, node)
        panels = _tagged({"u12": self.product(level, node, l1i, f), "l21": self.product(level, node, g, u1i)}, self.opts)
        l21, u12 = panels["l21"], panels["u12"]
        self.trace.add(level, node, "subtract", 1, h.meta.rows * h.meta.cols)
        s = self.keep(self.product(level, node, l21, u12, alpha=-1.0, beta=1.0, c=h))
        second = self.pieces(s, level + 1, node + "1")
        l2i, u2i = self.composed(second, level, node)
        whole = {}
        if self.factors:
            for name, part in (("1", first), ("2", second)):
                whole["l" + name], whole["u" + name] = joined(part)
        return LUPieces(l1i, u1i, l21, u12, l2i, u2i, **whole)

    def composed(self, p: LUPieces, level: int, node: str) -> tuple[BlockFrame, BlockFrame]:
        """Inverse factors of the whole from the pieces of its division."""
        half = _tagged({"l": self.product(level, node, p.l2i, p.l21), "u": self.product(level, node, p.u1i, p.u12)}, self.opts)
        lower = self.scaled(level, node, self.product(level, node, half["l"], p.l1i))
        upper = self.scaled(level, node, self.product(level, node, half["u"], p.u2i))
        both = _tagged({"l": ops.assemble(p.l1i, zeros(p.l1i), lower, p.l2i), "u": ops.assemble(p.u1i, upper, zeros(p.l1i), p.u2i)}, self.opts)
        return both["l"], both["u"]

    def base(self, a: BlockFrame, level: int, node: str) -> LUPieces:
        size = a.meta.block
        for op, calls in (("local_lu", 2), ("local_inverse", 4), ("local_multiply", 3), ("local_subtract", 1)):
            self.trace.add(level, node, op, calls, calls * size * size)

        def run(key, group):
            found = dict(zip(zip(group.column("bi").to_pylist(), group.column("bj").to_pylist()), arrays(group)))
            l1, u1 = lu_unpivoted(found[0, 0])
            l1i, u1i = _inverses(l1, u1)
            l21, u12 = found[1, 0] @ u1i, l1i @ found[0, 1]
            l2, u2 = lu_unpivoted(found[1, 1] - l21 @ u12)
            l2i, u2i = _inverses(l2, u2)
            return pa.Table.from_batches([record([(k, 0) for k in range(len(PIECES))], [l1i, u1i, l21, u12, l2i, u2i, l1, u1, l2, u2])])

        made = materialize(a.df.withColumn("all", F.lit(0)).groupBy("all").applyInArrow(run, BLOCK_DDL), self.opts.materialize)
        one = {"grid_rows": 1, "grid_cols": 1, "logical_rows": size, "logical_cols": size}
        found = {name: a.of(made.filter(F.col("bi") == k).withColumn("bi", F.lit(0).cast("long")), symmetric=False, **one) for k, name in enumerate(PIECES)}
        return LUPieces(**found)


def _inverses(lower: np.ndarray, upper: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return (inverse_or_nan(lower), inverse_or_nan(upper)) if np.isfinite(lower).all() and np.isfinite(upper).all() else (lower * np.nan, upper * np.nan)


def zeros(a: BlockFrame) -> BlockFrame:
    return a.of(a.df.withColumn("v", F.transform("v", lambda x: F.lit(0.0))).select(ops.BLOCK))


def joined(p: LUPieces) -> tuple[BlockFrame, BlockFrame]:
    """The factors L and U of the matrix that p divides."""
    return ops.assemble(p.l1, zeros(p.l1), p.l21, p.l2), ops.assemble(p.u1, p.u12, zeros(p.l1), p.u2)


def _prepared(a: BlockFrame, opts: InvertOptions) -> BlockFrame:
    if a.meta.logical_rows != a.meta.logical_cols:
        raise ValueError(f"not square: {a.meta.logical_rows} x {a.meta.logical_cols}")
    padded = pad(a)
    return padded.of(materialize(padded.df, opts.materialize), logical_rows=padded.meta.rows, logical_cols=padded.meta.rows, symmetric=False)


def block_lu(a: BlockFrame, opts: InvertOptions | None = None, factors: bool = False) -> LUPieces:
    """Pieces of the first division of a, which has at least 2 x 2 blocks (after padding to a power of two)."""
    opts = opts or InvertOptions()
    return _Run(opts, factors).pieces(_prepared(a, opts), 0, "r")


def lu_factors(a: BlockFrame, opts: InvertOptions | None = None) -> tuple[BlockFrame, BlockFrame]:
    """L (unit diagonal) and U with L U = a, of the padded grid."""
    return joined(block_lu(a, opts, factors=True))


def compose_factors(p: LUPieces, opts: InvertOptions | None = None) -> tuple[BlockFrame, BlockFrame]:
    return _Run(opts or InvertOptions()).composed(p, 0, "r")


def lu_inverse(a: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """Inverse of a by its block LU factors; one block is inverted locally."""
    opts = opts or InvertOptions()
    opts.trace.method = "blocklu"
    n = a.meta.logical_rows
    source = _prepared(a, opts)
    opts.trace.n, opts.trace.b = source.meta.rows, source.meta.grid_rows
    run = _Run(opts)
    if source.meta.grid_rows == 1:
        out = invert_leaf(source, "lu")
    else:
        p = run.pieces(source, 0, "r")
        first = _tagged({"k": run.product(0, "end", p.u1i, p.l1i), "z": run.product(0, "end", p.u2i, p.l2i), "p": run.product(0, "end", p.u1i, p.u12), "m": run.product(0, "end", p.l21, p.l1i)}, opts)
        second = _tagged({"pz": run.product(0, "end", first["p"], first["z"]), "zm": run.product(0, "end", first["z"], first["m"])}, opts)
        corner = run.product(0, "end", second["pz"], first["m"], alpha=1.0, beta=1.0, c=first["k"])
        out = ops.assemble(corner, ops.negate(second["pz"]), ops.negate(second["zm"]), first["z"])
    out = out.of(materialize(out.df, opts.materialize))
    opts.trace.residual = verified(source, out, opts.tolerance, "a leading block of the matrix is singular or nearly so")
    return _cropped(out, n, a)
