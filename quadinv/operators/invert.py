"""Distributed quadrant inversion (QuadInv).

For A = [[E, F], [G, H]] the leading quadrant is inverted first (P), then the Schur complement of it with its sign turned,
N = G P F - H (Q = inverse of N). With Lp = G P and R = P F the inverse is [[P - R Q Lp, R Q], [Q Lp, -Q]]: six products and
two subtractions a level, one local inversion a leaf. The recursion runs on the driver over metadata; each node's results that
are read more than once are materialised together, so that a plan spans one node at most.

No pivoting between blocks: a leading quadrant that is singular, or nearly so, spoils the result. A leaf that is singular to working
precision becomes NaN, and every result is probed (see verify) before it is returned: Newton steps, whose residual I - A X has twice the
digits of a double, mend what can be mended. Where they can't, the recursion runs once more with panels corrected by their own residual, for in a
badly conditioned matrix the rounding of P itself, times G and F, can be as large as N. Then the normal equations, inv(A'A) A', whose leading blocks
are regular whenever A is, are taken, mended and probed in their turn, or an error is raised. Nothing over the tolerance is returned.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

from pyspark import inheritable_thread_target

from ..functions.local import TOLERANCE
from ..plans.lineage import materialize
from ..plans.trace import RunTrace
from . import ops
from .blocks import BlockFrame, crop, identity, pad
from .gemm import multiply, precise_difference
from .leaf import invert_leaf
from .verify import probed_residual, probed_size


@dataclass(frozen=True)
class InvertOptions:
    leaf_blocks: int = 1  # blocks a side at which the recursion ends
    leaf_solver: str = "lu"  # lu, qr, svd, cholesky, gauss_jordan
    leaf_site: str = "executor"  # or driver, to compare
    split_mode: str = "direct"  # or tagged
    schur: str = "negated"  # or plain
    strategy: str = "grid3d"  # of the products, see gemm
    cells: int | None = None
    tiles: int = 1  # parts a side into which blocks are cut for the products, so that these are dealt to more tasks than blocks
    fuse: bool = True  # subtraction inside of the product
    on_singular: str = "normal"  # or raise
    tolerance: float = TOLERANCE  # of the probed residual of what is returned
    refine: int = 0  # steps of X (2I - AX), beside those that the tolerance asks for
    parallel_panels: bool = False  # independent products from two threads
    materialize: str = "reliable"  # or parquet, persist
    symmetric: bool = False  # A = A': left panel and lower corner are transposes, four products a level
    timed: bool = False  # materialise after each step and time it
    keep_leaves: bool = False  # leave the leaves' inverses in the trace
    corrected: bool = False  # panels corrected by their residual, at up to four products more a level; quad_inverse does so where it must
    trace: RunTrace = field(default_factory=RunTrace, compare=False)


#: Newton steps that are tried before the inverse is given up. A residual of HOPELESS isn't tried; below it they go on while they gain, for
#: they can converge from a probed residual near 1. MENDABLE is asked of the inverse of the normal equations.
MENDING_STEPS, MENDABLE, HOPELESS = 8, 0.5, 1e3
#: Quadrants up to this size aren't worth a job of their own where they are read twice only.
SMALL_BYTES = 4 << 20


def _tagged(frames: dict[str, BlockFrame], opts: InvertOptions) -> dict[str, BlockFrame]:
    """Several results in one job: united under a tag, materialised, and told apart again."""
    if opts.parallel_panels:
        with ThreadPoolExecutor(len(frames)) as pool:
            session = next(iter(frames.values())).spark
            done = {k: pool.submit(inheritable_thread_target(session)(materialize), f.df, opts.materialize) for k, f in frames.items()}
            return {k: frames[k].of(d.result()) for k, d in done.items()}
    united = None
    for tag, f in frames.items():
        part = f.df.selectExpr(*ops.BLOCK, f"'{tag}' as tag")
        united = part if united is None else united.union(part)
    held = materialize(united, opts.materialize, by="tag")
    return {tag: f.of(held.filter(f"tag = '{tag}'").select(ops.BLOCK)) for tag, f in frames.items()}


class _Run:
    def __init__(self, opts: InvertOptions):
        self.opts, self.trace = opts, opts.trace

    def step(self, level: int, node: str, op: str, made, elements: int):
        """Count an operation; with timing, also compute its result now."""
        if not self.opts.timed:
            self.trace.add(level, node, op, 1, elements)
            return made()
        with self.trace.timed(level, node, op, 1, elements):
            out = made()
            return out.of(materialize(out.df, self.opts.materialize)) if isinstance(out, BlockFrame) else out

    def product(self, level: int, node: str, a: BlockFrame, b: BlockFrame, **fused) -> BlockFrame:
        return self.step(level, node, "multiply", lambda: multiply(a, b, self.opts.strategy, cells=self.opts.cells, **fused), a.meta.rows * b.meta.cols)

    def difference(self, level: int, node: str, a: BlockFrame, b: BlockFrame, c: BlockFrame, turned: bool) -> BlockFrame:
        """a b - c, or c - a b if turned."""
        size = a.meta.rows * b.meta.cols
        if self.opts.fuse and not self.opts.timed:
            self.trace.add(level, node, "subtract", 1, size)
            return self.product(level, node, a, b, alpha=-1.0 if turned else 1.0, beta=1.0 if turned else -1.0, c=c)
        made = self.product(level, node, a, b)
        return self.step(level, node, "subtract", lambda: ops.subtract(c, made) if turned else ops.subtract(made, c), size)

    def node(self, a: BlockFrame, level: int, node: str) -> BlockFrame:
        opts, k = self.opts, a.meta.grid_rows
        size = a.meta.rows * a.meta.cols
        if k <= opts.leaf_blocks:
            out = self.step(level, node, "leaf", lambda: invert_leaf(a, opts.leaf_solver, opts.leaf_site), size)
            if opts.keep_leaves:
                out = self.keep(out)
                self.trace.leaves.append(out)
            return out
        self.step(level, node, "split", lambda: None, size)
        e, f, g, h = (self.step(level, node, "quadrant", lambda x=x, y=y: ops.quadrant(a, x, y, opts.split_mode), size // 4) for x in (1, 2) for y in (1, 2))
        p = self.keep(self.node(e, level + 1, node + "0"))
        right = self.product(level, node, p, f)
        if opts.corrected:
            right = self.keep(right)
            off = self.difference(level, node, e, right, f, turned=True)
            right = self.product(level, node, p, off, beta=1.0, c=right)
        if opts.symmetric:
            panels = _tagged({"right": right}, opts)
            panels["left"] = ops.transpose(panels["right"])
        else:
            left = self.product(level, node, g, p)
            if opts.corrected:
                left = self.keep(left)
                off = self.difference(level, node, left, e, g, turned=True)
                left = self.product(level, node, off, p, beta=1.0, c=left)
            panels = _tagged({"left": left, "right": right}, opts)
        left, right = panels["left"], panels["right"]
        plain = opts.schur == "plain"
        n = self.difference(level, node, g, right, h, turned=plain)
        self.trace.turned += 0 if plain else n.meta.rows
        q = self.keep(self.node(n if k == 2 * opts.leaf_blocks else self.keep(n), level + 1, node + "1"))
        upper = self.product(level, node, right, q)
        small = upper.meta.bytes <= SMALL_BYTES
        if opts.symmetric:
            upper = upper if small else _tagged({"upper": upper}, opts)["upper"]
            lower = ops.transpose(upper)
        else:
            corner = {"upper": upper, "lower": self.product(level, node, q, left)}
            upper, lower = (corner if small else _tagged(corner, opts)).values()
        if plain:
            top = self.step(level, node, "add", lambda: ops.add(p, multiply(right, lower, opts.strategy, cells=opts.cells)), size // 4)
            self.trace.add(level, node, "multiply", 1, size // 4)
            upper = self.step(level, node, "scale", lambda: ops.negate(upper), size // 4)
            lower = self.step(level, node, "scale", lambda: ops.negate(lower), size // 4)
        else:
            top = self.difference(level, node, right, lower, p, turned=True)
        last = q if plain else self.step(level, node, "scale", lambda: ops.negate(q), size // 4)
        return self.step(level, node, "assemble", lambda: ops.assemble(top, upper, lower, last), size)

    def keep(self, a: BlockFrame) -> BlockFrame:
        return a if self.opts.timed else a.of(materialize(a.df, self.opts.materialize))


def quad_inverse(a: BlockFrame, opts: InvertOptions | None = None) -> BlockFrame:
    """Inverse of a square a; its grid is padded to a power of two times leaf_blocks and the result cropped again."""
    opts = opts or InvertOptions()
    if a.meta.logical_rows != a.meta.logical_cols:
        raise ValueError(f"not square: {a.meta.logical_rows} x {a.meta.logical_cols}")
    if opts.on_singular not in ("normal", "raise"):
        raise ValueError(f"unknown on_singular {opts.on_singular!r}")
    n, grid = a.meta.logical_rows, max(1, opts.leaf_blocks)
    while grid < a.meta.grid_rows:
        grid *= 2
    opts = replace(opts, symmetric=opts.symmetric or a.meta.symmetric)
    opts.trace.n, opts.trace.b = grid * a.meta.block, grid
    padded = pad(a, grid) if grid > a.meta.grid_rows and a.meta.grid_rows > opts.leaf_blocks else a
    padded = padded.of(padded.df, logical_rows=padded.meta.rows, logical_cols=padded.meta.rows)
    if opts.tiles < 1 or a.meta.block % opts.tiles:
        raise ValueError(f"blocks of {a.meta.block} have no {opts.tiles} equal parts a side")
    tiles = opts.tiles if padded.meta.grid_rows > opts.leaf_blocks else 1
    if tiles > 1:
        padded, opts = ops.tiled(padded, tiles), replace(opts, leaf_blocks=opts.leaf_blocks * tiles, tiles=1)
    source = padded.of(materialize(padded.df, opts.materialize))
    out = _Run(opts).node(source, 0, "r")
    out = out.of(materialize(out.df, opts.materialize), symmetric=a.meta.symmetric)
    for _ in range(opts.refine):
        out = out.of(materialize(refined(source, out, opts).df, opts.materialize))
    out, off = mended(source, out, opts)
    if opts.tolerance < off < float("inf") and not opts.corrected:
        again = _Run(replace(opts, corrected=True, keep_leaves=False, trace=RunTrace(method="corrected"))).node(source, 0, "r")
        out, off = mended(source, again.of(materialize(again.df, opts.materialize), symmetric=a.meta.symmetric), opts, always=True)
    if not off <= opts.tolerance:
        if opts.on_singular == "raise":
            raise ArithmeticError(f"a leading block of the matrix is singular or nearly so: residual {off:.3g}")
        out = _normal(source, opts)
    return _cropped(ops.merged(out, tiles) if tiles > 1 else out, n, a)


def mended(a: BlockFrame, x: BlockFrame, opts: InvertOptions, always: bool = False) -> tuple[BlockFrame, float]:
    """x and its probed residual; where that is over the tolerance (or always), after as many Newton steps, x + x (I - a x), as it gains by.

    A step from within the tolerance is the last that can gain; it leaves x accurate to its own rounding, though the residual need not show it.
    """
    off = probed_residual(a, x)
    if (always or off > opts.tolerance) and off < HOPELESS:
        one = identity(a.spark, a.meta.rows, a.meta.block)
        away = _away(a, x, one, opts)
        off = probed_size(away)
        for _ in range(MENDING_STEPS):
            better = multiply(x, away, opts.strategy, beta=1.0, c=x, cells=opts.cells)
            better = x.of(materialize(better.df, opts.materialize))
            rest = _away(a, better, one, opts)
            new = probed_size(rest)
            if not new < off and not new <= opts.tolerance:
                break
            ended = new > off / 2
            x, away, off = better, rest, new
            if ended:
                break
    opts.trace.residual = off
    return x, off


def _away(a: BlockFrame, x: BlockFrame, one: BlockFrame, opts: InvertOptions) -> BlockFrame:
    """I - a x, with the digits that a product of doubles leaves out."""
    found = precise_difference(a, x, one)
    return found.of(materialize(found.df, opts.materialize))


def _cropped(out: BlockFrame, n: int, a: BlockFrame) -> BlockFrame:
    return crop(out, n) if (out.meta.logical_rows, out.meta.grid_rows) != (n, a.meta.grid_rows) else out


def refined(a: BlockFrame, x: BlockFrame, opts: InvertOptions) -> BlockFrame:
    """One step towards the inverse: 2 x - x (a x)."""
    ax = multiply(a, x, opts.strategy, cells=opts.cells)
    return multiply(x, ax, opts.strategy, alpha=-1.0, beta=2.0, c=x, cells=opts.cells)


def _normal(a: BlockFrame, opts: InvertOptions) -> BlockFrame:
    """inv(A'A) A': the leading blocks of A'A are regular whenever A is. Its condition is squared, hence the mending by A itself."""
    failed = ArithmeticError("the matrix is singular, or too badly conditioned")
    t = a.of(materialize(ops.transpose(a).df, opts.materialize))
    square = multiply(t, a, opts.strategy, cells=opts.cells)
    try:
        inner = quad_inverse(square.of(square.df, symmetric=True), replace(opts, on_singular="raise", symmetric=True, refine=0, tolerance=MENDABLE, trace=RunTrace(method="normal")))
    except ArithmeticError:
        raise failed from None
    whole = multiply(inner, t, opts.strategy, cells=opts.cells)
    out, off = mended(a, whole.of(materialize(whole.df, opts.materialize), symmetric=False), opts)
    if not off <= opts.tolerance:
        raise failed
    return out


def check_residual(a: BlockFrame, x: BlockFrame) -> BlockFrame:
    """a x - I, for measures of accuracy."""
    one = identity(a.spark, a.meta.logical_rows, a.meta.block)
    return multiply(a, x, alpha=1.0, beta=-1.0, c=one)
