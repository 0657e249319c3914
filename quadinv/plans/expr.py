"""Matrix expressions: a small tree, rewrites that Catalyst can't make, and the choice of physical products.

    a, b = Matrix(frame_a), Matrix(frame_b)
    result = evaluate(Inverse(a) @ b - 2.0 * b)
"""

from __future__ import annotations

from dataclasses import dataclass

from ..operators import ops
from ..operators.blocks import BlockFrame
from ..operators.gemm import BROADCAST_BYTES, multiply
from ..operators.invert import InvertOptions, quad_inverse


class MatExpr:
    def __matmul__(self, other: MatExpr) -> MatExpr:
        return Mul(self, other)

    def __sub__(self, other: MatExpr) -> MatExpr:
        return Sub(self, other)

    def __neg__(self) -> MatExpr:
        return Scale(self, -1.0)

    def __rmul__(self, s: float) -> MatExpr:
        return Scale(self, float(s))

    @property
    def T(self) -> MatExpr:
        return Transpose(self)


@dataclass(frozen=True)
class Matrix(MatExpr):
    """A given matrix; identity: known to be I."""

    frame: BlockFrame
    identity: bool = False


@dataclass(frozen=True)
class Mul(MatExpr):
    a: MatExpr
    b: MatExpr


@dataclass(frozen=True)
class Sub(MatExpr):
    a: MatExpr
    b: MatExpr


@dataclass(frozen=True)
class Scale(MatExpr):
    a: MatExpr
    s: float


@dataclass(frozen=True)
class Transpose(MatExpr):
    a: MatExpr


@dataclass(frozen=True)
class Inverse(MatExpr):
    a: MatExpr


@dataclass(frozen=True)
class Quad(MatExpr):
    a: MatExpr
    x: int
    y: int


@dataclass(frozen=True)
class Assemble(MatExpr):
    q11: MatExpr
    q12: MatExpr
    q21: MatExpr
    q22: MatExpr


@dataclass(frozen=True)
class Fused(MatExpr):
    """alpha a b + beta c, one pass over the product."""

    a: MatExpr
    b: MatExpr
    alpha: float
    beta: float
    c: MatExpr


def children(e: MatExpr) -> list[MatExpr]:
    return [v for v in vars(e).values() if isinstance(v, MatExpr)]


def _rebuilt(e: MatExpr) -> MatExpr:
    return type(e)(**{k: simplify(v) if isinstance(v, MatExpr) else v for k, v in vars(e).items()}) if children(e) else e


def simplify(e: MatExpr) -> MatExpr:
    """Rewrites, inner expressions first: double transposes, signs and inverses go, factors gather, products with I go,
    quadrants of an assembled matrix are the quadrants, transposes move inside, subtractions melt into products."""
    e = _rebuilt(e)
    match e:
        case Transpose(Transpose(a)) | Inverse(Inverse(a)):
            return a
        case Transpose(Matrix(frame, one) as a) if one or frame.meta.symmetric:
            return a
        case Transpose(Inverse(a)):
            return simplify(Inverse(Transpose(a)))
        case Transpose(Mul(a, b)):
            return simplify(Mul(Transpose(b), Transpose(a)))
        case Transpose(Scale(a, s)):
            return simplify(Scale(Transpose(a), s))
        case Scale(Scale(a, s), t):
            return simplify(Scale(a, s * t))
        case Scale(a, 1.0):
            return a
        case Inverse(Scale(a, s)) if s != 0.0:
            return simplify(Scale(Inverse(a), 1.0 / s))
        case Inverse(Matrix(_, True) as a):
            return a
        case Mul(Matrix(_, True), b):
            return b
        case Mul(a, Matrix(_, True)):
            return a
        case Mul(Scale(a, s), b) | Mul(a, Scale(b, s)):
            return simplify(Scale(Mul(a, b), s))
        case Quad(Assemble() as a, x, y):
            return (a.q11, a.q12, a.q21, a.q22)[2 * (x - 1) + y - 1]
        case Sub(Mul(a, b), c):
            return Fused(a, b, 1.0, -1.0, c)
        case Sub(Scale(Mul(a, b), s), c):
            return Fused(a, b, s, -1.0, c)
        case Sub(c, Mul(a, b)):
            return Fused(a, b, -1.0, 1.0, c)
        case Sub(c, Scale(Mul(a, b), s)):
            return Fused(a, b, -s, 1.0, c)
    return e


def choose_mul(a: BlockFrame, b: BlockFrame) -> str:
    """Strategy of a product: a small operand beside a much larger one is broadcast, all others go by coarse cells."""
    small, large = sorted((a.meta.bytes, b.meta.bytes))
    return "broadcast" if small <= BROADCAST_BYTES and large > 8 * max(small, 1 << 20) else "grid3d"


def evaluate(e: MatExpr, opts: InvertOptions | None = None) -> BlockFrame:
    """The frame of an expression, simplified first."""
    return _planned(simplify(e), opts)


def _planned(e: MatExpr, opts: InvertOptions | None) -> BlockFrame:
    down = lambda x: _planned(x, opts)
    match e:
        case Matrix(frame):
            return frame
        case Mul(a, b):
            x, y = down(a), down(b)
            return multiply(x, y, choose_mul(x, y))
        case Fused(a, b, alpha, beta, c):
            x, y = down(a), down(b)
            return multiply(x, y, choose_mul(x, y), alpha=alpha, beta=beta, c=down(c))
        case Sub(a, b):
            return ops.subtract(down(a), down(b))
        case Scale(a, s):
            return ops.scale(down(a), s)
        case Transpose(a):
            return ops.transpose(down(a))
        case Inverse(a):
            return quad_inverse(down(a), opts)
        case Quad(a, x, y):
            return ops.quadrant(down(a), x, y)
        case Assemble(q11, q12, q21, q22):
            return ops.assemble(down(q11), down(q12), down(q21), down(q22))
    raise TypeError(f"not an expression: {e!r}")
