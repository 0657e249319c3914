"""Single-machine kernels on numpy arrays: inverse solvers of a leaf, unpivoted LU, and the serial quadrant inversion."""

from __future__ import annotations

import numpy as np

SOLVERS = ("lu", "qr", "svd", "cholesky", "gauss_jordan")
#: Largest probed residual |A X v - v| of an inverse that is returned.
TOLERANCE = 1e-6
#: Sign vectors by which an inverse is probed.
PROBES = 8


def signs(start: int, rows: int) -> np.ndarray:
    """Rows start, start + 1, ... of the probe vectors: signs by index arithmetic, the same wherever they are made."""
    at = np.arange(start, start + rows, dtype=np.uint64)[:, None] * np.uint64(PROBES) + np.arange(1, PROBES + 1, dtype=np.uint64)
    with np.errstate(over="ignore"):
        at = at * np.uint64(0x9E3779B97F4A7C15)
        at = (at ^ (at >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        at = (at ^ (at >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return 1.0 - 2.0 * (at >> np.uint64(63)).astype(float)


def probed(a: np.ndarray, x: np.ndarray) -> float:
    """Largest absolute entry of a (x v) - v over the probe vectors; infinite where x isn't finite."""
    v = signs(0, len(a))
    with np.errstate(all="ignore"):
        off = float(np.abs(a @ (x @ v) - v).max(initial=0.0))
    return off if np.isfinite(off) else float("inf")


def slices(a: np.ndarray, bits: int, axis: int) -> list[np.ndarray]:
    """Up to four arrays that add up to a: the leading bits of each cell, counted from the largest cell along axis, then the next ones."""
    out, rest = [], a.astype(float)
    for _ in range(4):
        top = np.abs(rest).max(axis=axis, keepdims=True, initial=0.0)
        if not top.any():
            break
        big = np.ldexp(1.0, np.frexp(top)[1] + 53 - bits)
        high = (rest + big) - big
        out.append(high)
        rest = rest - high
    return out


def two_sum(hi: np.ndarray, lo: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """hi + lo + x, the rounding error of hi + x added to lo."""
    total = hi + x
    part = total - hi
    return total, lo + ((hi - (total - part)) + (x - part))


def precise_product(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """a @ b as a sum of two arrays, with about twice the digits of one.

    The operands are cut into slices of so few bits that products of slices have no rounding error, in whatever order the library adds.
    """
    bits = (53 - max(1, a.shape[1]).bit_length()) // 2
    left, right = slices(a, bits, 1), slices(b, bits, 0)
    hi, lo = np.zeros((a.shape[0], b.shape[1])), np.zeros((a.shape[0], b.shape[1]))
    for p, q in sorted(((p, q) for p in range(len(left)) for q in range(len(right)) if p + q < 5), key=sum):
        hi, lo = two_sum(hi, lo, left[p] @ right[q])
    return hi, lo


def rcond(a: np.ndarray, x: np.ndarray) -> float:
    """Reciprocal condition of a in the 1-norm, from its computed inverse x."""
    with np.errstate(all="ignore"):
        both = np.abs(a).sum(axis=0).max(initial=0.0) * np.abs(x).sum(axis=0).max(initial=0.0)
    return 1.0 / both if np.isfinite(both) and both > 0 else 0.0


def _by_lu(a: np.ndarray) -> np.ndarray:
    return np.linalg.inv(a)


def _by_qr(a: np.ndarray) -> np.ndarray:
    q, r = np.linalg.qr(a)
    return np.linalg.solve(r, q.T)


def _by_svd(a: np.ndarray) -> np.ndarray:
    u, s, vt = np.linalg.svd(a)
    if s[-1] <= s[0] * np.finfo(float).eps * len(s):
        raise np.linalg.LinAlgError("singular matrix")
    return (vt.T / s) @ u.T


def _by_cholesky(a: np.ndarray) -> np.ndarray:
    """For symmetric positive definite a."""
    lower = np.linalg.cholesky(a)
    half = np.linalg.solve(lower, np.eye(len(a)))
    return half.T @ half


def _by_gauss_jordan(a: np.ndarray) -> np.ndarray:
    """Row elimination on [a | I] with the largest pivot of each column."""
    n = len(a)
    tableau = np.hstack((a.astype(float), np.eye(n)))
    for k in range(n):
        pivot = k + int(np.abs(tableau[k:, k]).argmax())
        if tableau[pivot, k] == 0.0:
            raise np.linalg.LinAlgError("singular matrix")
        if pivot != k:
            tableau[[k, pivot]] = tableau[[pivot, k]]
        tableau[k] /= tableau[k, k]
        column = tableau[:, k].copy()
        column[k] = 0.0
        tableau -= np.outer(column, tableau[k])
    return tableau[:, n:]


_BY = {"lu": _by_lu, "qr": _by_qr, "svd": _by_svd, "cholesky": _by_cholesky, "gauss_jordan": _by_gauss_jordan}


def inverse(a: np.ndarray, solver: str = "lu") -> np.ndarray:
    """Inverse of a square array; LinAlgError where it is singular to working precision (or, for cholesky, not positive definite)."""
    if a.ndim != 2 or a.shape[0] != a.shape[1]:
        raise ValueError(f"not square: {a.shape}")
    if solver not in _BY:
        raise ValueError(f"unknown solver {solver!r}")
    x = _BY[solver](a)
    if len(a) and rcond(a, x) < np.finfo(float).eps:
        raise np.linalg.LinAlgError("singular to working precision")
    return x


def inverse_or_nan(a: np.ndarray, solver: str = "lu") -> np.ndarray:
    """Like inverse, with NaN for a singular array, so that a distributed run ends and is judged on the driver."""
    try:
        return inverse(a, solver)
    except np.linalg.LinAlgError:
        return np.full(a.shape, np.nan)


def lu_unpivoted(a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit lower and upper factor of a, without exchanges; NaN where a pivot is zero."""
    work, n = a.astype(float).copy(), len(a)
    with np.errstate(divide="ignore", invalid="ignore"):
        for k in range(n - 1):
            work[k + 1 :, k] /= work[k, k]
            work[k + 1 :, k + 1 :] -= np.outer(work[k + 1 :, k], work[k, k + 1 :])
    return np.tril(work, -1) + np.eye(n), np.triu(work)


def _quartered(a: np.ndarray, threshold: int, leaf: str) -> np.ndarray:
    n = len(a)
    if n <= max(1, threshold):
        return inverse(a, leaf)
    k = n // 2
    e, f, g, h = a[:k, :k], a[:k, k:], a[k:, :k], a[k:, k:]
    p = _quartered(e, threshold, leaf)
    left, right = g @ p, p @ f
    q = _quartered(g @ right - h, threshold, leaf)
    bottom = q @ left
    return np.block([[p - right @ bottom, right @ q], [bottom, -q]])


def quad_invert(a: np.ndarray, threshold: int, leaf: str = "lu", tolerance: float = TOLERANCE) -> np.ndarray:
    """Serial quadrant inversion: the plain solver below the threshold, else six half-size products.

    With a = [[e, f], [g, h]] the complement of e is inverted with its sign turned, which gives both off-diagonal quadrants
    of the result their sign. Odd orders are halved unevenly. LinAlgError where a leading block, or the whole, is singular or so
    near it that the probed residual is over tolerance; two Newton steps are tried first.
    """
    x = _quartered(a, threshold, leaf)
    for _ in range(2):
        off = probed(a, x)
        if off <= tolerance or off >= 0.5:
            break
        x = 2 * x - x @ (a @ x)
    if not probed(a, x) <= tolerance:
        raise np.linalg.LinAlgError("a leading block is singular or nearly so")
    return x
