"""Inverses: by LAPACK on the driver when small, by blocked elimination (Schur complements) over COO products otherwise;
and the change of an inverse, one outer product at a time or in one block."""

from __future__ import annotations

import numpy as np

from . import coo

LOCAL_SIDE = 2048


class Singular(ArithmeticError):
    """The changed matrix has no inverse to the given tolerance."""


def checked(x: np.ndarray, tol: float = 1e-12) -> np.ndarray:
    """Inverse of a small matrix; Singular where its smallest singular value is under tol of the largest."""
    d = np.linalg.svd(x, compute_uv=False)
    if len(d) and not d.min() > tol * d.max():
        raise Singular(f"singular values from {d.max():g} to {d.min():g}")
    return np.linalg.inv(x)


def invert(m: coo.Coo, local_side: int = LOCAL_SIDE) -> coo.Coo:
    n = m.rows
    if n <= local_side:
        return coo.from_numpy(m.df.sparkSession, checked(coo.to_numpy(m)))
    h = n // 2
    a, b, c, d = (coo.piece(m, r, q) for r in ((0, h), (h, n)) for q in ((0, h), (h, n)))
    settle = lambda x: coo.Coo(coo.cut(x.df), x.rows, x.cols)
    ai = settle(invert(a, local_side))
    left, right = settle(coo.mul(c, ai)), settle(coo.mul(ai, b))
    si = settle(invert(settle(coo.add(d, coo.mul(left, b), -1.0)), local_side))
    low = settle(coo.mul(si, left))
    top_right = coo.scale(-1.0, coo.mul(right, si))
    top_left = coo.add(ai, coo.mul(right, low))
    return settle(coo.vstack([coo.hstack([top_left, top_right]), coo.hstack([coo.scale(-1.0, low), si])]))


def rank1(w: np.ndarray, left: np.ndarray, right: np.ndarray, tol: float = 1e-12) -> tuple[np.ndarray, np.ndarray]:
    """Factors of the change of w = inverse(Z) when left @ right.T (one column each) is added to Z."""
    seen, back = w @ left, w.T @ right
    d = 1.0 + float((right.T @ seen)[0, 0])
    if abs(d) < tol:
        raise Singular(f"denominator {d}")
    return -seen / d, back


def block(w: np.ndarray, left: np.ndarray, right: np.ndarray, tol: float = 1e-12) -> tuple[np.ndarray, np.ndarray]:
    """The same for any rank in one step, by one small system."""
    seen = w @ left
    core = np.eye(left.shape[1]) + right.T @ seen
    if np.linalg.svd(core, compute_uv=False).min(initial=1.0) < tol:
        raise Singular("the small system is singular")
    return -np.linalg.solve(core.T, seen.T).T, w.T @ right


def rank_k(w: np.ndarray, left: np.ndarray, right: np.ndarray, tol: float = 1e-12) -> tuple[np.ndarray, np.ndarray]:
    """One outer product after the other; w is read with the factors so far and not rewritten. If one order meets a singular
    matrix on the way the reverse is tried, then the block form."""
    for order in (range(left.shape[1]), reversed(range(left.shape[1]))):
        a, b = np.zeros((len(w), 0)), np.zeros((len(w), 0))
        try:
            for k in order:
                u, v = left[:, [k]], right[:, [k]]
                seen, back = w @ u + a @ (b.T @ u), w.T @ v + b @ (a.T @ v)
                d = 1.0 + float((v.T @ seen)[0, 0])
                if abs(d) < tol:
                    raise Singular(f"denominator {d}")
                a, b = np.hstack([a, -seen / d]), np.hstack([b, back])
            return a, b
        except Singular:
            continue
    return block(w, left, right, tol)


def guarded(w: np.ndarray, z: np.ndarray, left: np.ndarray, right: np.ndarray, tol: float = 1e-12) -> np.ndarray:
    """New inverse after Z changes: chained, else in a block, else from scratch (z: the changed matrix)."""
    try:
        a, b = rank_k(w, left, right, tol)
        return w + a @ b.T
    except Singular:
        try:
            return np.linalg.inv(z)
        except np.linalg.LinAlgError as e:
            raise Singular(str(e)) from e


def residual(w: np.ndarray, z: np.ndarray) -> float:
    return float(np.abs(w @ z - np.eye(len(w))).max())


def cholesky_rank1(c: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Lower factor of c @ c.T + x x.T, by rotations."""
    c, x = c.copy(), np.asarray(x, float).ravel().copy()
    for k in range(len(x)):
        r = np.hypot(c[k, k], x[k])
        cos, sin = r / c[k, k], x[k] / c[k, k]
        c[k, k] = r
        c[k + 1 :, k] = (c[k + 1 :, k] + sin * x[k + 1 :]) / cos
        x[k + 1 :] = cos * x[k + 1 :] - sin * c[k + 1 :, k]
    return c


def compact(left: np.ndarray, right: np.ndarray, tol: float = 1e-12) -> tuple[np.ndarray, np.ndarray]:
    """Factors of least width with the same product, by values (thin QR, then SVD of the small core)."""
    q, r = np.linalg.qr(left)
    p, s = np.linalg.qr(right)
    u, d, v = np.linalg.svd(r @ s.T)
    k = int((d > tol * max(1.0, d.max(initial=0.0))).sum())
    return q @ (u[:, :k] * d[:k]), p @ v[:k].T
