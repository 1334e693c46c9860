"""Batched solvers of symmetric positive definite systems (n, d, d), (n, d), in NumPy."""

from __future__ import annotations

import numpy as np


def unpack(packed: np.ndarray, rank: int) -> np.ndarray:
    """Full symmetric matrices from packed upper triangles."""
    i, j = np.triu_indices(rank)
    out = np.empty((len(packed), rank, rank), dtype=packed.dtype)
    out[:, i, j] = packed
    out[:, j, i] = packed
    return out


def pack(full: np.ndarray) -> np.ndarray:
    i, j = np.triu_indices(full.shape[-1])
    return full[..., i, j]


def solve_lu(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.linalg.solve(a, b[..., None])[..., 0]


def _upper_solve(r: np.ndarray, y: np.ndarray) -> np.ndarray:
    x = np.empty_like(y)
    for k in range(y.shape[1] - 1, -1, -1):
        x[:, k] = (y[:, k] - np.einsum("nk,nk->n", r[:, k, k + 1 :], x[:, k + 1 :])) / r[:, k, k]
    return x


def _lower_solve(low: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = np.empty_like(b)
    for k in range(b.shape[1]):
        x[:, k] = (b[:, k] - np.einsum("nk,nk->n", low[:, k, :k], x[:, :k])) / low[:, k, k]
    return x


def solve_qr(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    q, r = np.linalg.qr(a)
    return _upper_solve(r, np.einsum("nij,ni->nj", q, b))


def solve_cholesky(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    low = np.linalg.cholesky(a)
    return _upper_solve(np.swapaxes(low, 1, 2), _lower_solve(low, b))


def _conjugate(apply, b: np.ndarray, iters: int, tol: float, start: np.ndarray | None) -> np.ndarray:
    x = np.zeros_like(b) if start is None else start.astype(b.dtype).copy()
    r = b - apply(x)
    p, rr = r.copy(), np.einsum("nd,nd->n", r, r)
    goal = tol * tol * np.maximum(np.einsum("nd,nd->n", b, b), np.finfo(b.dtype).tiny)
    for _ in range(iters):
        going = rr > goal
        if not going.any():
            break
        q = apply(p)
        step = np.where(going, rr / np.where(going, np.maximum(np.einsum("nd,nd->n", p, q), np.finfo(b.dtype).tiny), 1), 0).astype(b.dtype)
        x += step[:, None] * p
        r -= step[:, None] * q
        fresh = np.einsum("nd,nd->n", r, r)
        p = r + (np.where(going, fresh / np.where(rr > 0, rr, 1), 0).astype(b.dtype))[:, None] * p
        rr = fresh
    return x


def solve_cg(a: np.ndarray, b: np.ndarray, iters: int = 32, tol: float = 1e-6, start: np.ndarray | None = None) -> np.ndarray:
    """Conjugate gradients with an optional warm start; a row stops at its tolerance."""
    return _conjugate(lambda v: np.einsum("nij,nj->ni", a, v), b, iters, tol, start)


def solve_cg_free(vectors: np.ndarray, owner: np.ndarray, labels: np.ndarray, base: np.ndarray, n: int, iters: int = 32, tol: float = 1e-6, start: np.ndarray | None = None) -> np.ndarray:
    """Conjugate gradients that never form a row's matrix: base @ p plus the row's own vectors applied to p.

    vectors (m, d) and labels (m,) belong to the rows ``owner`` (ascending, below n); base is one matrix, or one a row.
    """
    b = np.zeros((n, vectors.shape[1]), dtype=vectors.dtype)
    np.add.at(b, owner, labels[:, None] * vectors)
    bounds = np.searchsorted(owner, np.arange(n))
    filled = np.flatnonzero(np.diff(np.append(bounds, len(owner))) > 0)

    def apply(p: np.ndarray) -> np.ndarray:
        out = p @ base if base.ndim == 2 else np.einsum("nij,nj->ni", base, p)
        if len(filled):
            weighted = np.einsum("md,md->m", vectors, p[owner])[:, None] * vectors
            out[filled] += np.add.reduceat(weighted, bounds[filled], axis=0)
        return out

    return _conjugate(apply, b, iters, tol, start)


def solve_batch(a: np.ndarray, b: np.ndarray, kind: str = "lu", iters: int = 32, tol: float = 1e-6, start: np.ndarray | None = None) -> np.ndarray:
    if kind == "lu":
        return solve_lu(a, b)
    if kind == "qr":
        return solve_qr(a, b)
    if kind == "cholesky":
        return solve_cholesky(a, b)
    if kind in ("cg", "cg_free"):
        return solve_cg(a, b, iters, tol, start)
    raise ValueError(f"unknown solver {kind!r}")


def residual(a: np.ndarray, b: np.ndarray, x: np.ndarray) -> np.ndarray:
    rest = np.einsum("nij,nj->ni", a, x) - b
    return np.linalg.norm(rest, axis=1) / np.maximum(np.linalg.norm(b, axis=1), np.finfo(float).tiny)


def bf16_round(x: np.ndarray) -> np.ndarray:
    """Nearest bfloat16 (ties to even), kept as float32; NaN stays."""
    bits = np.ascontiguousarray(x, dtype=np.float32).view(np.uint32)
    up = ((bits >> 16) & 1) + np.uint32(0x7FFF)
    out = ((bits + up) & np.uint32(0xFFFF0000)).view(np.float32)
    return np.where(np.isnan(x), np.float32(np.nan), out)


def bf16_pack(x: np.ndarray) -> np.ndarray:
    return (bf16_round(x).view(np.uint32) >> 16).astype("<u2")


def bf16_unpack(packed: np.ndarray) -> np.ndarray:
    return (packed.astype(np.uint32) << 16).view(np.float32)
