"""Dense linear algebra on one machine, in NumPy; the serial version of the methods."""

from __future__ import annotations

import numpy as np


def canonical(v: np.ndarray) -> np.ndarray:
    """Signs (+1 or -1) that make the entry of largest magnitude of each column positive; the first one of equals counts."""
    if not v.size:
        return np.ones(v.shape[1])
    at = np.round(v, 10)
    at = np.abs(at, out=at).argmax(axis=0)
    return np.where(v[at, np.arange(v.shape[1])] < 0, -1.0, 1.0)


def retain_by_diagonal(r: np.ndarray, working_precision: float) -> np.ndarray:
    """Columns whose diagonal entry of R is not numerically zero, measured against the first one; not only trailing ones drop."""
    d = np.abs(np.diag(r))
    if not len(d) or not d.any():
        return np.zeros(0, np.int64)
    return np.flatnonzero((d > 0) & (d >= d[0] * working_precision))


def retain_by_norm(norms: np.ndarray, working_precision: float) -> np.ndarray:
    """Columns whose norm is not numerically zero, measured against the largest by the square root of the working precision."""
    top = norms.max(initial=0.0)
    return np.flatnonzero((norms > 0) & (norms >= top * np.sqrt(working_precision)))


def r_of(*blocks: np.ndarray) -> np.ndarray:
    return np.linalg.qr(np.vstack(blocks), mode="r")


def triangular_solve(x: np.ndarray, r: np.ndarray, block: int = 64) -> np.ndarray:
    """x r^-1 for upper triangular r, by blocked substitution; no inverse of the whole is formed."""
    out = np.array(x, float)
    n = r.shape[0]
    for lo in range(0, n, block):
        hi = min(lo + block, n)
        if lo:
            out[:, lo:hi] -= out[:, :lo] @ r[:lo, lo:hi]
        out[:, lo:hi] = np.linalg.solve(r[lo:hi, lo:hi].T, out[:, lo:hi].T).T
    return out


def eigen(b: np.ndarray) -> np.ndarray:
    """Eigenvectors of a symmetric matrix, by falling eigenvalues; those of rows of zeros are unit vectors, exactly, and come last."""
    b = np.add(b, b.T, dtype=float)
    b /= 2
    there = b.any(axis=1)
    if there.all():
        return np.linalg.eigh(b)[1][:, ::-1]
    some, none = np.flatnonzero(there), np.flatnonzero(~there)
    out = np.zeros(b.shape)
    out[np.ix_(some, np.arange(len(some)))] = np.linalg.eigh(b[np.ix_(some, some)])[1][:, ::-1]
    out[none, np.arange(len(some), len(b))] = 1.0
    return out


def pivot_rows(y: np.ndarray) -> np.ndarray:
    """Rows that partial pivoting would choose, as many as there are columns."""
    a, rows = y.copy(), np.arange(len(y))
    k = min(a.shape)
    for j in range(k):
        p = j + int(np.abs(a[j:, j]).argmax())
        a[[j, p]], rows[[j, p]] = a[[p, j]], rows[[p, j]]
        if a[j, j] != 0:
            a[j + 1 :] -= np.outer(a[j + 1 :, j] / a[j, j], a[j])
    return y[rows[:k]]


def exact_svd(a: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """U, sigma, V of a matrix in memory."""
    u, s, vt = np.linalg.svd(a, full_matrices=False)
    return u, s, vt.T


def optimal_error(sigma: np.ndarray, k: int) -> float:
    """The least spectral-norm error of any approximation of rank k: the next singular value."""
    return float(sigma[k]) if k < len(sigma) else 0.0


def subspace_gap(a: np.ndarray, b: np.ndarray) -> float:
    """Spectral norm of the difference of the projectors onto two column spaces with orthonormal bases."""
    return float(np.linalg.norm(a @ a.T - b @ b.T, 2))
