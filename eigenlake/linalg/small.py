"""Dense routines on matrices that fit one task."""

from __future__ import annotations

import numpy as np

MASK = (1 << 64) - 1


def scramble(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x.astype(np.uint64, copy=True)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def gaussian(rows: np.ndarray, k: int, seed: int, dtype: str = "f8") -> np.ndarray:
    """Standard normal entries that depend on (seed, row, column) only, however rows are dealt out."""
    key = scramble(np.array([seed & MASK], np.uint64))[0]
    cell = scramble(rows.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(k, dtype=np.uint64)[None, :] * np.uint64(0xC2B2AE3D27D4EB4F) + key)

    def uniform(salt: int) -> np.ndarray:
        return ((scramble(cell + np.uint64(salt)) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)

    radius, turn = np.sqrt(-2 * np.log(uniform(1))), 2 * np.pi * uniform(2)
    if dtype == "c16":
        return radius * (np.cos(turn) + 1j * np.sin(turn)) / np.sqrt(2)
    return radius * np.cos(turn)


def small_eigh(g: np.ndarray, method: str = "dc") -> tuple[np.ndarray, np.ndarray]:
    """Ascending eigenpairs of a small self-adjoint matrix: 'dc' (divide and conquer), 'jacobi' or 'qr'."""
    g = (g + g.conj().T) / 2
    if method == "dc":
        return np.linalg.eigh(g)
    if method == "jacobi":
        return jacobi(g)
    if method == "qr":
        from ..baseline.tridiag import ql

        d, e, q = householder(g)
        values, vectors = ql(d, e)
        return values, q @ vectors
    raise ValueError(f"unknown small solver: {method}")


def jacobi(g: np.ndarray, sweeps: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """Cyclic Jacobi rotations."""
    a = np.array(g, complex if np.iscomplexobj(g) else float)
    n = len(a)
    v = np.eye(n, dtype=a.dtype)
    for _ in range(sweeps):
        off = np.abs(a - np.diag(np.diag(a))).max(initial=0)
        if off <= 1e-15 * max(1e-300, np.abs(a).max(initial=0)):
            break
        for p in range(n - 1):
            for q in range(p + 1, n):
                if abs(a[p, q]) == 0:
                    continue
                phase = a[p, q] / abs(a[p, q])
                tau = (a[q, q].real - a[p, p].real) / (2 * abs(a[p, q]))
                t = (1 if tau >= 0 else -1) / (abs(tau) + np.hypot(1, tau))
                c = 1 / np.hypot(1, t)
                s = t * c
                turn = np.array([[c, s * phase], [-s * np.conj(phase), c]], a.dtype)
                a[:, [p, q]] = a[:, [p, q]] @ turn
                a[[p, q], :] = turn.conj().T @ a[[p, q], :]
                v[:, [p, q]] = v[:, [p, q]] @ turn
    values = np.diag(a).real
    order = np.argsort(values)
    return values[order], v[:, order]


def householder(g: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Real tridiagonal (diagonal, off-diagonal) and basis Q with Q^H g Q tridiagonal."""
    a = np.array(g, complex if np.iscomplexobj(g) else float)
    n = len(a)
    q = np.eye(n, dtype=a.dtype)
    for k in range(n - 2):
        x = a[k + 1 :, k].copy()
        size = np.linalg.norm(x)
        if size == 0:
            continue
        x[0] += (x[0] / abs(x[0]) if x[0] != 0 else 1) * size
        x /= np.linalg.norm(x)
        a[k + 1 :, :] -= 2 * np.outer(x, x.conj() @ a[k + 1 :, :])
        a[:, k + 1 :] -= 2 * np.outer(a[:, k + 1 :] @ x, x.conj())
        q[:, k + 1 :] -= 2 * np.outer(q[:, k + 1 :] @ x, x.conj())
    e = np.array([a[k + 1, k] for k in range(n - 1)])
    if np.iscomplexobj(a):
        phase = np.ones(n, complex)
        for k in range(n - 1):
            phase[k + 1] = phase[k] * (e[k] / abs(e[k]) if e[k] != 0 else 1)
        q = q * phase[None, :]
        e = np.abs(e)
    return np.diag(a).real.copy(), np.asarray(e).real.copy(), q


def cholesky_inverse(s: np.ndarray) -> np.ndarray | None:
    """R^-1 with s = R^H R, shifted if s is nearly singular; None if that fails too."""
    s = (s + s.conj().T) / 2
    for shift in (0.0, 11 * np.finfo(float).eps * max(1, len(s)) * np.trace(s).real):
        try:
            r = np.linalg.cholesky(s + shift * np.eye(len(s))).conj().T
            if np.isfinite(r).all() and np.abs(np.diag(r)).min(initial=1) > 0:
                return np.linalg.inv(r)
        except np.linalg.LinAlgError:
            continue
    return None
