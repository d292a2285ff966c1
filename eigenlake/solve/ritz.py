"""Projection on a subspace, residuals, locking and bounds from Ritz values."""

from __future__ import annotations

import numpy as np

from ..linalg.small import small_eigh
from ..linalg.space import Space


def rayleigh_ritz(space: Space, q, method: str = "dc"):
    """(vectors, values, operator times vectors) of the projection on orthonormal columns q; one sweep."""
    aq = space.keep(space.apply(q))
    values, small = small_eigh(space.gram(q, aq), method)
    return space.keep(space.rotate(q, small)), values, space.rotate(aq, small)


def residuals(space: Space, vectors, values: np.ndarray, product=None, norm: str = "absolute", scale: float = 1.0) -> np.ndarray:
    """Norms of A v - theta v; a product at hand saves the sweep. 'relative' divides by an estimate of the operator's norm."""
    product = space.apply(vectors) if product is None else product
    out = space.residual_norms(product, vectors, values)
    return out / max(scale, 1e-300) if norm == "relative" else out


def lockable(res: np.ndarray, tol: float, order: str = "strict") -> np.ndarray:
    """Columns (ascending Ritz values) that may lock: below tol, from the wanted end without a gap if 'strict'."""
    good = res < tol
    if order == "free":
        return good
    if order == "strict":
        return np.cumprod(good).astype(bool)
    raise ValueError(f"unknown locking order: {order}")


def update_bounds(locked: np.ndarray, ritz: np.ndarray, b_sup: float) -> tuple[float, float, float]:
    """(mu_1, mu_ne, b_sup) from locked and active values together; b_sup grows if a value exceeds it."""
    every = np.concatenate([locked, ritz])
    low, high = float(every.min()), float(every.max())
    if high >= b_sup:
        b_sup = high + 0.05 * max(high - low, abs(high), 1e-300)
    return low, high, b_sup
