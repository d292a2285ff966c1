"""Coefficients of the filter and the degree each column needs."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def centre(mu_ne: float, b_sup: float) -> tuple[float, float]:
    """Centre and half-width of the part of the spectrum to damp."""
    return (b_sup + mu_ne) / 2, (b_sup - mu_ne) / 2


def cheb_coeffs(mu_1: float, mu_ne: float, b_sup: float, degree: int) -> list[tuple[float, float, float]]:
    """(alpha, beta, gamma) of each step: new = alpha (A - gamma I) now + beta before.

    Scaled so that the response at mu_1 stays 1, which keeps large degrees
    from overflowing.
    """
    c, e = centre(mu_ne, b_sup)
    sigma_1 = e / (mu_1 - c)
    out, sigma = [(sigma_1 / e, 0.0, c)], sigma_1
    for _ in range(1, degree):
        after = 1 / (2 / sigma_1 - sigma)
        out.append((2 * after / e, -sigma * after, c))
        sigma = after
    return out[:degree]


def degrees(tol: float, residuals: np.ndarray, ritz: np.ndarray, c: float, e: float, max_degree: int = 36, even: bool = True) -> np.ndarray:
    """Steps after which each column's residual should fall below tol.

    A column's error shrinks by rho per step, the growth of the Chebyshev
    polynomial at its Ritz value. A value inside the damped part gets the
    highest degree.
    """
    t = (np.asarray(ritz) - c) / e
    root = np.sqrt(np.maximum(t * t - 1, 0))
    rho = np.maximum(np.abs(t - root), np.abs(t + root))
    need = np.log(np.maximum(np.asarray(residuals), tol) / tol)
    with np.errstate(divide="ignore", invalid="ignore"):
        m = np.where(rho > 1 + 1e-12, np.ceil(need / np.log(rho)), max_degree)
    m = np.clip(m, 2, max_degree).astype(int)
    if even:
        m = np.minimum(m + m % 2, max_degree - max_degree % 2)
    return m


def worthwhile(wanted: float, c: float, e: float, gain: float = 1e3, most: int = 1 << 14) -> int:
    """The even degree at which a pass damps the unwanted part by `gain` against a wanted value."""
    t = abs(wanted - c) / e
    grows = math.acosh(t) if t > 1 else 0.0
    m = most if grows * most <= math.acosh(gain) else math.ceil(math.acosh(gain) / grows)
    return m + m % 2


def degree_column(tol: float, residual: Column, ritz: Column, c: float, e: float, max_degree: int = 36) -> Column:
    """`degrees` as a column expression, made even."""
    t = (ritz - F.lit(c)) / F.lit(e)
    root = F.sqrt(F.greatest(t * t - 1, F.lit(0.0)))
    rho = F.greatest(F.abs(t - root), F.abs(t + root))
    need = F.ln(F.greatest(residual, F.lit(tol)) / F.lit(tol))
    m = F.when(rho > 1 + 1e-12, F.ceil(need / F.ln(rho))).otherwise(F.lit(max_degree))
    m = F.least(F.greatest(m, F.lit(2)), F.lit(max_degree))
    return F.least(m + m % 2, F.lit(max_degree - max_degree % 2)).cast("int")


def response(values: np.ndarray, mu_1: float, mu_ne: float, b_sup: float, degree: int) -> np.ndarray:
    """What the filter makes of eigenvalues: the ratio of Chebyshev polynomials at them and at mu_1."""
    c, e = centre(mu_ne, b_sup)

    def chebyshev(t: np.ndarray) -> np.ndarray:
        t = np.asarray(t, float)
        inside = np.cos(degree * np.arccos(np.clip(t, -1, 1)))
        outside = np.sign(t) ** degree * np.cosh(degree * np.arccosh(np.maximum(np.abs(t), 1)))
        return np.where(np.abs(t) <= 1, inside, outside)

    return chebyshev((np.asarray(values) - c) / e) / chebyshev((mu_1 - c) / e)


def equalised(degrees_: np.ndarray, policy: str) -> np.ndarray:
    """Degrees under a policy: 'flops' keeps them, 'sweeps' lifts all to the highest (a sweep costs the same for any column)."""
    if policy == "flops":
        return degrees_
    if policy == "sweeps":
        return np.full_like(degrees_, degrees_.max(initial=2))
    raise ValueError(f"unknown degree policy: {policy}")


def matvecs(degrees_: np.ndarray) -> int:
    return int(np.sum(degrees_))


def sweeps(degrees_: np.ndarray, paired: bool = False) -> int:
    top = int(np.max(degrees_, initial=0))
    return math.ceil(top / 2) if paired else top
