"""Spectral bounds: repeated Lanczos runs and the density of states they sample."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..linalg.space import Space


@dataclass
class Density:
    """Quadrature nodes and weights of the spectrum, averaged over runs; and a safe upper bound."""

    theta: np.ndarray
    weight: np.ndarray
    upper: float

    def cdf(self, at: np.ndarray) -> np.ndarray:
        """Estimated share of eigenvalues at or below."""
        order = np.argsort(self.theta)
        total = np.concatenate([[0], np.cumsum(self.weight[order])])
        return total[np.searchsorted(self.theta[order], np.asarray(at), "right")]

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(float(t), float(w)) for t, w in zip(self.theta, self.weight)], "theta double, weight double")


def lanczos(space: Space, steps: int = 25, runs: int = 4, seed: int = 7) -> list[tuple[np.ndarray, np.ndarray]]:
    """Tridiagonals (diagonal, off-diagonal with the last remainder) of `runs` runs.

    All runs travel as one panel, so a step is one sweep over the operator
    whatever their number. A run that has used up its invariant subspace is
    cut off where its remainder vanishes.
    """
    steps = min(steps, space.n)
    v = space.random(runs, seed)
    v = space.rotate(v, np.diag(1 / np.sqrt(np.diag(space.gram(v, v)).real)))
    before, alphas, betas = None, [], []
    for k in range(steps):
        w = space.apply(v)
        a = np.diag(space.gram(v, w)).real
        w = space.minus(w, v, np.diag(a))
        if before is not None:
            w = space.minus(w, before, np.diag(betas[-1]))
        w = space.keep(w)
        b = np.sqrt(np.maximum(np.diag(space.gram(w, w)).real, 0))
        alphas.append(a)
        betas.append(b)
        if (b <= 1e-13 * (1 + np.abs(a))).all() or k == steps - 1:
            break
        before, v = v, space.keep(space.rotate(w, np.diag(np.where(b > 0, 1 / np.where(b > 0, b, 1), 0))))
    out = []
    alpha, beta = np.array(alphas), np.array(betas)
    for r in range(runs):
        small = np.flatnonzero(beta[:, r] <= 1e-12 * (1 + np.abs(alpha[:, r])))
        m = int(small[0]) + 1 if len(small) else len(alpha)
        out.append((alpha[:m, r], beta[:m, r]))
    return out


def density(runs: list[tuple[np.ndarray, np.ndarray]], form: str = "safe") -> Density:
    """Nodes are the tridiagonals' eigenvalues, weights the squared first components of their vectors.

    The upper bound adds the last remainder to the largest node ('safe'), or to
    each node only as much of it as its own residual holds ('tight').
    """
    theta, weight, upper = [], [], -np.inf
    for a, b in runs:
        t = np.diag(a) + np.diag(b[: len(a) - 1], 1) + np.diag(b[: len(a) - 1], -1)
        values, vectors = np.linalg.eigh(t)
        theta.append(values)
        weight.append(vectors[0] ** 2 / len(runs))
        left = abs(b[len(a) - 1])
        upper = max(upper, values[-1] + left if form == "safe" else float((values + left * np.abs(vectors[-1])).max()))
    return Density(np.concatenate(theta), np.concatenate(weight), float(upper))


def upper_bound(space: Space, steps: int = 25, runs: int = 4, seed: int = 7, form: str = "safe") -> float:
    """A number no eigenvalue exceeds, in all but freak cases; the solver enlarges it if one does."""
    return density(lanczos(space, steps, runs, seed), form).upper


def estimate(space: Space, ne: int, steps: int = 25, runs: int = 4, seed: int = 7, use_density: bool = True) -> tuple[float, float, float]:
    """(mu_1, mu_ne, b_sup): the lowest value, the value with ne below it, and the upper bound.

    Without the density of states mu_ne comes from the plain share of the way
    between the extremes.
    """
    d = density(lanczos(space, steps, runs, seed))
    mu_1 = float(d.theta.min())
    span = max(d.upper - mu_1, 1e-8 * max(1.0, abs(mu_1)))
    top = mu_1 + span
    if use_density:
        order = np.argsort(d.theta)
        at = np.searchsorted(np.cumsum(d.weight[order]), ne / space.n)
        mu_ne = float(d.theta[order][min(at, len(order) - 1)])
    else:
        mu_ne = mu_1 + span * ne / space.n
    mu_ne = min(max(mu_ne, mu_1 + 1e-3 * span), top - 0.05 * span)
    return mu_1, mu_ne, top


def quantile(nodes: DataFrame, share: float) -> DataFrame:
    """The quantile rule on a table (theta, weight): the first node at which the cumulative weight reaches `share`.

    The window has no partition: it runs over quadrature nodes, of which
    there are runs times steps.
    """
    total = nodes.agg(F.sum("weight").alias("total"))
    by = Window.orderBy("theta").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    cdf = nodes.crossJoin(total).select("theta", (F.sum("weight").over(by) / F.col("total")).alias("cdf"))
    return cdf.where(F.col("cdf") >= share).agg(F.min("theta").alias("theta"))
