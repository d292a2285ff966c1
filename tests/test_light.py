"""Operators held by few numbers, filters as long as they are worth, and thresholds that double precision can meet."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from eigenlake.baseline import tridiag
from eigenlake.build import spectra
from eigenlake.build import tridiag as bands
from eigenlake.linalg.operators import Reflected, banded
from eigenlake.linalg.space import LocalSpace
from eigenlake.solve import bounds, degrees, driver


def test_banded_and_reflected_are_their_matrices():
    rng = np.random.default_rng(4)
    a = np.diag(rng.normal(size=5000)) + np.diag(rng.normal(size=4997), 3) + np.diag(rng.normal(size=4998), -2)
    i, j = np.nonzero(a)
    x = rng.normal(size=(5000, 3))
    assert np.allclose(banded(i, j, a[i, j], 5000) @ x, a @ x)
    assert banded(np.zeros(20, int), np.arange(20), np.ones(20), 20) is None
    u, lam = rng.normal(size=40), rng.normal(size=40)
    h = np.eye(40) - 2 * np.outer(u, u) / (u @ u)
    assert np.allclose(Reflected(lam, u) @ x[:40], h @ np.diag(lam) @ h @ x[:40])


def test_a_diagonal_operator_needs_no_square(spark):
    """Of order 200,000: its square would take 320 GB."""
    lam = np.linspace(0, 1, 200_000)
    assert 1 <= bounds.upper_bound(LocalSpace(lam)) < 1.5
    got = LocalSpace(lam).filter(np.ones((len(lam), 1)), np.array([8]), degrees.cheb_coeffs(0.0, 0.3, 1.0, 8))[:, 0]
    assert np.allclose(got, degrees.response(lam, 0.0, 0.3, 1.0, 8))


def test_long_filters_converge_where_the_spectrum_is_dense(spark):
    n = 3000
    result = driver.eigs(bands.tridiag_121(spark.range(n), "id"), n, 4, 6, max_iter=40)
    assert result.how == "single_task"
    assert np.allclose(result.solution.values, spectra.values("onetwoone", n)[:4], atol=1e-9)
    found = driver.eigs_reflected(spectra.spectrum(spark.range(n), "id", "geometric"), F.sin(F.col("k").cast("double")), n, 4, 6, max_iter=40)
    assert np.allclose(found.solution.values, spectra.values("geometric", n)[:4], atol=1e-9)


def test_a_threshold_below_double_precision_is_met_as_far_as_it_goes():
    rng = np.random.default_rng(5)
    a = 1e9 * np.abs(rng.normal(size=(50, 50)))
    a = a + a.T
    s = driver.solve(LocalSpace(a, -1.0), driver.Options(1, 6, tol=1e-8))
    assert s.converged and np.isclose(s.values[0], np.linalg.eigvalsh(a)[-1], rtol=1e-13)


@pytest.mark.parametrize("n", [300, 3000])
def test_bisection_cuts_by_many_shifts_at_once(monkeypatch, n):
    calls, plain = [], tridiag.counts
    monkeypatch.setattr(tridiag, "counts", lambda *a: calls.append(1) or plain(*a))
    got = tridiag.bisect(np.full(n, 2.0), np.ones(n - 1), np.arange(5))
    assert np.allclose(got, spectra.values("onetwoone", n)[:5], atol=1e-12)
    assert n < 3000 or len(calls) < 20
