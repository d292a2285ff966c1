"""The filtered solver: spectra, variants, invariants and edges."""

from __future__ import annotations

import numpy as np
import pytest

from eigenlake import types
from eigenlake.build import spectra
from eigenlake.linalg.small import gaussian, householder, jacobi, small_eigh
from eigenlake.linalg.space import LocalSpace
from eigenlake.solve import bounds, degrees, ritz
from eigenlake.solve.driver import Options, solve


def matrix(kind: str, n: int) -> np.ndarray:
    tri = np.eye(n, k=1) + np.eye(n, k=-1)
    if kind == "onetwoone":
        return 2 * np.eye(n) + tri
    if kind == "wilkinson":
        return np.diag(np.abs(np.arange(n) - (n - 1) / 2)) + tri
    q = np.linalg.qr(gaussian(np.arange(n), n, 5))[0]
    if kind == "complex":
        a = gaussian(np.arange(n), n, 6, "c16")
        return a + a.conj().T
    return q.T @ np.diag(spectra.values(kind, n, eps=1e-2)) @ q


@pytest.mark.parametrize("kind", ["onetwoone", "wilkinson", "uniform", "geometric", "complex"])
@pytest.mark.parametrize("end", ["low", "high"])
def test_values_vectors_and_invariants(kind, end):
    a = matrix(kind, 120)
    exact = np.linalg.eigvalsh(a)[:: 1 if end == "low" else -1]
    s = solve(LocalSpace(a, 1.0 if end == "low" else -1.0), Options(9, 9, 1e-9, max_iter=200))
    assert s.converged and np.allclose(s.values, exact[:9], atol=1e-9)
    assert (s.residuals < 1e-9).all()
    assert np.abs(a @ s.vectors - s.vectors * s.values).max() < 1e-8
    assert np.abs(s.vectors.conj().T @ s.vectors - np.eye(9)).max() < 1e-9
    locked = [r["locked"] for r in s.trace if r["phase"] == "Filter"]
    assert locked == sorted(locked)
    assert s.matvecs == sum(sum(r["degrees"]) for r in s.trace if r["phase"] == "Filter")


@pytest.mark.parametrize("qr", ["local", "cholqr2", "tsqr"])
@pytest.mark.parametrize("small", ["dc", "jacobi", "qr"])
def test_kernels_agree_iteration_for_iteration(qr, small):
    a = matrix("wilkinson", 60)
    base, other = solve(LocalSpace(a), Options(6, 6)), solve(LocalSpace(a), Options(6, 6, qr=qr, small=small))
    assert (base.iterations, base.matvecs) == (other.iterations, other.matvecs)
    assert np.allclose(base.values, other.values, atol=1e-10)


@pytest.mark.parametrize(
    "more",
    [{"locking": False}, {"optimise_degree": False}, {"use_density": False}, {"residual_mode": "fresh"}, {"degree_policy": "sweeps"}, {"order": "free"}, {"residual_norm": "relative"}, {"bounds": (0.0, 0.2, 4.2)}, {"filter_dtype": "f4"}],
)
def test_variants_reach_the_same_values(more):
    a = matrix("onetwoone", 80)
    s = solve(LocalSpace(a), Options(6, 8, **more, max_iter=200))
    assert np.allclose(s.values, np.linalg.eigvalsh(a)[:6], atol=1e-8)


def test_reusing_the_product_saves_a_sweep_per_iteration():
    a = matrix("uniform", 80)
    once, twice = (solve(LocalSpace(a), Options(6, 8, residual_mode=m)) for m in ("reuse", "fresh"))
    # The mode that reuses products ends with one fresh product for all that is returned.
    assert twice.sweeps == once.sweeps - 1 + once.iterations


def test_equal_degrees_cost_fewer_or_equal_sweeps_and_more_products():
    a = matrix("geometric", 150)
    flops, sweeps = (solve(LocalSpace(a), Options(10, 10, degree_policy=p, max_iter=200)) for p in ("flops", "sweeps"))
    assert sweeps.matvecs >= flops.matvecs and sweeps.sweeps <= flops.sweeps + 40


def test_edges():
    assert solve(LocalSpace(np.array([[3.0]])), Options(1, 0)).values.tolist() == [3.0]
    assert np.allclose(solve(LocalSpace(np.zeros((6, 6))), Options(2, 2)).values, 0)
    a = matrix("onetwoone", 12)
    for nev, nex in ((11, 1), (3, 0), (12, 0)):
        assert np.allclose(solve(LocalSpace(a), Options(nev, nex, max_iter=500)).values, np.linalg.eigvalsh(a)[:nev], atol=1e-8)
    with pytest.raises(types.SubspaceTooLarge):
        solve(LocalSpace(a), Options(10, 3))
    exact = np.linalg.eigh(a)[1][:, :6]
    warm = solve(LocalSpace(a), Options(3, 3), exact)
    assert warm.iterations == 1
    with pytest.raises(types.NotConverged) as e:
        solve(LocalSpace(matrix("uniform", 60)), Options(5, 5, tol=1e-30, max_iter=3))
    assert e.value.result.iterations == 3
    one = solve(LocalSpace(matrix("uniform", 60)), Options(5, 5, max_iter=1, require_convergence=False))
    assert one.iterations == 1


def test_repeated_eigenvalues():
    one = matrix("onetwoone", 9)
    lattice = np.kron(one, np.eye(9)) + np.kron(np.eye(9), one)
    s = solve(LocalSpace(lattice), Options(8, 8, max_iter=200))
    assert np.allclose(s.values, np.linalg.eigvalsh(lattice)[:8], atol=1e-8)


def test_filter_is_the_ratio_of_chebyshev_polynomials():
    lam = np.linspace(0, 1, 40)
    space = LocalSpace(np.diag(lam))
    for m in (1, 2, 7, 20):
        out = np.diag(space.filter(np.eye(40), np.full(40, m), degrees.cheb_coeffs(0.0, 0.3, 1.0, m)))
        assert np.allclose(out, degrees.response(lam, 0.0, 0.3, 1.0, m), atol=1e-12)
        assert np.abs(out[lam >= 0.3]).max() <= 1 / abs(degrees.response(np.array([0.0]), 0.3, 0.3, 1.0, m)[0]) + 1e-12


def test_degrees():
    c, e = degrees.centre(0.3, 1.0)
    m = degrees.degrees(1e-10, np.array([1e-3, 1e-12, 1.0, 1e-3]), np.array([0.0, 0.0, 0.29, 0.5]), c, e)
    assert m.tolist()[1:] == [2, 36, 36] and m[0] % 2 == 0 and 2 <= m[0] < 36


def test_bounds_hold():
    for kind in ("uniform", "onetwoone", "wilkinson"):
        a = matrix(kind, 90)
        top = np.linalg.eigvalsh(a)[-1]
        for form in ("safe", "tight"):
            assert top <= bounds.upper_bound(LocalSpace(a), form=form) <= 1.6 * top
    low, high, grown = ritz.update_bounds(np.array([0.1]), np.array([0.2, 5.0]), 4.0)
    assert (low, high) == (0.1, 5.0) and grown > 5


def test_locking_order():
    res = np.array([1e-12, 1e-3, 1e-12])
    assert ritz.lockable(res, 1e-10).tolist() == [True, False, False]
    assert ritz.lockable(res, 1e-10, "free").tolist() == [True, False, True]


def test_small_solvers():
    for dtype in ("f8", "c16"):
        a = gaussian(np.arange(25), 25, 9, dtype)
        a = a + a.conj().T
        d, e, q = householder(a)
        t = np.diag(d) + np.diag(e, 1) + np.diag(e, -1)
        assert np.abs(q.conj().T @ a @ q - t).max() < 1e-12
        for w, v in (jacobi(a), small_eigh(a, "qr")):
            assert np.abs(a @ v - v * w).max() < 1e-11


def test_random_entries_do_not_depend_on_how_rows_are_dealt():
    whole = gaussian(np.arange(100), 3, 7)
    assert np.array_equal(whole[40:60], gaussian(np.arange(40, 60), 3, 7))
    assert abs(whole.mean()) < 0.3 and 0.7 < whole.std() < 1.3


def test_expressions_are_rewritten_before_they_run():
    from eigenlake.linalg.expr import Fused, Gram, Implicit, Formed, Leaf, PanelOps, apply, explain, rewrite

    a = matrix("uniform", 20)
    leaf = Leaf(LocalSpace(a))
    v = gaussian(np.arange(20), 3, 1)
    e = (2 * leaf.t.shift(0.5)).shift(1.0)
    assert isinstance(rewrite(e), Fused) and rewrite(e).inner == leaf
    assert np.allclose(apply(e, v), 2 * (a - 0.5 * np.eye(20)) @ v - v)
    assert np.allclose(apply((leaf + 3 * leaf).t, v), 4 * a @ v)
    assert "product alpha=2" in explain(rewrite(2 * leaf))
    assert isinstance(rewrite(Gram(None, "x", 10**9, 64)), Implicit) and isinstance(rewrite(Gram(None, "x", 100, 4)), Formed)
    space = LocalSpace(a)
    m = gaussian(np.arange(3), 2, 4)
    assert np.allclose(PanelOps.start(3).columns([2, 0, 1]).rotate(m).run(space, v), v[:, [2, 0, 1]] @ m)
    assert np.array_equal(PanelOps.start(3).columns([2, 0]).run(space, v), v[:, [2, 0]])


def test_returned_residuals_are_fresh():
    a = matrix("uniform", 80)
    s = solve(LocalSpace(a), Options(6, 8))
    assert s.trace[-1]["phase"] == "Check" and s.converged
    assert np.allclose(s.residuals, np.linalg.norm(a @ s.vectors - s.vectors * s.values, axis=0), atol=1e-14)
