"""Iterative solvers to compare with: plain subspace iteration, thick-restart Lanczos, rational filter, shift-invert slices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import types
from ..linalg import blocks as layout
from ..linalg.operators import Banded, TridiagonalInverse
from ..linalg.small import gaussian, householder
from ..linalg.space import LocalSpace, Space
from ..session import broadcast_limit
from ..solve.driver import Options, Solution, _anchor, operator, solve
from .direct import ONE_TASK
from .tridiag import _interval, counts


class Inverted(LocalSpace):
    """-(B - s)^-1 for B = sign * A of three diagonals and an s just below the spectrum, by one factorisation.

    Its low end has the vectors of B's low end, in the same order, and lies far
    from the rest even where B's is dense: with products of the (1-2-1)
    operator alone, the passes that are needed grow with the square of its order.
    """

    def __init__(self, space: LocalSpace):
        below, d, above = (space.sign * x for x in space.a.tridiagonal())
        self.plain, self.shift = space, _interval(d.real, above[:-1])[0]
        self.a, self.n, self.sign, self.dtype, self.light = TridiagonalInverse(below, d, above, self.shift), space.n, -1.0, space.dtype, True


def _iterated(space: Space) -> Space:
    """What a solver without a filter iterates with: the inverse where three diagonals hold the operator, else the operator."""
    banded = isinstance(space, LocalSpace) and isinstance(space.a, Banded) and space.a.tridiagonal() is not None
    return Inverted(space) if banded else space


def _read(work: Space, vectors, theta: np.ndarray, res: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The operator's values, their residuals, and the larger of these and of the inverse's relative to its norm."""
    if not isinstance(work, Inverted):
        return theta, res, res
    values = work.shift - 1 / theta
    own = work.plain.residual_norms(work.plain.apply(vectors), vectors, values)
    return values, own, np.maximum(own, res / np.abs(theta).max())


def _sweeps(space: Space, work: Space) -> int:
    return space.sweeps + (work.sweeps if work is not space else 0)


def subspace_eigs(space: Space, nev: int, nex: int, tol: float = 1e-8, max_iter: int = 2000) -> Solution:
    """Subspace iteration without a filter: multiply by (b_sup - A), or by A's inverse where it has three diagonals, orthonormalise, project."""
    from ..solve.bounds import upper_bound
    from ..solve.ritz import rayleigh_ritz, residuals

    work = _iterated(space)
    top = upper_bound(space) if work is space else None
    v = space.random(nev + nex, 8)
    matvecs = 0
    for k in range(1, max_iter + 1):
        v = space.orthonormalise(None, work.apply(v) if top is None else space.step(v, None, -1.0, 0.0, top))
        matvecs += nev + nex
        v, theta, product = rayleigh_ritz(work, v)
        ritz, res, worst = _read(work, v, theta, residuals(work, v, theta, product))
        if (worst[:nev] < tol).all():
            break
    order = np.arange(nev)
    return Solution(getattr(space, "sign", 1.0) * ritz[:nev], res[:nev], np.full(nev, k), space.columns(v, order), [], k, matvecs, _sweeps(space, work), bool((worst[:nev] < tol).all()))


def lanczos_eigs(space: Space, nev: int, keep: int | None = None, size: int | None = None, tol: float = 1e-8, max_restart: int = 200) -> Solution:
    """Thick-restart Lanczos with full orthogonalisation: one column, so one product (with A's inverse where it has three diagonals), per step."""
    keep = keep or nev + 4
    size = min(space.n, size or 2 * keep + 10)
    work = _iterated(space)
    v = space.orthonormalise(None, space.random(1, 8))
    basis, image, matvecs = None, None, 0
    for turn in range(1, max_restart + 1):
        while basis is None or space.gram(basis, basis).shape[0] < size:
            basis = v if basis is None else space.beside(basis, v)
            w = work.apply(v)
            image = w if image is None else space.beside(image, w)
            matvecs += 1
            if space.gram(basis, basis).shape[0] == space.n:
                break
            v = space.orthonormalise(basis, w)
        theta, s = np.linalg.eigh((lambda g: (g + g.conj().T) / 2)(space.gram(basis, image)))
        some = s[:, :keep]
        ritz, product = space.rotate(basis, some), space.rotate(image, some)
        values, res, worst = _read(work, ritz, theta[:keep], space.residual_norms(product, ritz, theta[:keep]))
        if (worst[:nev] < tol).all():
            break
        v = space.orthonormalise(ritz, v)
        basis, image = ritz, product
    at = np.arange(nev)
    return Solution(getattr(space, "sign", 1.0) * values[:nev], res[:nev], np.full(nev, turn), space.columns(ritz, at), [], turn, matvecs, _sweeps(space, work), bool((worst[:nev] < tol).all()))


def _contour(low: float, high: float, nodes: int) -> tuple[np.ndarray, np.ndarray]:
    """Where the upper half of a circle through low and high is sampled, as offsets from its centre, and the weights."""
    x, w = np.polynomial.legendre.leggauss(nodes)
    return (high - low) / 2 * np.exp(1j * np.pi * (x + 1) / 2), w


def _resolvent(a: np.ndarray | Banded, shift: complex) -> np.ndarray | TridiagonalInverse | None:
    """(a - shift)^-1 where a has three diagonals, so that it is held by them; None elsewhere."""
    three = a.tridiagonal() if isinstance(a, Banded) else None
    return TridiagonalInverse(*three, shift) if three is not None else None


def _whole(a: np.ndarray | Banded) -> np.ndarray:
    return a.dense() if isinstance(a, Banded) else a


def _node_term(a: np.ndarray | Banded, y: np.ndarray, centre: float, offset: complex, weight: float) -> np.ndarray:
    """What one node adds to the filtered block: one factorisation of a shifted operator."""

    def at(offset: complex) -> np.ndarray:
        inverse = _resolvent(a, centre + offset)
        if inverse is not None:
            return -weight / 2 * offset * (inverse @ y)
        return weight / 2 * offset * np.linalg.solve((centre + offset) * np.eye(len(a)) - _whole(a), y)

    return (at(offset) + at(np.conj(offset))) / 2 if np.issubdtype(a.dtype, np.complexfloating) else at(offset).real


def _contour_pairs(a: np.ndarray | Banded, q: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ritz values, vectors and residuals in the range of a filtered block."""
    u, s, _ = np.linalg.svd(q, full_matrices=False)
    u = u[:, s > 1e-10 * s[0]]
    theta, v = np.linalg.eigh(u.conj().T @ (a @ u))
    y = u @ v
    return theta, y, np.linalg.norm(a @ y - y * theta, axis=0)


def _wanted(a: np.ndarray | Banded, shifts: np.ndarray) -> np.ndarray:
    """How many eigenvalues lie between each two neighbouring shifts, by inertia."""
    three = a.tridiagonal() if isinstance(a, Banded) else None
    d, e = (three[1], three[2][:-1]) if three is not None else householder(_whole(a))[:2]
    return np.diff(counts(d, e, np.asarray(shifts, float)))


def _accepted(theta: np.ndarray, res: np.ndarray, low: float, high: float, want: int, tol: float) -> tuple[np.ndarray, bool]:
    """The `want` best pairs inside, in order, and whether all have converged; other values inside are ghosts."""
    inside = np.flatnonzero((theta >= low) & (theta < high))
    good = np.sort(inside[np.argsort(res[inside], kind="stable")[:want]])
    return good, len(good) == want and bool((res[good] < tol * max(1, abs(low), abs(high))).all())


def rational_eigs(a: np.ndarray, low: float, high: float, m0: int, nodes: int = 8, tol: float = 1e-10, max_iter: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues in (low, high) by contour quadrature: a linear solve at each node, sum, project.

    The block has m0 columns, and at least two more than there are values inside.
    """
    offsets, weights = _contour(low, high, nodes)
    want = int(_wanted(a, (low, high))[0])
    y = LocalSpace(a).random(min(max(m0, want + 2), len(a)), 8)
    for _ in range(max_iter):
        theta, y, res = _contour_pairs(a, sum(_node_term(a, y, (low + high) / 2, z, w) for z, w in zip(offsets, weights)))
        good, done = _accepted(theta, res, low, high, want, tol)
        if done:
            break
    return theta[good], y[:, good]


def _copies(coo: DataFrame, n: int, key: str, count: int) -> DataFrame:
    """The entries of an operator that fits a task (known to have three diagonals, or of an order that is not too large), once for each of `count` tasks."""
    if n > ONE_TASK and getattr(coo, "_bands", n) > 3:
        raise types.DoesNotFit(f"order {n} is beyond one task; a factorised shift stops at {ONE_TASK}")
    each = F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias(key)
    return coo.unionByName(_anchor(coo)).select("*", each)


def _counted(coo: DataFrame, n: int, shifts: np.ndarray) -> DataFrame:
    """(slice, want): how many eigenvalues each slice holds, counted in one task."""

    def count(table: pa.Table) -> pa.Table:
        want = _wanted(operator(table, n), shifts)
        return pa.table({"slice": pa.array(np.arange(len(want)), pa.int32()), "want": want.astype(np.int64)})

    return coo.unionByName(_anchor(coo)).groupBy(F.lit(1).alias("one")).applyInArrow(count, "slice int, want long")


def rational_rows(coo: DataFrame, n: int, low: float, high: float, m0: int, nodes: int = 8, tol: float = 1e-10, max_iter: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """`rational_eigs` with a task for each node: (values, residuals).

    The operator is copied to the nodes once and stays there; an iteration sends
    them the block (n x m0, which must fit a broadcast) and sums their terms.
    """
    spark, kind = coo.sparkSession, np.dtype(layout.kind(coo))
    copies = _copies(coo, n, "node", nodes)
    want = int(_counted(coo, n, np.array([low, high])).first()["want"])
    m0 = min(max(m0, want + 2), n)
    if n * m0 * kind.itemsize > broadcast_limit(spark):
        raise types.DoesNotFit(f"a block of {n} x {m0} is beyond the broadcast limit")
    offsets, weights = _contour(low, high, nodes)
    centre = (low + high) / 2
    held = copies.repartition(nodes, "node").persist()
    one = F.lit(1).alias("one")
    y = gaussian(np.arange(n), m0, 8, layout.kind(coo))
    try:
        for _ in range(max_iter):
            block = spark.sparkContext.broadcast(y)

            def term(key: tuple, table: pa.Table) -> pa.Table:
                node = key[0].as_py()
                part = _node_term(operator(table, n), block.value, centre, offsets[node], weights[node])
                return pa.table({"node": pa.array([node], pa.int32()), "part": [np.ascontiguousarray(part).tobytes()]})

            def project(table: pa.Table, parts: pa.Table) -> pa.Table:
                parts = parts.sort_by("node").column("part").to_pylist()
                theta, v, res = _contour_pairs(operator(table, n), sum(np.frombuffer(x, kind).reshape(n, -1) for x in parts))
                return pa.table({k: [np.ascontiguousarray(x).tobytes()] for k, x in (("theta", theta), ("vectors", v), ("res", res))})

            parts = held.groupBy("node").applyInArrow(term, "node int, part binary")
            row = coo.unionByName(_anchor(coo)).groupBy(one).cogroup(parts.groupBy(one)).applyInArrow(project, "theta binary, vectors binary, res binary").first()
            theta, res = np.frombuffer(row["theta"]), np.frombuffer(row["res"])
            y = np.frombuffer(row["vectors"], kind).reshape(n, -1)
            block.unpersist()
            good, done = _accepted(theta, res, low, high, want, tol)
            if done:
                break
    finally:
        held.unpersist()
    return theta[good], res[good]


def _in_slice(a: np.ndarray | Banded, lo: float, hi: float, want: int, width: int, tol: float, max_iter: int) -> tuple[np.ndarray, np.ndarray]:
    """The `want` eigenvalues in [lo, hi) and their residuals, by inverse subspace iteration at the middle."""
    shift = float((lo + hi) / 2 + 1e-13 * (hi - lo))
    inverse = _resolvent(a, shift)
    if inverse is None:
        inverse = np.linalg.inv(_whole(a) - shift * np.eye(len(a)))
    v = LocalSpace(a).random(min(len(a), want + width), 8)
    for _ in range(max_iter):
        q = np.linalg.qr(inverse @ v)[0]
        theta, s = np.linalg.eigh(q.conj().T @ (a @ q))
        v = q @ s
        res = np.linalg.norm(a @ v - v * theta, axis=0)
        good, done = _accepted(theta, res, lo, hi, want, tol)
        if done:
            break
    return theta[good], res[good]


def slice_eigs(a: np.ndarray, shifts: np.ndarray, width: int = 8, tol: float = 1e-10, max_iter: int = 60) -> np.ndarray:
    """All eigenvalues between the first and last shift: inverse subspace iteration at the middle of each slice."""
    shifts = np.asarray(shifts, float)
    found = [_in_slice(a, lo, hi, int(want), width, tol, max_iter)[0] for lo, hi, want in zip(shifts, shifts[1:], _wanted(a, shifts)) if want]
    return np.sort(np.concatenate([np.zeros(0), *found]))


def slice_rows(coo: DataFrame, n: int, shifts: np.ndarray, width: int = 8, tol: float = 1e-10, max_iter: int = 60) -> DataFrame:
    """`slice_eigs` with a task for each slice: (slice, eigenvalue, residual). One task counts what the slices hold."""
    shifts = np.asarray(shifts, float)

    def solve_slice(key: tuple, table: pa.Table, wanted: pa.Table) -> pa.Table:
        at, want = key[0].as_py(), wanted.column("want")[0].as_py()
        w, res = _in_slice(operator(table, n), shifts[at], shifts[at + 1], want, width, tol, max_iter) if want else (np.zeros(0), np.zeros(0))
        return pa.table({"slice": pa.array([at] * len(w), pa.int32()), "eigenvalue": w, "residual": res})

    copies = _copies(coo, n, "slice", len(shifts) - 1)
    return copies.groupBy("slice").cogroup(_counted(coo, n, shifts).groupBy("slice")).applyInArrow(solve_slice, "slice int, eigenvalue double, residual double")


def filtered(a: np.ndarray, nev: int, nex: int, end: str = "low", **options) -> Solution:
    """The filtered solver on a matrix in memory, for comparisons."""
    return solve(LocalSpace(a, -1.0 if end == "high" else 1.0), Options(nev, nex, end=end, **options))
