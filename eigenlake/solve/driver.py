"""The filtered solver: block subspace iteration with a Chebyshev polynomial filter."""

from __future__ import annotations

import json
import time
import uuid
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import types
from ..linalg import blocks as layout
from ..linalg.operators import BANDS, Banded, Reflected, banded
from ..linalg.space import LocalSpace, Space, SparkSpace
from ..session import broadcast_limit
from . import bounds as spectral
from .degrees import centre, cheb_coeffs, degrees, equalised, worthwhile
from .ritz import lockable, rayleigh_ritz, residuals, update_bounds

#: Entries of the operator up to which the whole solve runs inside one task.
SINGLE_TASK = 4_000_000
#: Orders up to which operators of few diagonals are multiplied as dense ones.
SMALL = 256


@dataclass
class Options:
    """How to solve. See `eigs`."""

    nev: int
    nex: int = 8
    tol: float = 1e-10
    deg: int = 20
    end: str = "low"
    max_iter: int = 50
    max_deg: int = 36
    optimise_degree: bool = True
    degree_policy: str = "flops"
    locking: bool = True
    order: str = "strict"
    bounds: tuple[float, float, float] | None = None
    use_density: bool = True
    lanczos_steps: int = 25
    lanczos_runs: int = 4
    qr: str = "cholqr2"
    small: str = "dc"
    residual_mode: str = "reuse"
    residual_norm: str = "absolute"
    filter_dtype: str = "f8"
    require_convergence: bool = True
    seed: int = 7


@dataclass
class Solution:
    """What one solve gives: ascending from the low end, or descending for 'high'."""

    values: np.ndarray
    residuals: np.ndarray
    iteration: np.ndarray
    vectors: object
    trace: list[dict]
    iterations: int
    matvecs: int
    sweeps: int
    converged: bool
    ritz: np.ndarray = field(default_factory=lambda: np.zeros(0))


def solve(space: Space, o: Options, start=None) -> Solution:
    """Iterate filter, orthonormalise, project, lock until nev pairs are locked."""
    ne = o.nev + o.nex
    if o.nev < 1 or o.nex < 0 or ne > space.n:
        raise types.SubspaceTooLarge(f"nev + nex = {ne} for an operator of order {space.n}")
    run, trace = uuid.uuid4().hex[:12], []
    clock = [time.perf_counter()]

    def note(iteration: int, phase: str, **more) -> None:
        now = time.perf_counter()
        trace.append({"run_id": run, "iteration": iteration, "phase": phase, "seconds": now - clock[0], "sweeps": space.sweeps, **more})
        clock[0] = now

    if o.bounds is not None:
        mu_1, mu_ne, b_sup = o.bounds
    else:
        mu_1, mu_ne, b_sup = spectral.estimate(space, ne, o.lanczos_steps, o.lanczos_runs, o.seed, o.use_density)
    note(0, "Lanczos", mu_1=mu_1, mu_ne=mu_ne, b_sup=b_sup)
    v = space.random(ne, o.seed + 1) if start is None else start
    first = o.deg + o.deg % 2
    m = np.full(ne, min(first, o.max_deg - o.max_deg % 2))
    locked, locked_values, locked_res, locked_at = None, np.zeros(0), np.zeros(0), np.zeros(0, int)
    matvecs, iteration, ritz, res = 0, 0, np.zeros(ne), np.full(ne, np.inf)
    while iteration < o.max_iter:
        iteration += 1
        steps = cheb_coeffs(mu_1, mu_ne, b_sup, int(m.max()))
        coarse = o.filter_dtype == "f4" and hasattr(space, "filter_low") and float(np.min(res)) > 1e-4 * max(abs(mu_1), abs(b_sup))
        v = space.filter_low(v, m, steps) if coarse else space.filter(v, m, steps)
        matvecs += int(m.sum())
        note(iteration, "Filter", matvecs=int(m.sum()), max_degree=int(m.max()), degrees=m.tolist(), active=len(m), locked=len(locked_values))
        q = space.orthonormalise(locked, v, o.qr)
        note(iteration, "QR")
        v, ritz, product = rayleigh_ritz(space, q, o.small)
        note(iteration, "RR")
        scale = max(abs(mu_1), abs(b_sup))
        res = residuals(space, v, ritz, product if o.residual_mode == "reuse" else None, o.residual_norm, scale)
        note(iteration, "Resid", residuals=res.tolist())
        # A product of a large operator resolves no less than this, whatever the tolerance.
        floor = 100 * np.finfo(float).eps * (1.0 if o.residual_norm == "relative" else max(abs(mu_1), abs(b_sup)))
        ready = lockable(res, max(o.tol, floor), o.order)
        done = int(ready.sum()) + len(locked_values) >= o.nev
        if o.locking or done:
            at = np.flatnonzero(ready)
            if len(at):
                part = space.columns(v, at)
                locked = space.keep(part if locked is None else space.beside(locked, part))
                locked_values = np.concatenate([locked_values, ritz[at]])
                locked_res = np.concatenate([locked_res, res[at]])
                locked_at = np.concatenate([locked_at, np.full(len(at), iteration)])
                rest = np.flatnonzero(~ready)
                v, ritz, res = space.columns(v, rest), ritz[rest], res[rest]
        if len(locked_values) >= o.nev or not len(ritz):
            break
        mu_1, mu_ne, b_sup = update_bounds(locked_values, ritz, b_sup)
        if not o.nex:
            mu_ne += 0.02 * (b_sup - mu_ne)  # without extra columns nothing shows where the unwanted part begins
        c, e = centre(mu_ne, b_sup)
        most, plain, aim = o.max_deg, min(first, o.max_deg), o.tol
        if space.light:
            # Where products are cheap, a pass goes on until it is worth its orthonormalisation and projection, and aims well below the threshold.
            worth = worthwhile(ritz[o.nev - len(locked_values) - 1], c, e)
            most, plain, aim = max(most, worth), max(plain, worth), o.tol / 10
        m = degrees(aim, res, ritz, c, e, most) if o.optimise_degree else np.full(len(ritz), plain)
        m = equalised(m, o.degree_policy)
        order = np.argsort(m, kind="stable")
        v, ritz, res, m = space.keep(space.columns(v, order)), ritz[order], res[order], m[order]
        note(iteration, "Lock", mu_1=mu_1, mu_ne=mu_ne, b_sup=b_sup, active=len(m), locked=len(locked_values))
    converged = len(locked_values) >= o.nev
    order = np.argsort(locked_values, kind="stable")[: o.nev]
    vectors = space.columns(locked, order) if locked is not None else None
    if len(order) and o.residual_mode == "reuse":
        # What was locked rests on products that were rotated along; one fresh product has the last word.
        locked_res = locked_res.copy()
        locked_res[order] = residuals(space, vectors, locked_values[order], None, o.residual_norm, max(abs(mu_1), abs(b_sup)))
        converged = converged and bool((locked_res[order] < 10 * max(o.tol, floor)).all())
        note(iteration, "Check", residuals=locked_res[order].tolist())
    sign = space.sign if hasattr(space, "sign") else 1.0
    out = Solution(sign * locked_values[order], locked_res[order], locked_at[order], vectors, trace, iteration, matvecs, space.sweeps, converged, sign * np.sort(ritz))
    if not converged and o.require_convergence:
        raise types.NotConverged(f"{len(order)} of {o.nev} pairs converged in {iteration} iterations", out)
    return out


class EigenResult:
    """A solution with its tables."""

    def __init__(self, spark: SparkSession, solution: Solution, n: int, bs: int, dtype: str, how: str):
        self.spark, self.solution, self.n, self.bs, self.dtype, self.how = spark, solution, n, bs, dtype, how
        self.iterations, self.matvecs, self.sweeps, self.converged = solution.iterations, solution.matvecs, solution.sweeps, solution.converged

    @property
    def values(self) -> DataFrame:
        s = self.solution
        rows = [(k, float(v), float(r), int(i), True, s.matvecs) for k, (v, r, i) in enumerate(zip(s.values, s.residuals, s.iteration))]
        return self.spark.createDataFrame(rows, types.SPECTRUM)

    def vectors(self) -> DataFrame:
        """(i, col, v[, im]) of the wanted vectors."""
        v = self.solution.vectors
        if isinstance(v, DataFrame):
            return layout.from_panel(v, self.bs, self.dtype)
        i, j = (x.ravel() for x in np.indices(v.shape))
        cols = {"i": i, "col": j.astype(np.int32), "v": v.real.ravel()} | ({"im": v.imag.ravel()} if self.dtype == "c16" else {})
        return self.spark.createDataFrame(pa.table(cols))

    @property
    def trace(self) -> DataFrame:
        names = [f.split()[0] for f in types.TRACE.split(", ")]
        return self.spark.createDataFrame([tuple(r.get(k) for k in names) for r in self.solution.trace], types.TRACE)

    def explain(self) -> str:
        return f"{self.how}: order {self.n}, blocks of {self.bs}, {self.iterations} iterations, {self.matvecs} matvecs, {self.sweeps} sweeps"


def dense(table: pa.Table, n: int) -> np.ndarray:
    """A matrix from coordinate columns i, j, v[, im]."""
    v = table.column("v").to_numpy()
    if "im" in table.column_names:
        v = v + 1j * table.column("im").to_numpy()
    out = np.zeros((n, n), v.dtype)
    np.add.at(out, (table.column("i").to_numpy(), table.column("j").to_numpy()), v)
    return out


def operator(table: pa.Table, n: int) -> np.ndarray | Banded:
    """The same, by its diagonals where they are few and the order is beyond SMALL."""
    if n > SMALL and "im" not in table.column_names:
        found = banded(*(table.column(c).to_numpy() for c in ("i", "j", "v")), n)
        if found is not None:
            return found
    return dense(table, n)


_TASK = "ok boolean, values binary, residuals binary, iteration binary, vectors binary, facts string"


def _in_task(coo: DataFrame, n: int, o: Options, start: np.ndarray | None, build=operator) -> Solution:
    """Solve in one task, over the operator that `build` makes of all rows and n."""
    sign = -1.0 if o.end == "high" else 1.0

    def run(table: pa.Table) -> pa.Table:
        space = LocalSpace(build(table, n), sign)
        try:
            s, ok = solve(space, o, start), True
        except types.NotConverged as e:
            s, ok = e.result, False
        vectors = s.vectors if s.vectors is not None else np.zeros((n, 0), space.dtype)
        facts = json.dumps({"trace": s.trace, "iterations": s.iterations, "matvecs": s.matvecs, "sweeps": s.sweeps, "ritz": s.ritz.tolist()})
        cols = [ok, s.values.tobytes(), s.residuals.tobytes(), s.iteration.astype(np.int64).tobytes(), np.ascontiguousarray(vectors).tobytes(), facts]
        return pa.table({k: [x] for k, x in zip(("ok", "values", "residuals", "iteration", "vectors", "facts"), cols)})

    rows = coo.unionByName(_anchor(coo)) if build is operator else coo
    row = rows.groupBy(F.lit(1).alias("one")).applyInArrow(run, _TASK).first()
    f = json.loads(row["facts"])
    values = np.frombuffer(row["values"])
    vectors = np.frombuffer(row["vectors"], layout.kind(coo)).reshape(n, -1)
    s = Solution(values, np.frombuffer(row["residuals"]), np.frombuffer(row["iteration"], np.int64), vectors, f["trace"], f["iterations"], f["matvecs"], f["sweeps"], row["ok"], np.array(f["ritz"]))
    if not row["ok"] and o.require_convergence:
        raise types.NotConverged(f"{len(values)} of {o.nev} pairs converged in {s.iterations} iterations", s)
    return s


def _anchor(coo: DataFrame) -> DataFrame:
    """A zero entry, so that an operator without entries still is one group."""
    zero = coo.sparkSession.range(1).select(F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(0.0).alias("v"))
    return zero.withColumn("im", F.lit(0.0)) if "im" in coo.columns else zero


def eigs(
    coo: DataFrame, n: int, nev: int, nex: int = 8, tol: float = 1e-10, strategy: str = "auto", bs: int | None = None, half: bool = False,
    sub_grid: tuple[int, int] = (1, 1), shift: str = "fused", cut_every: int = 1, alternate: bool = False, start: np.ndarray | None = None, **options,
) -> EigenResult:
    """nev eigenpairs at one end of the self-adjoint operator with coordinates (i, j, v[, im]).

    strategy: 'single_task' runs everything in one task, 'grid', 'broadcast',
    'paired' and 'coo' are the distributed products of `SparkSpace`, and
    `alternate` its alternating steps; 'auto' takes
    one task while n * n is small, a broadcast panel while it is small enough,
    and the grid beyond. Further options are those of `Options`. This is an
    eager boundary: jobs run before it returns.
    """
    o = Options(nev, nex, tol, **options)
    if o.end not in ("low", "high"):
        raise ValueError(f"unknown end of the spectrum: {o.end}")
    if nev < 1 or nex < 0 or nev + nex > n:
        raise types.SubspaceTooLarge(f"nev + nex = {nev + nex} for an operator of order {n}")
    spark, dtype = coo.sparkSession, layout.kind(coo)
    if strategy == "auto":
        small = n * (nev + nex) * np.dtype(dtype).itemsize <= broadcast_limit(spark)
        bands = getattr(coo, "_bands", n)
        strategy = "single_task" if n * min(n, bands) <= SINGLE_TASK and (n * n <= SINGLE_TASK or bands <= BANDS) else "broadcast" if small else "grid"
    if strategy == "single_task":
        return EigenResult(spark, _in_task(coo, n, o, start), n, n, dtype, strategy)
    bs = bs or min(layout.BLOCK_ROWS, max(1, -(-n // 4)))
    space = SparkSpace(layout.to_blocks(coo, n, bs), n, bs, dtype, strategy, half, -1.0 if o.end == "high" else 1.0, sub_grid, cut_every, shift, alternate=alternate).pin()
    try:
        return EigenResult(spark, solve(space, o, None if start is None else space.load(start)), n, bs, dtype, strategy)
    finally:
        space.unpin()


def eigs_reflected(spectrum: DataFrame, u: Column, n: int, nev: int, nex: int = 8, tol: float = 1e-10, index: str = "k", value: str = "lambda", **options) -> EigenResult:
    """`eigs` of `dense.reflector_entries(spectrum, u)` in one task that holds the n values and u, not the n * n entries."""
    o = Options(nev, nex, tol, **options)
    if nev < 1 or nex < 0 or nev + nex > n:
        raise types.SubspaceTooLarge(f"nev + nex = {nev + nex} for an operator of order {n}")

    def build(table: pa.Table, n: int) -> Reflected:
        table = table.sort_by("k")
        return Reflected(table.column("lam").to_numpy(), table.column("u").to_numpy())

    rows = spectrum.select(F.col(index).alias("k"), F.col(value).alias("lam"), u.alias("u"))
    return EigenResult(spectrum.sparkSession, _in_task(rows, n, o, None, build), n, n, "f8", "single_task")


def group_eigs(coo: DataFrame, group: str, nev: int, end: str = "high") -> DataFrame:
    """(group, k, eigenvalue) of many small operators (group, i, j, v), each solved whole in one task of its own."""
    kind = coo.select(group).schema[0].dataType.simpleString()

    def run(key: tuple, table: pa.Table) -> pa.Table:
        n = int(max(table.column("i").to_numpy().max(), table.column("j").to_numpy().max())) + 1
        values = np.linalg.eigvalsh(dense(table, n))
        values = values[::-1] if end == "high" else values
        values = values[:nev]
        return pa.table({group: pa.array([key[0].as_py()] * len(values)).cast(key[0].type), "k": pa.array(np.arange(len(values)), pa.int32()), "eigenvalue": values})

    return coo.groupBy(group).applyInArrow(run, f"{group} {kind}, k int, eigenvalue double")


