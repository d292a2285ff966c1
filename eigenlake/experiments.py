"""The experiments re-expressed on one machine: families, bindings, strong and weak scaling, comparison with direct solvers, sizing.

    python -m eigenlake.experiments [families] [bindings] [strong] [weak] [complex] [sequence] [sizing]

Each prints its rows as JSON lines. Tasks of the local session stand for
nodes, cuts of a task's part of the operator for its devices. No number here
is comparable with one measured on other hardware; what carries over is which
method wins and how measures move.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession

from .baseline import direct, krylov
from .build import dense, spectra
from .cost import memory
from .cost.stages import measured
from .linalg.small import gaussian
from .linalg.space import LocalSpace, SparkSpace
from .solve.driver import Options, Solution, solve


def session(tasks: int) -> SparkSession:
    active = SparkSession.getActiveSession()
    if active is not None:
        active.stop()
    s = SparkSession.builder.master(f"local[{tasks}]").config("spark.sql.shuffle.partitions", str(tasks)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "6g").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


def phases(s: Solution) -> dict[str, float]:
    out: dict[str, float] = {}
    for row in s.trace:
        out[row["phase"]] = out.get(row["phase"], 0.0) + row["seconds"]
    return {k: round(v, 4) for k, v in out.items()}


def matrix(kind: str, n: int) -> np.ndarray:
    tri = np.eye(n, k=1) + np.eye(n, k=-1)
    if kind == "onetwoone":
        return 2 * np.eye(n) + tri
    if kind == "wilkinson":
        return np.diag(np.abs(np.arange(n) - (n - 1) / 2)) + tri
    q = np.linalg.qr(gaussian(np.arange(n), n, 5))[0]
    return q.T @ np.diag(spectra.values(kind, n)) @ q


def families(n: int = 1000, repeat: int = 3, tol: float = 1e-9) -> Iterator[dict]:
    """Four matrix types, 7.5 % wanted and 2.5 % extra columns, mean and deviation over repetitions; kernels compared iteration for iteration."""
    nev, nex = n * 75 // 1000, n * 25 // 1000
    for kind in ("onetwoone", "geometric", "uniform", "wilkinson"):
        a, seconds, last = matrix(kind, n), [], None
        for _ in range(repeat):
            began = time.perf_counter()
            last = solve(LocalSpace(a), Options(nev, nex, tol, max_iter=400, require_convergence=False))
            seconds.append(time.perf_counter() - began)
        other = solve(LocalSpace(a), Options(nev, nex, tol, max_iter=400, require_convergence=False, qr="local"))
        exact = np.linalg.eigvalsh(a)[:nev]
        yield {
            "experiment": "families", "kind": kind, "n": n, "iterations": last.iterations, "matvecs": last.matvecs, "matvecs_per_column": round(last.matvecs / (nev + nex), 1), "seconds": round(float(np.mean(seconds)), 4),
            "deviation": round(float(np.std(seconds)), 4), "phases": phases(last), "other_qr": [other.iterations, other.matvecs], "value_error": float(np.abs(last.values - exact[: len(last.values)]).max()), "max_residual": float(last.residuals.max()),
        }


def _filter_once(spark: SparkSession, n: int, bs: int, sub_grid: tuple[int, int], strategy: str, k: int = 20, degree: int = 4) -> dict:
    """One filter pass of a uniform operator: seconds, rate, and from stage metrics what was shuffled and the share of time that took."""
    blocks = dense.reflector_blocks(spark, spectra.values("uniform", n), bs=bs)
    space = SparkSpace(blocks, n, bs, strategy=strategy, sub_grid=sub_grid).pin()
    v = space.keep(space.random(k, 7))
    space.blocks.count()
    from .solve.degrees import cheb_coeffs

    began = time.perf_counter()
    _, moved = measured(spark, lambda: space.filter(v, np.full(k, degree), cheb_coeffs(0.0, 0.1, 1.2, degree)).count())
    took = time.perf_counter() - began
    space.unpin()
    return {"strategy": strategy, "filter_seconds": round(took, 3), "gflops": round(2e-9 * n * n * k * degree / took, 2), "shuffle_mb": round(moved["shuffle_bytes_written"] / 1e6, 2), "communication_share": round(moved["communication_share"], 3)}


def bindings(n: int = 1500) -> Iterator[dict]:
    """Tasks times cuts per task: 1 x 4, 2 x 2, 4 x 1."""
    for tasks, cuts in ((1, (2, 2)), (2, (1, 2)), (4, (1, 1))):
        spark = session(tasks)
        for strategy in ("grid", "broadcast"):
            yield {"experiment": "bindings", "tasks": tasks, "cuts": cuts[0] * cuts[1], "n": n} | _filter_once(spark, n, -(-n // 4), cuts, strategy)


def strong(n: int = 2000) -> Iterator[dict]:
    """A fixed problem on more tasks."""
    for strategy in ("grid", "paired"):
        first = None
        for tasks in (1, 2, 4, 8):
            row = _filter_once(session(tasks), n, -(-n // 8), (1, 1), strategy)
            first = first or row["filter_seconds"]
            yield {"experiment": "strong", "tasks": tasks, "n": n, "speedup": round(first / row["filter_seconds"], 2)} | row


def weak(per_side: int = 800) -> Iterator[dict]:
    """n grows with the square root of the tasks, so work per task stays the same."""
    for strategy in ("grid", "paired"):
        first = None
        for side in (1, 2):
            n = per_side * side
            row = _filter_once(session(side * side), n, -(-n // 4), (1, 1), strategy)
            first = first or row["filter_seconds"]
            yield {"experiment": "weak", "tasks": side * side, "n": n, "efficiency": round(first / row["filter_seconds"], 3)} | row


def complex_(n: int = 700) -> Iterator[dict]:
    """A complex operator with 1 % wanted columns: the filtered solver against direct and Krylov solvers."""
    a = gaussian(np.arange(n), n, 6, "c16")
    a = a + a.conj().T
    nev = max(4, n // 100)
    runs = {
        "filtered": lambda: solve(LocalSpace(a), Options(nev, nev, 1e-8)).values,
        "direct": lambda: direct.direct(a, nev)[0],
        "direct_values": lambda: direct.direct(a, nev, vectors=False)[0],
        "one_stage": lambda: direct.direct(a, nev, "householder")[0],
        "krylov": lambda: krylov.lanczos_eigs(LocalSpace(a), nev).values,
    }
    exact = np.linalg.eigvalsh(a)[:nev]
    for name, f in runs.items():
        began = time.perf_counter()
        values = f()
        yield {"experiment": "complex", "method": name, "n": n, "nev": nev, "seconds": round(time.perf_counter() - began, 4), "value_error": float(np.abs(values - exact).max())}


def sequence_(n: int = 400, problems: int = 5) -> Iterator[dict]:
    """Products of a sequence of slowly changing problems, with warm and with cold starts."""
    base, change = (x + x.T for x in (gaussian(np.arange(n), n, s) for s in (1, 2)))
    for warm in (True, False):
        start, products = None, []
        for t in range(problems):
            s = solve(LocalSpace(base + 1e-4 * t * change), Options(10, 10, 1e-9), start)
            products.append(s.matvecs)
            start = np.concatenate([s.vectors, gaussian(np.arange(n), 10, 11)], 1) if warm else None
        yield {"experiment": "sequence", "warm": warm, "matvecs": products}


def sizing() -> Iterator[dict]:
    """Smallest square grid for each size of the weak-scaling series, and the largest operator of each grid."""
    for p in range(1, 13):
        n = 30_000 * p
        side = next(q for q in range(1, 99) if memory.device_elements(n, 3000, q, q, 2, 2) * 8 <= 40e9)
        yield {"experiment": "sizing", "n": n, "grid": side, "device_gb": round(memory.device_elements(n, 3000, side, side, 2, 2) * 8e-9, 2), "host_gb": round(memory.host_elements(n, 3000, side, side) * 8e-9, 2), "largest_n": memory.largest_n(3000, p, p, 40e9)}


ALL = {"families": families, "bindings": bindings, "strong": strong, "weak": weak, "complex": complex_, "sequence": sequence_, "sizing": sizing}


def main(names: list[str]) -> None:
    for name in names or list(ALL):
        for row in ALL[name]():
            print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
