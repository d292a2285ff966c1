"""Sequences of correlated problems: each solve starts from the vectors of the one before."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
from pyspark.sql import DataFrame

from .driver import EigenResult, eigs


def eigs_sequence(problems: Iterable[DataFrame], n: int, nev: int, nex: int, tol: float = 1e-10, warm: bool = True, **options) -> list[EigenResult]:
    """One result for each problem in order.

    A warm start fills the first nev columns with the last vectors and needs
    only a short Lanczos run for the bounds; the rest stay random.
    """
    from ..linalg.small import gaussian

    out: list[EigenResult] = []
    start = None
    for coo in problems:
        more = dict(options)
        if start is not None:
            more |= {"lanczos_steps": max(5, options.get("lanczos_steps", 25) // 2)}
        result = eigs(coo, n, nev, nex, tol, start=start, **more)
        out.append(result)
        if warm:
            v = result.solution.vectors
            if isinstance(v, DataFrame):
                raise ValueError("warm starts need a solve in one task")
            start = np.concatenate([v, gaussian(np.arange(n), nex, 11, result.dtype)], 1)
    return out
