"""Direct solvers: reduce to condensed form, solve, transform back."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import types
from ..linalg.small import householder
from ..session import cut
from ..solve.driver import _anchor, dense
from .tridiag import tridiag_eigs

#: Largest order that one task takes on.
ONE_TASK = 8192


def to_band(a: np.ndarray, bw: int) -> tuple[np.ndarray, np.ndarray]:
    """(band, q) with q^H a q of bandwidth bw: block columns are reduced by QR factorisations, one after the other."""
    a = np.array(a, complex if np.iscomplexobj(a) else float)
    n = len(a)
    q = np.eye(n, dtype=a.dtype)
    for k in range(0, n - bw - 1, bw):
        rows, cols = slice(k + bw, n), slice(k, min(k + bw, n))
        part = np.linalg.qr(a[rows, cols], mode="complete")[0]
        a[rows, :] = part.conj().T @ a[rows, :]
        a[:, rows] = a[:, rows] @ part
        q[:, rows] = q[:, rows] @ part
    return a, q


def band_to_tridiagonal(a: np.ndarray, bw: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(d, e, q): rotations push each element outside the tridiagonal down and off the band."""
    a = np.array(a)
    n = len(a)
    q = np.eye(n, dtype=a.dtype)
    for col in range(n - 2):
        for far in range(min(col + bw, n - 1), col + 1, -1):
            i, at = far, col
            while i < n:
                x, y = a[i - 1, at], a[i, at]
                r = np.sqrt(abs(x) ** 2 + abs(y) ** 2)
                if abs(y) > 0:
                    turn = np.array([[np.conj(x), np.conj(y)], [-y, x]]) / r
                    a[[i - 1, i], :] = turn @ a[[i - 1, i], :]
                    a[:, [i - 1, i]] = a[:, [i - 1, i]] @ turn.conj().T
                    q[:, [i - 1, i]] = q[:, [i - 1, i]] @ turn.conj().T
                at, i = i - 1, i + bw
    e = np.array([a[k + 1, k] for k in range(n - 1)])
    if np.iscomplexobj(a):
        phase = np.ones(n, complex)
        for k in range(n - 1):
            phase[k + 1] = phase[k] * (e[k] / abs(e[k]) if e[k] != 0 else 1)
        q, e = q * phase[None, :], np.abs(e)
    return np.diag(a).real.copy(), np.asarray(e).real.copy(), q


def direct(a: np.ndarray, nev: int, method: str = "dense", vectors: bool = True, tridiagonal: str = "dc", bw: int = 8) -> tuple[np.ndarray, np.ndarray | None]:
    """Lowest nev eigenpairs of a matrix in memory, by one or two stages; without the back transformation if only values are asked for."""
    if method == "dense":
        if not vectors:
            return np.linalg.eigvalsh(a)[:nev], None
        w, v = np.linalg.eigh(a)
        return w[:nev], v[:, :nev]
    if method == "householder":
        d, e, q = householder(a)
    elif method == "band":
        band, q1 = to_band(a, bw)
        d, e, q2 = band_to_tridiagonal(band, bw)
        q = q1 @ q2
    else:
        raise ValueError(f"unknown direct method: {method}")
    if not vectors:
        return tridiag_eigs(d, e, "bisect" if nev < len(d) // 4 else "ql", nev)[0], None
    w, v = tridiag_eigs(d, e, tridiagonal, nev)
    return w, q @ v


def direct_eigs(coo: DataFrame, n: int, nev: int, method: str = "dense", end: str = "low", vectors: bool = False, **more) -> DataFrame:
    """(k, eigenvalue) from the wanted end, computed whole in one task: the baseline, so n is limited."""
    if n > ONE_TASK:
        raise types.DoesNotFit(f"order {n} is beyond one task; the direct baseline stops at {ONE_TASK}")
    sign = -1.0 if end == "high" else 1.0

    def run(table: pa.Table) -> pa.Table:
        w, _ = direct(sign * dense(table, n), nev, method, vectors, **more)
        return pa.table({"k": pa.array(np.arange(len(w)), pa.int32()), "eigenvalue": sign * w})

    return coo.unionByName(_anchor(coo)).groupBy(F.lit(1).alias("one")).applyInArrow(run, "k int, eigenvalue double")


def householder_distributed(coo: DataFrame, n: int) -> DataFrame:
    """(i, j, v): the tridiagonal form of a real operator, one reflector and one rewritten operator per column.

    n - 2 dependent passes, each of which writes the operator anew: what makes
    the direct way lose at scale. For small n.
    """
    a = cut(coo.select("i", "j", "v"))
    spark = coo.sparkSession
    for k in range(n - 2):
        x = a.where((F.col("j") == k) & (F.col("i") > k)).select("i", F.col("v").alias("x"))
        head = x.agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("size"), F.max(F.when(F.col("i") == k + 1, F.col("x"))).alias("x0"))
        u = spark.range(k + 1, n).select(F.col("id").alias("i")).join(x, "i", "left").crossJoin(F.broadcast(head))
        first = F.when(F.coalesce("x0", F.lit(0.0)) >= 0, F.col("size")).otherwise(-F.col("size"))
        u = u.select("i", (F.coalesce("x", F.lit(0.0)) + F.when(F.col("i") == k + 1, first).otherwise(0.0)).alias("u"))
        total = u.agg(F.sum(F.col("u") * F.col("u")).alias("uu"))
        u = u.crossJoin(F.broadcast(total)).where("uu > 0").select("i", (F.col("u") / F.sqrt("uu")).alias("u"))
        p = a.join(u.select(F.col("i").alias("j"), F.col("u").alias("uj")), "j").groupBy("i").agg(F.sum(F.col("v") * F.col("uj")).alias("p"))
        up = u.join(p, "i").agg(F.sum(F.col("u") * F.col("p")).alias("g"))
        both = p.join(u, "i", "full").crossJoin(F.broadcast(up)).select("i", F.coalesce("u", F.lit(0.0)).alias("u"), (F.coalesce("p", F.lit(0.0)) - F.coalesce("g", F.lit(0.0)) * F.coalesce("u", F.lit(0.0))).alias("w"))
        other = both.select(F.col("i").alias("j"), F.col("u").alias("uj"), F.col("w").alias("wj"))
        change = both.crossJoin(other).select("i", "j", (-2 * F.col("u") * F.col("wj") - 2 * F.col("w") * F.col("uj")).alias("v"))
        a = cut(a.unionByName(change).groupBy("i", "j").agg(F.sum("v").alias("v")).where(F.abs("v") > 1e-14))
    return a


def owner(layout_: str, bi, bj, rows: int, cols: int, count: int, nb: int = 1):
    """Column expression: which task of a rows x cols grid holds block (bi, bj) of `count` per side.

    'block' gives contiguous parts, 'cyclic' deals single blocks, 'block_cyclic' runs of nb.
    """
    if layout_ == "block":
        a, b = F.floor(bi * rows / count), F.floor(bj * cols / count)
    elif layout_ == "cyclic":
        a, b = bi % rows, bj % cols
    elif layout_ == "block_cyclic":
        a, b = F.floor(bi / nb) % rows, F.floor(bj / nb) % cols
    else:
        raise ValueError(f"unknown layout: {layout_}")
    return (a * cols + b).cast("int")


