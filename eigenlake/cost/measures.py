"""Cost and accuracy measures over traces, runs and results."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..linalg.space import Space

PHASES = ["Lanczos", "Filter", "QR", "RR", "Resid"]


def matvecs(trace: DataFrame) -> DataFrame:
    """(run_id, matvecs): products inside the filter only, the sum of all columns' degrees."""
    each = F.aggregate(F.coalesce("degrees", F.array().cast("array<int>")), F.lit(0).cast("long"), lambda a, x: a + x)
    return trace.where("phase = 'Filter'").groupBy("run_id").agg(F.sum(each).alias("matvecs"))


def phase_seconds(trace: DataFrame) -> DataFrame:
    """(run_id, one column a phase, All)."""
    out = trace.groupBy("run_id").pivot("phase", PHASES).agg(F.sum("seconds"))
    return out.withColumn("All", sum((F.coalesce(F.col(p), F.lit(0.0)) for p in PHASES), F.lit(0.0)))


def phase_stats(trace: DataFrame) -> DataFrame:
    """(phase, mean, sd, runs) of the seconds that a run spends in each phase."""
    per_run = trace.groupBy("run_id", "phase").agg(F.sum("seconds").alias("s"))
    return per_run.groupBy("phase").agg(F.avg("s").alias("mean"), F.stddev("s").alias("sd"), F.count(F.lit(1)).alias("runs"))


def tflops(n: int, products: int, seconds: float, nodes: int = 1, complex_: bool = False) -> float:
    """Rate of the filter: 2 n^2 operations a product (four times that if complex), per node."""
    return 2.0 * n * n * products * (4 if complex_ else 1) / seconds / nodes / 1e12


def speedup(old: DataFrame, new: DataFrame, on: list[str], time: str = "seconds") -> DataFrame:
    """Join two sets of runs on their configuration: old time over new time."""
    return old.select(*on, F.col(time).alias("old")).join(new.select(*on, F.col(time).alias("new")), on).withColumn("speedup", F.col("old") / F.col("new"))


def strong_scaling(runs: DataFrame, group: str, nodes: str = "nodes", time: str = "seconds") -> DataFrame:
    """Speedup against the run of the group on the fewest nodes."""
    first = F.first(time).over(Window.partitionBy(group).orderBy(nodes).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return runs.withColumn("speedup", first / F.col(time))


def weak_efficiency(runs: DataFrame, group: str, nodes: str = "nodes", time: str = "seconds") -> DataFrame:
    """Efficiency when the problem grows with the nodes: the same quotient, 1 being ideal."""
    return strong_scaling(runs, group, nodes, time).withColumnRenamed("speedup", "efficiency")


def orthogonality(space: Space, panel) -> float:
    """Largest deviation of the Gram matrix from the identity."""
    g = space.gram(panel, panel)
    return float(np.abs(g - np.eye(len(g))).max(initial=0))


def value_error(values: DataFrame, spectrum: DataFrame) -> DataFrame:
    """(k, error): distance of each computed value from the known one of the same rank (k from 0 on both sides)."""
    return values.select("k", "eigenvalue").join(spectrum.select("k", F.col("lambda").alias("known")), "k").select("k", F.abs(F.col("eigenvalue") - F.col("known")).alias("error"))


def subspace_angle(u: np.ndarray, v: np.ndarray) -> float:
    """Sine of the largest angle between two orthonormal bases."""
    s = np.linalg.svd(u.conj().T @ v, compute_uv=False)
    return float(np.sqrt(max(0.0, 1 - float(s.min(initial=1)) ** 2)))


def compare_runs(left: DataFrame, right: DataFrame) -> DataFrame:
    """(iteration, same): whether two traces did the same products at each iteration."""
    a, b = (t.where("phase = 'Filter'").select("iteration", F.col("matvecs").alias(x)) for t, x in ((left, "a"), (right, "b")))
    return a.join(b, "iteration", "full").select("iteration", F.col("a").eqNullSafe(F.col("b")).alias("same"))
