"""Gram, covariance and kernel operators of vectors, and Gram operators that are never formed."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..linalg.space import Space


def long_vectors(df: DataFrame, key: str, features: str) -> DataFrame:
    """(key, j, x) of an array column, from 0."""
    return df.select(key, F.posexplode(F.col(features).cast("array<double>")).alias("j", "x"))


def gram(df: DataFrame, features: str, group: str | None = None) -> DataFrame:
    """([group,] i, j, v): sums of x_i x_j over rows.

    Rows expand to their d * d products where they are and meet as partial
    sums, so the shuffle holds d * d values per task and group, not rows.
    """
    by = [group] if group else []
    x = df.where(F.col(features).isNotNull()).select(*by, F.col(features).cast("array<double>").alias("x"))
    left = x.select(*by, "x", F.posexplode("x").alias("i", "a"))
    both = left.select(*by, "i", "a", F.posexplode("x").alias("j", "b"))
    return both.groupBy(*by, F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j")).agg(F.sum(F.col("a") * F.col("b")).alias("v"))


def covariance(df: DataFrame, features: str) -> DataFrame:
    """(i, j, v): the sample covariance (n - 1) of the features, centred before the products are summed."""
    x = df.where(F.col(features).isNotNull()).select(F.col(features).cast("array<double>").alias("x"))
    means = x.select(F.posexplode("x").alias("i", "a")).groupBy("i").agg(F.avg("a").alias("m")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("m"))
    count = x.agg(F.count(F.lit(1)).alias("n"))
    centred = x.crossJoin(F.broadcast(means)).select(F.zip_with("x", "m", lambda a, b: a - b).alias("x"))
    return gram(centred, "x").crossJoin(F.broadcast(count)).select("i", "j", (F.col("v") / (F.col("n") - 1)).alias("v"))


def kernel(df: DataFrame, key: str, features: str, kind: str = "linear", gamma: float = 1.0) -> DataFrame:
    """(i, j, v) over pairs of rows: inner products, or exp(-gamma |x - y|^2). n * n entries: for a stated set of rows."""
    x = df.select(F.col(key).cast("long").alias("i"), F.col(features).cast("array<double>").alias("x"))
    y = x.select(F.col("i").alias("j"), F.col("x").alias("y"))
    if kind == "linear":
        v = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0), lambda s, a: s + a)
    elif kind == "rbf":
        v = F.exp(-F.lit(gamma) * F.aggregate(F.zip_with("x", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, a: s + a))
    else:
        raise ValueError(f"unknown kernel: {kind}")
    return x.crossJoin(y).select("i", "j", v.alias("v"))


class GramOperator(Space):
    """X'X applied as X'(X V): one pass over the rows of X per product, the d x d matrix is never formed.

    Rows stay in their partitions; each sends one d x k partial sum, and
    those add up in a tree.
    """

    def __init__(self, df: DataFrame, features: str, center: bool = False, sign: float = 1.0, divide: float = 1.0):
        self.x = df.where(F.col(features).isNotNull()).select(F.col(features).cast("array<double>").alias("x"))
        self.parts = self.x.rdd.getNumPartitions()
        first = self.x.first()
        self.n, self.dtype, self.sign, self.sweeps, self.divide = (len(first["x"]) if first else 0), "f8", sign, 0, divide
        self.mean = np.zeros(self.n)
        if center:
            total = self.x.select(F.posexplode("x").alias("i", "a")).groupBy("i").agg(F.avg("a").alias("m")).collect()
            for r in total:
                self.mean[r["i"]] = r["m"]

    def random(self, k: int, seed: int) -> np.ndarray:
        from ..linalg.small import gaussian

        return gaussian(np.arange(self.n), k, seed)

    def load(self, a):
        return np.asarray(a)

    def _product(self, now: np.ndarray) -> DataFrame:
        """(data): what each partition adds to the product, as bytes."""
        held = self.x.sparkSession.sparkContext.broadcast((now, self.mean))
        d, k = now.shape

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            v, mean = held.value
            total = np.zeros((d, k))
            for batch in batches:
                x = batch.column(0).flatten().to_numpy().reshape(-1, d) - mean
                total += x.T @ (x @ v)
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["data"])

        return self.x.mapInArrow(run, "data binary")

    def step(self, now, before, alpha, beta, gamma):
        self.sweeps += 1
        d, k = now.shape

        def fold(table: pa.Table) -> pa.Table:
            rows = sorted(table.column("data").to_pylist())
            total = sum(np.frombuffer(r).reshape(d, k) for r in rows)
            return pa.table({"data": [total.tobytes()]})

        parts = self._product(now)
        if self.parts > 16:
            parts = parts.groupBy(F.pmod(F.spark_partition_id(), F.lit(16)).alias("g")).applyInArrow(fold, "data binary")
        got = sum(np.frombuffer(r["data"]).reshape(d, k) for r in sorted(parts.collect(), key=lambda r: r["data"])) / self.divide
        out = (alpha * self.sign) * got - (alpha * gamma) * now
        return out if before is None or beta == 0 else out + beta * before

    columns = staticmethod(lambda panel, at: panel[:, at])
    beside = staticmethod(lambda left, right: np.concatenate([left, right], 1))
    gram = staticmethod(lambda left, right: left.T @ right)
    rotate = staticmethod(lambda panel, m: panel @ m)
    minus = staticmethod(lambda panel, basis, m: panel - basis @ m)
    keep = staticmethod(lambda panel: panel)
    gather = staticmethod(lambda panel: panel)
    triangle = staticmethod(lambda panel: np.linalg.qr(panel, mode="r"))

    def residual_norms(self, product, panel, theta):
        return np.linalg.norm(product - panel * theta[None, :], axis=0)

    def orthonormalise(self, locked, panel, method="local"):
        whole = panel if locked is None else np.concatenate([locked, panel], 1)
        return np.linalg.qr(whole)[0][:, whole.shape[1] - panel.shape[1] :]


def gram_apply(df: DataFrame, features: str, x: dict[int, float] | None = None) -> DataFrame:
    """(i, v): X'(X x) in SQL, for x_j = 1 / (j + 1) unless given; X'X is not formed."""
    rows = df.where(F.col(features).isNotNull()).select(F.col(features).cast("array<double>").alias("a"))
    weight = (lambda j: F.lit(1.0) / (j + 1)) if x is None else (lambda j: F.coalesce(F.create_map(*(F.lit(y) for p in x.items() for y in p))[j], F.lit(0.0)))
    dot = F.aggregate(F.transform("a", lambda v, j: v * weight(j)), F.lit(0.0), lambda s, v: s + v)
    return rows.select("a", dot.alias("d")).select("d", F.posexplode("a").alias("i", "v")).groupBy(F.col("i").cast("long").alias("i")).agg(F.sum(F.col("v") * F.col("d")).alias("v"))
