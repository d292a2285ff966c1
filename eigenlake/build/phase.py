"""Complex self-adjoint operators of flows: size from both directions, phase from their imbalance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def phase_matrix(flows: DataFrame, theta: float = 0.25) -> DataFrame:
    """(i, j, v, im) from flows (i, j, f): with s = f_ij + f_ji, magnitude s / 2 and phase 2 pi theta (f_ij - f_ji) / s."""
    two = flows.select("i", "j", "f", F.lit(0.0).alias("b")).unionByName(flows.select(F.col("j").alias("i"), F.col("i").alias("j"), F.lit(0.0).alias("f"), F.col("f").alias("b")))
    sums = two.groupBy("i", "j").agg(F.sum("f").alias("f"), F.sum("b").alias("b")).where(F.col("f") + F.col("b") != 0)
    s, turn = F.col("f") + F.col("b"), F.lit(2 * 3.141592653589793 * theta) * (F.col("f") - F.col("b")) / (F.col("f") + F.col("b"))
    return sums.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), (s / 2 * F.cos(turn)).alias("v"), (s / 2 * F.sin(turn)).alias("im"))


def real_embedding(coo: DataFrame, n: int) -> DataFrame:
    """(i, j, v) of [[Re, -Im], [Im, Re]], of order 2 n: every eigenvalue twice."""
    parts = F.array(
        F.struct(F.col("i").alias("i"), F.col("j").alias("j"), F.col("v").alias("v")), F.struct((F.col("i") + n).alias("i"), (F.col("j") + n).alias("j"), F.col("v").alias("v")),
        F.struct(F.col("i").alias("i"), (F.col("j") + n).alias("j"), (-F.col("im")).alias("v")), F.struct((F.col("i") + n).alias("i"), F.col("j").alias("j"), F.col("im").alias("v")),
    )
    return coo.select(F.explode(parts).alias("x")).select("x.*").where("v != 0")
