"""Analytic tridiagonal operators over a contiguous 0-based key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _banded(index: DataFrame, key: str, diagonal: Column, off: float) -> DataFrame:
    n = index.agg(F.count(F.lit(1)).alias("n"))
    rows = index.select(F.col(key).cast("long").alias("i")).crossJoin(F.broadcast(n))
    at = F.explode(F.array(F.struct(F.col("i").alias("j"), diagonal.alias("v")), F.struct((F.col("i") - 1).alias("j"), F.lit(off).alias("v")), F.struct((F.col("i") + 1).alias("j"), F.lit(off).alias("v"))))
    out = rows.select("i", "n", at.alias("x")).where("x.j >= 0 and x.j < n").select("i", "x.j", "x.v")
    out._bands = 3  # known without a look at the entries
    return out


def tridiag_121(index: DataFrame, key: str, off: float = 1.0) -> DataFrame:
    """Diagonal 2, neighbours `off` (1 or -1 give the same spectrum)."""
    return _banded(index, key, F.lit(2.0), off)


def tridiag_wilkinson(index: DataFrame, key: str) -> DataFrame:
    """Diagonal |i - (n - 1) / 2|, neighbours 1."""
    return _banded(index, key, F.abs(F.col("i") - (F.col("n") - 1) / 2).cast("double"), 1.0)
