"""Windows over spectra and within keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def rank_spectrum(spectrum: DataFrame, value: str, key: str) -> DataFrame:
    """Ranks of values with ties. The window has no partition: for spectra of k rows."""
    by = Window.orderBy(F.desc(value))
    return spectrum.select(
        key, F.row_number().over(Window.orderBy(F.desc(value), key)).alias("place"), F.rank().over(by).alias("rank"), F.dense_rank().over(by).alias("dense"),
        F.ntile(4).over(Window.orderBy(F.desc(value), key)).alias("quarter"), F.round(F.percent_rank().over(by), 6).alias("percent"), F.round(F.cume_dist().over(by), 6).alias("cume"),
    )


def gaps(spectrum: DataFrame, value: str, key: str) -> DataFrame:
    """Distance from each value to the next larger."""
    return spectrum.select(key, (F.lead(value).over(Window.orderBy(key)) - F.col(value)).alias("gap"))


def explained(spectrum: DataFrame, value: str, key: str) -> DataFrame:
    """Cumulative share of the values in their order."""
    total = F.sum(value).over(Window.partitionBy(F.lit(1)))
    run = F.sum(value).over(Window.orderBy(key).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return spectrum.select(key, (run / total).alias("share"))


def moving_average(df: DataFrame, on: list[str], order: list[str], value: str, rows: int) -> DataFrame:
    """Mean of a row and the `rows` before it, per key."""
    by = Window.partitionBy(*on).orderBy(*order).rowsBetween(-rows, 0)
    return df.withColumn("mean", F.avg(value).over(by))


def top_per_key(df: DataFrame, on: list[str], order: list, k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(*on).orderBy(*order))).where(F.col("place") <= k)
