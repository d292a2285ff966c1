"""Joins that the engine needs beside plain equality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, on: list[str], time: str, value: str) -> DataFrame:
    """left with the latest `value` of right at or before its time, per key.

    Both sides are stacked and sorted once within their keys; the last value
    seen is carried forward. Nothing is paired, so cost is that of a sort.
    """
    stacked = left.select(*left.columns, F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__side")).unionByName(
        right.select(*on, time, F.col(value).alias("__v"), F.lit(0).alias("__side")), allowMissingColumns=True
    )
    by = Window.partitionBy(*on).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return stacked.withColumn("__v", F.last("__v", ignorenulls=True).over(by)).where("__side = 1").drop("__side").withColumnRenamed("__v", value)


def previous(df: DataFrame, on: list[str], order: list[str], value: str) -> DataFrame:
    """df with the value of the row before, per key, strictly earlier in `order`."""
    return df.withColumn(f"previous_{value}", F.lag(value).over(Window.partitionBy(*on).orderBy(*order)))


def range_bins(left: DataFrame, value: str, edges: DataFrame, low: str = "low", high: str = "high") -> DataFrame:
    """left joined to the bins (low <= value < high); bins are few, so they are broadcast behind Spark's own size check."""
    return left.join(edges, (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def interval(left: DataFrame, right: DataFrame, on: list[str], left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of the same key with 0 <= right time - left time <= seconds.

    Times are cut into buckets of that width; a row meets only its own and
    the next bucket, so the join is an equality with a residual condition.
    """
    slot = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    a = left.withColumn("__slot", F.explode(F.array(slot(left_time), slot(left_time) + 1)))
    b = right.withColumn("__slot", slot(right_time))
    gap = F.unix_micros(F.col(right_time).cast("timestamp")) - F.unix_micros(F.col(left_time).cast("timestamp"))
    return a.join(b, [*on, "__slot"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("__slot")


def semi(df: DataFrame, index: DataFrame, on: list[str]) -> DataFrame:
    return df.join(index, on, "left_semi")


def anti(df: DataFrame, index: DataFrame, on: list[str]) -> DataFrame:
    return df.join(index, on, "left_anti")


def salted(left: DataFrame, right: DataFrame, on: list[str], salts: int) -> DataFrame:
    """An inner join whose left side's hot keys are spread over `salts` partitions, with the right side repeated for each."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*on, "__salt"]).drop("__salt")


def symmetrised(edges: DataFrame, value: Column | None = None) -> DataFrame:
    """(i, j, v) with the larger of v_ij and v_ji on both sides, by a full join of the edges with their mirror."""
    mirror = edges.select(F.col("j").alias("i"), F.col("i").alias("j"), F.col("v").alias("w"))
    both = edges.join(mirror, ["i", "j"], "full")
    return both.select("i", "j", (F.greatest("v", "w") if value is None else value).alias("v"))
