"""Readers of operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import types


def read_coo(spark: SparkSession, path: str, fmt: str = "parquet", symmetric: bool = False, complex_: bool = False) -> DataFrame:
    """Coordinates from parquet, orc, json or csv (with a header); `symmetric` files hold one triangle and are mirrored."""
    schema = types.COO_COMPLEX if complex_ else types.COO
    reader = spark.read.schema(schema)
    coo = (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)
    return mirrored(coo) if symmetric else coo


def mirrored(coo: DataFrame) -> DataFrame:
    """One triangle made whole; the mirror of a complex entry is its conjugate."""
    off = coo.where("i != j").select(F.col("j").alias("i"), F.col("i").alias("j"), "v", *([(-F.col("im")).alias("im")] if "im" in coo.columns else []))
    return coo.unionByName(off)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(types.BLOCK).parquet(path)


def read_coord_text(spark: SparkSession, path: str) -> DataFrame:
    """Coordinates from text: '%' starts a comment (sizes belong there), every other line is 'i j value' from 1."""
    lines = spark.read.text(path).where(~F.col("value").startswith("%") & (F.trim("value") != ""))
    parts = lines.select(F.split(F.trim("value"), r"\s+").alias("p"))
    return parts.select((F.col("p")[0].cast("long") - 1).alias("i"), (F.col("p")[1].cast("long") - 1).alias("j"), F.col("p")[2].cast("double").alias("v"))


def view(df: DataFrame, name: str) -> DataFrame:
    df.createOrReplaceTempView(name)
    return df
