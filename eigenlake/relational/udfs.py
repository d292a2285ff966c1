"""User functions for what built-in expressions lack; Arrow batches, never single rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType


@arrow_udf(DoubleType())
def vector_norm(v: pa.Array) -> pa.Array:
    """Euclidean norm of each list."""
    flat = np.asarray(v.flatten().cast(pa.float64()))
    ends = np.cumsum(np.asarray(v.value_lengths().fill_null(0)))
    total = np.concatenate([[0.0], np.cumsum(flat * flat)])
    starts = np.concatenate([[0], ends[:-1]]).astype(int)
    return pa.array(np.sqrt(np.array([float(flat[a:b] @ flat[a:b]) for a, b in zip(starts, ends)])) if len(ends) else total[:0])


@udtf(returnType=StructType([StructField("k", IntegerType()), StructField("eigenvalue", DoubleType())]))
class EigTable:
    """Table function: the eigenvalues, largest first, of a matrix given as an array of rows."""

    def eval(self, matrix: list[list[float]]):
        values = np.linalg.eigvalsh(np.array(matrix, float))[::-1]
        for k, v in enumerate(values):
            yield k, float(v)


def partial_gram(df: DataFrame, features: str, d: int) -> DataFrame:
    """(i, j, v): X'X with one d x d partial per task, added up by coordinate."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d, d))
        for batch in batches:
            x = np.asarray(batch.column(0).flatten()).reshape(-1, d)
            total += x.T @ x
        i, j = np.indices((d, d))
        yield pa.RecordBatch.from_arrays([pa.array(i.ravel()), pa.array(j.ravel()), pa.array(total.ravel())], names=["i", "j", "v"])

    x = df.where(F.col(features).isNotNull()).select(F.col(features).cast("array<double>").alias("x"))
    return x.mapInArrow(run, "i long, j long, v double").groupBy("i", "j").agg(F.sum("v").alias("v"))
