"""Warm-started solves of a stream's batches."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..linalg.small import gaussian
from ..solve.driver import eigs


def solve_batches(stream: DataFrame, build: Callable[[DataFrame], DataFrame], n: int, nev: int, nex: int, path: str, checkpoint: str, **options) -> StreamingQuery:
    """For each micro-batch, add its operator to the sum so far, solve from the last basis, and write SPECTRUM under the batch id.

    `build` makes coordinates from a batch. Everything a batch needs lies under
    `path`, by batch id, so a batch that runs again overwrites its own rows
    and reads the same predecessor.
    """
    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        coo = build(batch)
        before = None
        if batch_id:
            before = spark.read.parquet(f"{path}/basis/batch={batch_id - 1}").toArrow()
            coo = coo.unionByName(spark.read.parquet(f"{path}/operator/batch={batch_id - 1}")).groupBy("i", "j").agg(F.sum("v").alias("v"))
        coo.write.mode("overwrite").parquet(f"{path}/operator/batch={batch_id}")
        coo = spark.read.parquet(f"{path}/operator/batch={batch_id}")
        start = None
        if before is not None:
            start = np.zeros((n, nev))
            start[before.column("i").to_numpy(), before.column("col").to_numpy()] = before.column("v").to_numpy()
            start = np.concatenate([start, gaussian(np.arange(n), nex, 11)], 1)
        result = eigs(coo, n, nev, nex, start=start, **options)
        result.vectors().write.mode("overwrite").parquet(f"{path}/basis/batch={batch_id}")
        result.values.withColumn("matvecs", F.lit(result.matvecs).cast("long")).write.mode("overwrite").parquet(f"{path}/spectrum/batch={batch_id}")

    return stream.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
