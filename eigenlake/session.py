"""What the library needs from the session, read from it and never fixed here."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir; a session in one process may go without."""
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="eigenlake-checkpoints-"))
    return context._jsc.sc().getCheckpointDir().get()


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and go on from the files, so that a lost executor costs no more than this step.

    The shuffle files behind it go at once: an iteration of many steps would
    otherwise fill the executors' disks.
    """
    spark = df.sparkSession
    shared_folder(spark)
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        own = df.select("*")  # takes the setting as it is made
    finally:
        spark.conf.set(_CLEANUP, before)
    return own.checkpoint(eager=True)


def broadcast_limit(spark: SparkSession) -> int:
    """Bytes that may be broadcast: the session's own threshold, at least 8 MB."""
    text = str(spark.conf.get("spark.sql.autoBroadcastJoinThreshold")).lower().rstrip("b")
    unit = {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30}.get(text[-1:], 1)
    return max(8 << 20, int(float(text.rstrip("kmg"))) * unit)
