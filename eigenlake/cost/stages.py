"""What the stages of an action moved and how long they ran, from Spark's own status store."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import SparkSession


def measured(spark: SparkSession, action: Callable[[], object]) -> tuple[object, dict]:
    """The action's result, and totals over the stages that it ran.

    Bytes and rows written to and read from shuffles, seconds that tasks ran,
    and the seconds of those that they waited for or wrote shuffled data;
    `communication_share` is the latter over the former.
    """
    context, group = spark.sparkContext, uuid.uuid4().hex
    before = context.getLocalProperty("spark.jobGroup.id")
    context.setJobGroup(group, "measured")
    try:
        result = action()
    finally:
        context.setLocalProperty("spark.jobGroup.id", before)
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    out = {"jobs": len(jobs), "stages": 0, "shuffle_bytes_written": 0, "shuffle_bytes_read": 0, "shuffle_rows_written": 0, "task_seconds": 0.0, "exchange_seconds": 0.0}
    for stage in sorted({s for j in jobs if j for s in j.stageIds}):
        try:
            data = store.lastStageAttempt(stage)
        except Py4JJavaError:  # a stage that was skipped has no attempt
            continue
        if data.status().toString() != "COMPLETE":
            continue
        out["stages"] += 1
        out["shuffle_bytes_written"] += data.shuffleWriteBytes()
        out["shuffle_bytes_read"] += data.shuffleReadBytes()
        out["shuffle_rows_written"] += data.shuffleWriteRecords()
        out["task_seconds"] += data.executorRunTime() / 1e3
        out["exchange_seconds"] += data.shuffleFetchWaitTime() / 1e3 + data.shuffleWriteTime() / 1e9
    out["communication_share"] = out["exchange_seconds"] / out["task_seconds"] if out["task_seconds"] else 0.0
    return result, out
