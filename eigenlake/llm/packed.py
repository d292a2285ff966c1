"""Keyed exchange of many small values as a few large rows.

A corpus has far more windows than rows. Shuffling one row per window costs
several times the input in row headers alone, so keys travel packed: documents
are dealt to *blocks*, a block sends one row of 64-bit keys to each *bucket* of
the key space, the bucket's task answers for every block with one array in the
order of the keys sent, and the block reads the answers beside its documents.
Equal keys meet in one bucket; a block sends a key once however often it holds
it, so a key that a third of all rows hold arrives once per block.

The text is shuffled once: both uses of the blocks share the exchange.
"""

from __future__ import annotations

import math
import tempfile
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textnum


#: Bytes of text in a block and of what a bucket receives: one worker holds one at a time. Smaller ones mean more, shorter messages.
BLOCK_BYTES, BUCKET_BYTES = 64 << 20, 256 << 20
#: Bytes of text in a task, and in a task when there would be more than so many tasks.
TASK_BYTES, WIDE_BYTES, MANY_TASKS = 32 << 20, 1 << 30, 20_000


@dataclass(frozen=True)
class Deal:
    """How many tasks, blocks and buckets an exchange of so many bytes is dealt to."""

    tasks: int
    blocks: int
    buckets: int


def dealt(size: int, partitions: int) -> Deal:
    """At least what the session's partitions ask for; more where blocks, buckets or tasks would grow beyond their bytes."""
    tasks = max(partitions, min(math.ceil(size / TASK_BYTES), max(MANY_TASKS, math.ceil(size / WIDE_BYTES))))
    return Deal(tasks, max(2 * partitions, math.ceil(size / BLOCK_BYTES)), max(partitions, math.ceil(3 * size / BUCKET_BYTES)))


def deal(docs: DataFrame, text: str) -> Deal:
    """The deal for a table by the bytes of one column: an aggregate that reads that column alone."""
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length(text))).first()[0] or 0
    return dealt(size, max(1, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir.

    A session in one process may go without and gets a temporary one; on a
    cluster, where executors would not see it, that is an error.
    """
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="eigenlake-checkpoints-"))
    return context._jsc.sc().getCheckpointDir().get()


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared checkpoint folder and go on from the files.

    The shuffle files that made it are of no further use and go at once,
    rather than when the driver's garbage happens to be collected.
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


def blocks(docs: DataFrame, key: str, text: str, by: Deal) -> DataFrame:
    """(block, id, text): documents dealt evenly to blocks."""
    at = F.pmod(F.xxhash64(F.col(key), F.col(text)), F.lit(by.blocks)).cast("int")
    return docs.select(at.alias("block"), F.col(key).cast("long").alias("id"), F.col(text).alias("text")).repartition(by.tasks, "block")


def ordered(table: pa.Table) -> pa.Table:
    """A block's rows in an order that every run gives."""
    textnum.settle()
    return table.combine_chunks().sort_by([("id", "ascending"), ("text", "ascending")])


def send(block: int, keys: np.ndarray, buckets: int, **values: np.ndarray) -> dict[str, list]:
    """Rows (block, bucket, keys, values...) for distinct keys; `order` of `slots` gives their order."""
    order, bound = slots(keys, buckets)
    out: dict[str, list] = {"block": [], "bucket": [], "keys": []} | {k: [] for k in values}
    keys, values = keys[order], {k: v[order] for k, v in values.items()}
    for b in np.flatnonzero(np.diff(bound)):
        lo, hi = bound[b], bound[b + 1]
        out["block"].append(block)
        out["bucket"].append(int(b))
        out["keys"].append(keys[lo:hi].tobytes())
        for k, v in values.items():
            out[k].append(v[lo:hi].tobytes())
    return out


def slots(keys: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The order in which keys are sent, and where each bucket's begin."""
    own = (keys >> np.uint64(33)) % np.uint64(buckets)
    own = own.astype(np.int32)
    return np.argsort(own, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(own, minlength=buckets))])


def answers(table: pa.Table, n: int, keys: np.ndarray, buckets: int, kind: type, name: str = "answer") -> np.ndarray:
    """What the buckets said about each key, in the keys' own order."""
    order, bound = slots(keys, buckets)
    got = np.zeros(n, kind)
    for b, raw in zip(table.column("bucket").to_pylist(), table.column(name).to_pylist()):
        got[bound[b] : bound[b + 1]] = np.frombuffer(raw, kind)
    out = np.empty(n, kind)
    out[order] = got
    return out


def gathered(table: pa.Table, name: str, kind: type) -> np.ndarray:
    """A bucket's arrays one after the other."""
    return np.frombuffer(b"".join(table.column(name).to_pylist()), kind)


def bounds(table: pa.Table) -> np.ndarray:
    """Where each row's keys begin in what `gathered` gives."""
    textnum.settle()
    return np.cumsum([0, *(len(x) // 8 for x in table.column("keys").to_pylist())])


def reply(table: pa.Table, at: np.ndarray, **values: np.ndarray) -> pa.Table:
    """One row for each row received, holding the answers to its keys."""
    cols = {"block": table.column("block"), "bucket": table.column("bucket")}
    for k, v in values.items():
        cols[k] = pa.array([v[lo:hi].tobytes() for lo, hi in zip(at[:-1], at[1:])], pa.binary())
    return pa.table(cols)


def meet(sent: DataFrame, by: Deal, answer: Callable[[pa.Table], pa.Table], schema: str) -> DataFrame:
    """Run `answer` once for each bucket over all rows sent to it."""
    return sent.repartition(by.tasks, "bucket").groupBy("bucket").applyInArrow(answer, schema)
