"""Operators of graphs that tables hold."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import types
from ..session import broadcast_limit
from .gram import GramOperator


#: Rows up to which a group is held in one row.
WHOLE = 1000
#: Lists that the items of a larger group are dealt to.
LISTS = 64


def cooccurrence(df: DataFrame, group: str, item: str) -> DataFrame:
    """(i, j, v): in how many groups two different items both occur.

    Repeated (group, item) rows count once. A group of up to `WHOLE` rows is
    one set. The items of a larger one lie in lists by a hash of the item, and
    pairs come from two lists at a time, so that it is spread over tasks and no
    row holds all of it. Counts of i < j meet as partial sums and serve both ways.
    """
    known = df.where(F.col(group).isNotNull() & F.col(item).isNotNull()).select(F.col(group).alias("g"), F.col(item).cast("long").alias("item"))
    large = F.broadcast(known.groupBy("g").agg(F.count(F.lit(1)).alias("rows")).where(F.col("rows") > WHOLE).select("g"))
    sets = known.join(large, "g", "left_anti").groupBy("g").agg(F.collect_set("item").alias("items"))
    small = sets.select("items", F.explode("items").alias("i")).select("i", F.explode("items").alias("j")).where("i < j")
    lists = known.join(large, "g", "left_semi").distinct().groupBy("g", F.pmod(F.xxhash64("item"), F.lit(LISTS)).alias("part")).agg(F.collect_list("item").alias("items"))
    parts = lists.groupBy("g").agg(F.collect_list("part").alias("parts"))
    left = lists.join(parts, "g").select("g", F.col("items").alias("left"), F.explode("parts").alias("part"))
    both = left.join(lists.withColumnRenamed("items", "right"), ["g", "part"])
    pairs = both.select("right", F.explode("left").alias("i")).select("i", F.explode("right").alias("j")).where("i < j")
    counted = small.unionByName(pairs).groupBy("i", "j").agg(F.count(F.lit(1)).cast("double").alias("v"))
    ways = F.explode(F.array(F.struct("i", "j"), F.struct(F.col("j").alias("i"), F.col("i").alias("j"))))
    return counted.select(ways.alias("at"), "v").select("at.i", "at.j", "v")


def laplacian(edges: DataFrame, n: int | None = None, kind: str = "normalised") -> DataFrame:
    """(i, j, v) of D - S ('plain') or I - D^-1/2 S D^-1/2 ('normalised') from weights (i, j, v) without loops."""
    degree = edges.groupBy("i").agg(F.sum("v").alias("d"))
    if kind == "plain":
        off = edges.select("i", "j", (-F.col("v")).alias("v"))
        diagonal = degree.select("i", F.col("i").alias("j"), F.col("d").alias("v"))
    elif kind == "normalised":
        dj = degree.select(F.col("i").alias("j"), F.col("d").alias("dj"))
        off = edges.join(degree, "i").join(dj, "j").select("i", "j", (-F.col("v") / F.sqrt(F.col("d") * F.col("dj"))).alias("v"))
        diagonal = degree.select("i", F.col("i").alias("j"), F.lit(1.0).alias("v"))
    else:
        raise ValueError(f"unknown Laplacian: {kind}")
    return off.unionByName(diagonal)


def laplacian_apply(edges: DataFrame, x: DataFrame) -> DataFrame:
    """(i, v): (D - S) x for x (i, x), without forming the Laplacian."""
    with_x = edges.join(x.select(F.col("i").alias("j"), F.col("x").alias("xj")), "j").join(x, "i")
    return with_x.groupBy("i").agg(F.sum(F.col("v") * (F.col("x") - F.col("xj"))).alias("v"))


class LaplacianOperator(GramOperator):
    """D - S applied edge by edge: the weights (i, j, v) stay in their partitions and the Laplacian is never formed.

    A panel is an array on the driver whose size is checked; each task sends
    one partial sum of it, and those add up in a tree.
    """

    def __init__(self, edges: DataFrame, n: int, sign: float = 1.0):
        self.x = edges.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.col("v").cast("double").alias("v"))
        self.parts = self.x.rdd.getNumPartitions()
        self.n, self.dtype, self.sign, self.sweeps, self.divide = n, "f8", sign, 0, 1.0

    def _product(self, now: np.ndarray) -> DataFrame:
        if now.nbytes > 16 * broadcast_limit(self.x.sparkSession):
            raise types.DoesNotFit(f"a panel of {now.nbytes} bytes is not broadcast")
        held = self.x.sparkSession.sparkContext.broadcast(now)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            x = held.value
            total = np.zeros(x.shape)
            for batch in batches:
                i, j, v = (c.to_numpy() for c in batch.columns)
                np.add.at(total, i, v[:, None] * (x[i] - x[j]))
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["data"])

        return self.x.mapInArrow(run, "data binary")


def succession(df: DataFrame, group: str, item: str, order: list[str]) -> DataFrame:
    """(i, j, f): how often item j comes right after a different item i within a group."""
    after = F.lead(item).over(Window.partitionBy(group).orderBy(*order))
    return df.select(F.col(item).cast("long").alias("i"), after.cast("long").alias("j")).where("j is not null and i != j").groupBy("i", "j").agg(F.count(F.lit(1)).cast("double").alias("f"))
