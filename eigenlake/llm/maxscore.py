"""Exact top-k inner products by MaxScore over shards of dense vectors."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import packed

#: Vectors in a shard, queries in a block, and terms added between two prunings.
SHARD, BLOCK, STEP = 1 << 16, 1 << 14, 8
#: A table too small for a shard in every partition is cut into smaller ones, of so many vectors at least.
LEAST = 1024


def _matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids and component rows; shorter vectors end in zeros."""
    table = table.combine_chunks().sort_by([("id", "ascending")])
    column = table.column("parts").combine_chunks()
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.list_(pa.int64()))
    size = np.asarray(column.value_lengths().fill_null(0), np.int64) if len(column) else np.zeros(0, np.int64)
    out = np.zeros((len(size), int(size.max(initial=0))), np.int64)
    row = np.repeat(np.arange(len(size)), size)
    out[row, np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)] = column.flatten().to_numpy()
    return table.column("id").to_numpy(), out


def _kind(a: np.ndarray, b: np.ndarray) -> type:
    """The cheapest number type in which every inner product is exact."""
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[1])
    return np.float32 if most < 2**24 else np.float64 if most < 2**53 else np.int64


def search(ids: np.ndarray, rows: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, k: int, bars: np.ndarray | None = None) -> tuple[list[int], list[int], list[int]]:
    """The k best rows of one shard for each query, ties to smaller ids, without rows of the query's own id.

    A component is a term whose posting list is the shard. A term adds at most
    its bound, max(q * highest, q * lowest). Terms go by the range of what
    they can add. The essential ones, without which no row could reach the
    k-th best score known, are added for all rows; the others are probed a few
    at a time, only for rows that what is left could still lift to that score.
    `bars` are scores that k rows elsewhere are known to reach (-2**63: none);
    a first part of the shard, searched alone, raises them for the rest.
    """
    kind = _kind(rows, queries)
    wide = max(rows.shape[1], queries.shape[1])
    rows, queries = (np.pad(x, ((0, 0), (0, wide - x.shape[1]))) for x in (rows, queries))
    exact = np.int64 if kind is np.int64 else np.float64
    first = min(len(rows), max(64 * k, len(rows) // 16))
    parts = [(ids[a:b], np.ascontiguousarray(rows[a:b].T).astype(kind), rows[a:b].max(0, initial=-(1 << 62)).astype(exact), rows[a:b].min(0, initial=1 << 62).astype(exact)) for a, b in ((0, first), (first, len(rows))) if b > a]
    out: tuple[list[int], list[int], list[int]] = ([], [], [])
    known = [None] * len(queries) if bars is None else [None if x == -(1 << 63) else exact(x) for x in bars.tolist()]
    for own, q, bar in zip(query_ids.tolist(), queries.astype(exact), known):
        got, total = np.zeros(0, np.int64), np.zeros(0, exact)
        for part in parts:
            new, score = _search(own, q, bar, *part)
            got, total = np.concatenate([got, new]), np.concatenate([total, score])
            if len(total) >= k:
                edge = np.partition(total, -k)[-k]
                got, total = got[total >= edge], total[total >= edge]
                bar = edge if bar is None else max(bar, edge)
        best = np.lexsort((got, -total))[:k]
        out[0].extend([own] * len(best))
        out[1].extend(got[best].tolist())
        out[2].extend(int(x) for x in total[best])
    return out


def _search(own: int, q: np.ndarray, bar: float | None, ids: np.ndarray, postings: np.ndarray, high: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids and scores of the rows that reach the bar (all but the query's own, without one)."""
    exact, kind, wide = high.dtype, postings.dtype, len(postings)
    up, down = np.maximum(q * high, q * low), np.minimum(q * high, q * low)
    order = np.argsort(down - up, kind="stable")
    rest = np.concatenate([np.cumsum(up[order][::-1])[::-1], [0]])
    floor = np.cumsum(down[order])
    essential = wide if bar is None else int(np.searchsorted(-(rest[1:] + floor), -bar, "right"))
    at = min(wide, max(STEP, essential + 1))
    score = q[order[:at]].astype(kind) @ postings[order[:at]]
    alive = np.flatnonzero(ids != own)
    total = score[alive].astype(exact)
    while bar is not None:
        keep = total + rest[at] >= bar
        alive, total = alive[keep], total[keep]
        if at >= wide:
            break
        terms = order[at : at + STEP]
        total = total + q[terms] @ postings[np.ix_(terms, alive)].astype(exact)
        at += len(terms)
    return ids[alive], total


def top_k(vectors: DataFrame, is_query: Column, key: str = "vec_id", vector: str = "embedding", k: int = 5, scale: int = 256) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best rows for each query row, by floor(scale * x) inner product.

    Every query meets every row, block by shard; each shard gives k rows a
    query and these are merged. The first shard is searched first, and the
    k-th best score there is the bar that the others start from. Ties go to the smaller id; rows of the query's
    own id are left out, and a query with fewer partners gets them all.

    Vectors that are null, or hold a null or non-finite component, and rows
    with a null id take no part. Empty vectors score 0; a shorter vector ends
    in zeros. A repeated row is a candidate as often as it occurs, and a
    query once. Scores must fit a long. An empty table
    gives no rows; other columns are not read.
    """
    good = F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    base = vectors.select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks")).where(F.col("id").isNotNull()).where(good)
    count = base.agg(F.count(F.lit(1)).alias("n"), F.count_if("asks").alias("q")).first()
    partitions = max(1, int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    n = max(1, count["n"])
    shards, blocks = max(math.ceil(n / SHARD), min(partitions, math.ceil(n / LEAST))), math.ceil(max(1, count["q"]) / BLOCK)
    parts = F.transform("v", lambda x: F.floor(x * scale).cast("long")).alias("parts")
    spread = lambda col, n: F.pmod(F.xxhash64("id", F.lit(col)), F.lit(n)).cast("int")
    every = lambda lo, hi: F.explode(F.sequence(F.lit(lo), F.lit(hi - 1)))
    rows = base.select("id", parts, spread("shard", shards).alias("shard"), every(0, blocks).alias("block"))
    asked = base.where("asks").select("id", parts).dropDuplicates(["id"]).withColumn("block", spread("block", blocks))
    on, found_as = ["shard", "block"], "query_id long, vec_id long, score long"

    def meet(asks: pa.Table, cands: pa.Table) -> pa.Table:
        if not asks.num_rows or not cands.num_rows:
            return pa.table({n: pa.array([], pa.int64()) for n in ("query_id", "vec_id", "score")})
        bars = asks.combine_chunks().sort_by([("id", "ascending")]).column("bar").fill_null(-(1 << 63)).to_numpy()
        found = search(*_matrix(cands), *_matrix(asks), k, bars)
        return pa.table({n: pa.array(x, pa.int64()) for n, x in zip(("query_id", "vec_id", "score"), found)})

    def met(asks: DataFrame, cands: DataFrame) -> DataFrame:
        cands = cands.toDF(*("id", "parts", "shard", "block"))  # names of its own, as both sides come from one table
        return asks.groupBy(*on).cogroup(cands.groupBy(*on)).applyInArrow(meet, found_as)

    partial = met(asked.select("*", F.lit(0).alias("shard"), F.lit(None).cast("long").alias("bar")), rows.where("shard = 0"))
    if shards > 1:
        first = packed.cut(partial)
        bars = first.groupBy(F.col("query_id").alias("q")).agg(F.min("score").alias("bar"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= k).select("q", "bar")
        barred = asked.join(bars, F.col("id") == F.col("q"), "left").drop("q").select("*", every(1, shards).alias("shard"))
        partial = first.unionByName(met(barred, rows.where("shard > 0")))
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return partial.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
