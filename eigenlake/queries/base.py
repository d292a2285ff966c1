"""The registry, and SQL that several oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    """Register a function (spark, sf_dir) under its name, with the SQL that checks it."""
    def add(f: Query) -> Query:
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"registered twice: {key}")
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def r6(c: Column | str, digits: int = 6) -> Column:
    """Rounded, without a negative zero."""
    return F.round(F.col(c) if isinstance(c, str) else c, digits) + F.lit(0.0)


def nearest(c: Column | str, digits: int = 6) -> Column:
    """Rounded as DuckDB does it: to whole multiples of the last digit, halves away from zero, without a negative zero.

    `F.round` goes through the decimal text of each number, which takes longer
    than all else where there are billions of them. Not for numbers of 2^52
    multiples and more, which have no digits beyond.
    """
    x = (F.col(c) if isinstance(c, str) else c) * F.lit(10.0**digits)
    size = F.abs(x)
    whole = F.floor(size)
    whole = whole + F.when(size - whole >= 0.5, 1).otherwise(0)
    return F.when(x < 0, -whole).otherwise(whole) / F.lit(10.0**digits) + F.lit(0.0)


def power_sql(entries: str, order: str, steps: int, result: str, group: str = "0") -> str:
    """DuckDB: the two leading eigenvalues (a, b) of entries(g, i, j, v), by iterating two columns at once.

    `entries` and `order` (one value n) are queries; `result` selects from
    final(g, a, b).
    """
    return f"""
    WITH RECURSIVE e AS MATERIALIZED ({entries}), o AS MATERIALIZED ({order}),
    grid AS (SELECT g.g, a.i, b.i AS j FROM (SELECT DISTINCT g FROM e) g, (SELECT range AS i FROM range((SELECT n FROM o))) a, (SELECT range AS i FROM range((SELECT n FROM o))) b),
    lines AS (SELECT grid.g, grid.i, list(coalesce(e.v, 0.0)::DOUBLE ORDER BY grid.j) AS r FROM grid LEFT JOIN e ON e.g = grid.g AND e.i = grid.i AND e.j = grid.j GROUP BY ALL),
    m AS MATERIALIZED (SELECT g, list(r ORDER BY i) AS a FROM lines GROUP BY g),
    it(g, step, x, y) AS (
      SELECT g, 0, list_transform(range(1, (SELECT n FROM o) + 1), lambda k: 1.0::DOUBLE / k), list_transform(range(1, (SELECT n FROM o) + 1), lambda k: sin(1.7 * k)::DOUBLE) FROM m
      UNION ALL
      SELECT g, step + 1, x2, list_transform(w, lambda q: q / sqrt(list_dot_product(w, w)))
      FROM (SELECT g, step, x2, list_transform(u2, lambda q, k: q - list_dot_product(x2, u2) * x2[k]) AS w
        FROM (SELECT g, step, list_transform(u1, lambda q: q / sqrt(list_dot_product(u1, u1))) AS x2, u2
          FROM (SELECT it.g, step, list_transform(a, lambda r: list_dot_product(r, x)) AS u1, list_transform(a, lambda r: list_dot_product(r, y)) AS u2 FROM it JOIN m ON m.g = it.g WHERE step < {steps})))
    ),
    final AS (SELECT it.g, list_dot_product(x, list_transform(a, lambda r: list_dot_product(r, x))) AS a, list_dot_product(y, list_transform(a, lambda r: list_dot_product(r, y))) AS b FROM it JOIN m ON m.g = it.g WHERE step = {steps})
    {result}"""


EMBEDDING_GRAM = "SELECT 0 AS g, a.j - 1 AS i, b.j - 1 AS j, sum(a.x * b.x) AS v FROM (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings) a JOIN (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings) b USING (vec_id) GROUP BY ALL"
COSUPPLY = "SELECT a.l_suppkey AS i, b.l_suppkey AS j, count(*)::DOUBLE AS v FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey != b.l_suppkey GROUP BY ALL"
FLOWS = "SELECT c_nationkey::BIGINT AS i, s_nationkey::BIGINT AS j, count(*)::DOUBLE AS f FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"
PHASE = f"SELECT i, j, (f + b) / 2 * cos(pi() / 2 * (f - b) / (f + b)) AS v, (f + b) / 2 * sin(pi() / 2 * (f - b) / (f + b)) AS im FROM (SELECT i, j, sum(f) AS f, sum(b) AS b FROM (SELECT i, j, f, 0.0 AS b FROM ({FLOWS}) UNION ALL SELECT j, i, 0.0, f FROM ({FLOWS})) GROUP BY ALL) WHERE f + b != 0"


def cosupply(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..build.graph import cooccurrence

    return cooccurrence(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey"), "l_orderkey", "l_suppkey")


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, j, f): lines from customers of nation i to suppliers of nation j."""
    lines, orders, customer, supplier = (table(spark, sf_dir, x) for x in ("lineitem", "orders", "customer", "supplier"))
    joined = (
        lines.select("l_orderkey", "l_suppkey").join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(customer.select("c_custkey", F.col("c_nationkey").cast("long").alias("i")), F.col("o_custkey") == F.col("c_custkey"))
        .join(supplier.select("s_suppkey", F.col("s_nationkey").cast("long").alias("j")), F.col("l_suppkey") == F.col("s_suppkey"))
    )
    return joined.groupBy("i", "j").agg(F.count(F.lit(1)).cast("double").alias("f"))
