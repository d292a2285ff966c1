"""The library from SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..relational.udfs import EigTable


def register(spark: SparkSession) -> None:
    """SQL functions mem_host, mem_device, cheb_degree (built-in expressions) and the table function eig_table."""
    spark.udtf.register("eig_table", EigTable)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mem_host(n DOUBLE, s DOUBLE, r DOUBLE, c DOUBLE) RETURNS DOUBLE RETURN 8 * ((n / r) * (n / c) + (n / r + n / c) * s + 2 * s * n)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mem_device(n DOUBLE, s DOUBLE, r DOUBLE, c DOUBLE, u DOUBLE, w DOUBLE) RETURNS DOUBLE RETURN 8 * ((n / r) * (n / c) / (u * w) + 3 * s * greatest(n / (r * u), n / (c * w)) + s * (2 * n + s))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cheb_degree(tol DOUBLE, res DOUBLE, t DOUBLE) RETURNS INT RETURN CAST(ceil(ln(greatest(res, tol) / tol) / ln(abs(t) + sqrt(t * t - 1))) AS INT)")


def views(operator: DataFrame, spectrum: DataFrame, trace: DataFrame) -> None:
    """Temporary views `operator`, `spectrum` and `trace`."""
    for name, df in (("operator", operator), ("spectrum", spectrum), ("trace", trace)):
        df.createOrReplaceTempView(name)
