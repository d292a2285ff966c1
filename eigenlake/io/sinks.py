"""Writers of operators and results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_blocks(blocks: DataFrame, path: str, groups: int = 16, mode: str = "errorifexists") -> None:
    """Blocks as parquet, partitioned by groups of block rows so that a stripe is read alone."""
    blocks.withColumn("bi_group", F.expr(f"bi div {groups}")).write.mode(mode).partitionBy("bi_group").parquet(path)


def write_bucketed(blocks: DataFrame, table: str, buckets: int, mode: str = "errorifexists") -> None:
    """Blocks as a bucketed catalog table, so that joins on bj need no shuffle of the operator."""
    blocks.write.mode(mode).bucketBy(buckets, "bj").sortBy("bi").saveAsTable(table)


def write_coord_text(coo: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """One 'i j value' line for each entry, from 1."""
    coo.select(F.concat_ws(" ", (F.col("i") + 1).cast("string"), (F.col("j") + 1).cast("string"), F.col("v").cast("string")).alias("value")).write.mode(mode).text(path)


def write_result(result, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """Values, vectors and trace of a result beside each other."""
    for name, df in (("values", result.values), ("vectors", result.vectors()), ("trace", result.trace)):
        out = df.withColumns({c: F.to_json(c) for c, t in df.dtypes if t.startswith("array")}) if fmt == "csv" else df
        out.write.mode(mode).format(fmt).option("header", True).save(f"{path}/{name}")


def noop(df: DataFrame) -> None:
    """Compute everything, keep nothing: for benches."""
    df.write.format("noop").mode("overwrite").save()
