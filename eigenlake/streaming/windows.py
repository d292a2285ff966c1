"""Event-time windows over a stream of events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _marked(stream: DataFrame, time: str, watermark: str | None) -> DataFrame:
    """The stream with its watermark; None leaves one that an earlier step has set."""
    return stream.withWatermark(time, watermark) if watermark else stream


def deduplicated(stream: DataFrame, time: str, key: str, watermark: str = "1 hour") -> DataFrame:
    """Rows whose key was not seen within the watermark."""
    return stream.withWatermark(time, watermark).dropDuplicatesWithinWatermark([key])


def tumbling_counts(stream: DataFrame, time: str, by: str, size: str = "7 days", watermark: str | None = "1 hour") -> DataFrame:
    """(start, by, n) of tumbling windows."""
    return _marked(stream, time, watermark).groupBy(F.window(time, size).alias("w"), by).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), by, "n")


def sliding_moments(stream: DataFrame, time: str, value: str, size: str = "7 days", slide: str = "1 day", watermark: str | None = "1 hour") -> DataFrame:
    """(start, n, sx, sxx) of sliding windows: what a variance or a Gram entry needs, as sums that add up."""
    w = F.window(time, size, slide).alias("w")
    sums = _marked(stream, time, watermark).groupBy(w).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias("sx"), F.sum(F.col(value) * F.col(value)).alias("sxx"))
    return sums.select(F.col("w.start").alias("start"), "n", "sx", "sxx")


def sessions(stream: DataFrame, time: str, by: str, gap: str = "30 minutes", watermark: str | None = "1 hour") -> DataFrame:
    """(by, start, end, n) of sessions that end after a gap."""
    s = F.session_window(time, gap).alias("s")
    return _marked(stream, time, watermark).groupBy(s, by).agg(F.count(F.lit(1)).alias("n")).select(by, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def enriched(stream: DataFrame, static: DataFrame, on: list[str]) -> DataFrame:
    """A stream joined to a static table; no state is kept."""
    return stream.join(static, on)


def followed(first: DataFrame, second: DataFrame, on: str, within: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """Pairs of two streams' rows of one key, the second at most `within` after the first.

    Both sides are kept no longer than the watermarks and the interval ask
    for. The streams have columns (key, id, ts); the result has (key,
    first_id, second_id).
    """
    a = first.select(F.col(on), F.col("id").alias("first_id"), F.col("ts").alias("t1")).withWatermark("t1", watermark)
    b = second.select(F.col(on).alias("__k"), F.col("id").alias("second_id"), F.col("ts").alias("t2")).withWatermark("t2", watermark)
    return a.join(b, F.expr(f"{on} = __k AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select(on, "first_id", "second_id")
