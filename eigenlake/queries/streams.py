"""Streams of events replayed to their end; each equals the batch answer on the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import partitions, shared_folder
from ..streaming import state, windows
from .base import query, r6, table


def replay(spark: SparkSession, sf: str, build: Callable[[DataFrame], DataFrame], mode: str, files: int = 3, conf: dict[str, str] | None = None) -> DataFrame:
    """Write events in slices of days, stream them one slice after the other with `build`, and read what the stream wrote.

    The stream runs in a session of its own, with few state partitions: a
    bounded replay of one table needs no more.
    """
    own = spark.newSession()
    for key, value in ({"spark.sql.shuffle.partitions": str(min(8, partitions(spark)))} | (conf or {})).items():
        own.conf.set(key, value)
    folder = f"{shared_folder(spark)}/replay-{uuid.uuid4().hex}"
    events = table(spark, sf, "events")
    events.withColumn("slice", F.pmod(F.dayofyear("ts"), F.lit(files))).write.partitionBy("slice").parquet(f"{folder}/in")
    stream = own.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in/*")
    stream = stream.withColumn("ts", F.col("ts").cast("timestamp"))

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.withColumn("batch", F.lit(batch_id)).write.mode("overwrite").parquet(f"{folder}/out/{batch_id}")

    q = build(stream).writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination(600)
    return spark.read.parquet(f"{folder}/out/*")


def latest(rows: DataFrame, on: list[str], values: list[str]) -> DataFrame:
    """The last version of each key."""
    return rows.groupBy(*on).agg(F.max_by(F.struct(*values), "batch").alias("x")).select(*on, *(F.col(f"x.{v}").alias(v) for v in values))


_EPOCH = "TIMESTAMP '1970-01-01'"


@query(f"SELECT time_bucket(INTERVAL 7 DAY, ts, {_EPOCH})::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling_counts(spark: SparkSession, sf: str) -> DataFrame:
    out = replay(spark, sf, lambda s: windows.tumbling_counts(s, "ts", "event_type", watermark="60 days"), "update")
    return latest(out, ["start", "event_type"], ["n"]).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query(f"SELECT (time_bucket(INTERVAL 1 DAY, ts, {_EPOCH}) - INTERVAL 1 DAY * b.range)::TIMESTAMP AS start, count(*) AS n, round(sum(value), 4) AS sx, round(sum(value * value), 2) AS sxx FROM events, range(7) b GROUP BY ALL")
def stream_sliding_cov(spark: SparkSession, sf: str) -> DataFrame:
    out = replay(spark, sf, lambda s: windows.sliding_moments(s, "ts", "value", watermark="60 days"), "update")
    return latest(out, ["start"], ["n", "sx", "sxx"]).select(F.col("start").cast("timestamp_ntz").alias("start"), "n", r6("sx", 4).alias("sx"), r6("sxx", 2).alias("sxx"))


@query("SELECT user_id, count(*) AS sessions, max(n)::BIGINT AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT user_id, ts, event_id, (coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE, true))::INT AS new FROM events)) GROUP BY ALL) GROUP BY 1")
def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    out = replay(spark, sf, lambda s: windows.sessions(s, "ts", "user_id", watermark="60 days"), "complete")
    last = out.agg(F.max("batch").alias("last"))
    return out.join(F.broadcast(last), F.col("batch") == F.col("last")).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS sx, round(sum(value * value), 2) AS sxx, round(sum(value * (user_id % 7)), 3) AS sxy FROM events GROUP BY 1")
def stream_gram_state(spark: SparkSession, sf: str) -> DataFrame:
    store = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"}
    out = replay(spark, sf, lambda s: state.running_gram(s.withColumn("y", F.col("user_id") % 7), "event_type", ["value", "y"]), "update", conf=store)
    return latest(out, ["key"], ["n", "s", "g"]).select(F.col("key").alias("event_type"), "n", r6(F.col("s")[0], 4).alias("sx"), r6(F.col("g")[0], 2).alias("sxx"), r6(F.col("g")[1], 3).alias("sxy"))


@query("SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY 1")
def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    def nations(stream: DataFrame) -> DataFrame:
        return table(stream.sparkSession, sf, "nation").select(F.col("n_nationkey").cast("long").alias("k"), "n_name")

    out = replay(spark, sf, lambda s: windows.enriched(s.withColumn("k", F.col("user_id") % 25), nations(s), ["k"]).groupBy("n_name").agg(F.count(F.lit(1)).alias("n")), "update")
    return latest(out, ["n_name"], ["n"])


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = (SELECT min(event_type) FROM events) AND b.event_type = (SELECT max(event_type) FROM events)")
def stream_stream_join(spark: SparkSession, sf: str) -> DataFrame:
    """Events of the first kind followed within an hour by the user's events of the last kind."""
    kinds = table(spark, sf, "events").agg(F.min("event_type").alias("a"), F.max("event_type").alias("b")).first()

    def build(stream: DataFrame) -> DataFrame:
        side = lambda kind: stream.where(F.col("event_type") == kind).select("user_id", F.col("event_id").alias("id"), "ts")
        return windows.followed(side(kinds["a"]), side(kinds["b"]), "user_id", watermark="60 days")

    return replay(spark, sf, build, "append").select("first_id", "second_id")
