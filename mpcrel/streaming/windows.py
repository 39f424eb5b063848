"""Structured-streaming forms of event windows, deduplication, joins and state, run over what is available."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import settle
from ..sources.tables import fixed, micros


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream with event time `at`; a glob lets a single file be the source."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]")
    return stream.select("event_id", "user_id", "event_type", fixed("value").alias("cents"), F.timestamp_micros(micros("ts")).alias("at"))


def drained(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs the stream until its input is used up and returns what its sink holds: files in the shared folder, beside the state.

    Batches are written as they come, each to a place of its own, so that a batch that runs again replaces itself; of a
    complete-mode query the last batch is the result.
    """
    spark = df.sparkSession
    settle(spark.range(1))
    folder = f"{spark.sparkContext.getCheckpointDir()}/drained-{uuid.uuid4().hex}"
    seen = []

    def take(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch={number}")
        seen.append(number)

    query = df.writeStream.outputMode(mode).foreachBatch(take).trigger(availableNow=True).option("checkpointLocation", f"{folder}-state").start()
    query.awaitTermination()
    if not seen:
        return spark.createDataFrame([], df.schema)
    kept = seen[-1:] if mode == "complete" else seen
    return spark.read.schema(df.schema).parquet(*(f"{folder}/batch={n}" for n in kept))


def _start(window: str = "window") -> list:
    return [F.unix_micros(F.col(f"{window}.start")).alias("start"), "event_type", "n", "cents"]


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).groupBy(F.window("at", "1 day"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    return drained(out).select(*_start())


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).groupBy(F.window("at", "2 days", "1 day"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    return drained(out).select(*_start())


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).groupBy(F.session_window("at", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    return drained(out).select("user_id", F.unix_micros("session_window.start").alias("start"), "n")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = events(spark, sf_dir)
    return drained(rows.withWatermark("at", "1 hour").dropDuplicates(["event_id"]).select("event_id", "user_id"), "append")


def with_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment")
    joined = events(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey"))
    return drained(joined.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")))


def clicks_to_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a click and a purchase of the same user within the next day."""
    click = events(spark, sf_dir).where("event_type = 'click'").select(F.col("user_id").alias("who"), F.col("event_id").alias("click"), F.col("at").alias("clicked")).withWatermark("clicked", "1 day")
    buy = events(spark, sf_dir).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("at").alias("bought")).withWatermark("bought", "1 day")
    near = F.expr("user_id = who AND bought >= clicked AND bought <= clicked + INTERVAL 1 DAY")
    return drained(click.join(buy, near).select("click", "purchase"), "append")


DAY = "CAST(floor(epoch_us(ts) / 86400000000) AS BIGINT) * 86400000000"
CENTS = "CAST(round(value * 100) AS BIGINT)"
ENTRIES: dict[str, tuple[Callable, str]] = {
    "st_tumbling": (tumbling, f"SELECT {DAY} AS start, event_type, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM events GROUP BY ALL"),
    "st_sliding": (sliding, f"SELECT {DAY} - k * 86400000000 AS start, event_type, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM events, (VALUES (0), (1)) o(k) GROUP BY ALL"),
    "st_session": (sessions, """SELECT user_id, min(us) AS start, count(*) AS n FROM (SELECT user_id, us, sum(new) OVER (PARTITION BY user_id ORDER BY us, event_id) AS s FROM (
        SELECT user_id, event_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s"""),
    "st_dedup": (deduplicated, "SELECT DISTINCT event_id, user_id FROM events"),
    "st_stream_static": (with_customers, f"SELECT c_mktsegment, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL"),
    "st_stream_stream": (clicks_to_purchases, "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY"),
}
