"""Streams with state of their own, late rows, and the ingest of shares."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import shares
from ..model import settle
from ..sources import share_store
from .windows import CENTS, DAY, drained, events


def running_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many events each user has, kept as state per key and written out at the end of each batch."""
    import pandas as pd

    def count(key, batches, state):
        total = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((total,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [total]})

    counted = events(spark, sf_dir).select("user_id").groupBy("user_id").applyInPandasWithState(count, "user_id long, n long", "n long", "update", "NoTimeout")
    return drained(counted, "update").groupBy("user_id").agg(F.max("n").alias("n"))


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts by watermark: a second batch holds a row far ahead, which closes the windows before it, and a third one a row
    long before the watermark, which is dropped. The row far ahead stays in its open window."""
    settle(spark.range(1))
    folder = f"{spark.sparkContext.getCheckpointDir()}/late-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.unix_date(F.col("ts").cast("date")).cast("long").alias("day"))
    rows.withColumn("at", F.timestamp_seconds(F.col("day") * 86400)).drop("day").coalesce(1).write.parquet(f"{folder}/a")
    for name, day in (("b", "2100-01-01"), ("c", "1971-01-01")):
        spark.range(1).select((F.col("id") - 1).alias("event_id"), F.lit(day).cast("timestamp").alias("at")).write.parquet(f"{folder}/{name}")
    schema = "event_id long, at timestamp"

    def run(path: str) -> DataFrame:
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("at", "1 day")
        return stream.groupBy(F.window("at", "1 day")).agg(F.count("*").alias("n"))

    return drained(run(f"{folder}/*"), "append").select(F.unix_micros("window.start").alias("start"), "n")


def shares_on_arrival(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows are shared batch by batch as they arrive, one folder for each party; two parties open them again."""
    settle(spark.range(1))
    folder = f"{spark.sparkContext.getCheckpointDir()}/ingest-{uuid.uuid4().hex}"

    def take(batch: DataFrame, number: int) -> None:
        share_store.upload(batch, ["cents"], f"{folder}/batch={number}", f"ingest{number}", "event_id")

    stream = events(spark, sf_dir).select("event_id", "cents")
    stream.writeStream.foreachBatch(take).trigger(availableNow=True).option("checkpointLocation", f"{folder}/state").start().awaitTermination()
    views = {p: spark.read.parquet(f"{folder}/batch=*/party={p}") for p in (0, 2)}
    return shares.open_views(views, ["cents"], "event_id").select("event_id", "cents")


ENTRIES: dict[str, tuple[Callable, str]] = {
    "st_state_degrees": (running_degrees, "SELECT user_id, count(*) AS n FROM events GROUP BY 1"),
    "st_watermark_late": (late_rows, f"SELECT {DAY} AS start, count(*) AS n FROM events GROUP BY 1"),
    "st_share_ingest": (shares_on_arrival, f"SELECT event_id, {CENTS} AS cents FROM events"),
}
