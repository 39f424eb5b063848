"""Reading tables and encoding their values as 64-bit words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read(name: str):
    """A reader of one Parquet table; columns are pruned and predicates pushed by the plan above it."""
    def table(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.read.parquet(f"{sf_dir}/{name}.parquet")

    return table


def fixed(column: str, scale: int = 2) -> Column:
    """Fixed point: exact for values that are multiples of 10^-scale."""
    return F.round(F.col(column) * (10**scale)).cast("long")


def micros(column: str) -> Column:
    """Microseconds of a time-zone-free timestamp, whatever the session's time zone."""
    c = F.col(column)
    days = F.unix_date(c.cast("date")).cast("long") * 86_400_000_000
    return days + (F.hour(c) * 3600 + F.minute(c) * 60).cast("long") * 1_000_000 + F.round(F.expr(f"extract(SECOND FROM {column})") * 1_000_000).cast("long")


def text_tag(column: str) -> Column:
    """Two words that stand for a string of an open domain."""
    return F.struct(F.xxhash64(column).alias("t0"), F.xxhash64(F.lit(0x7A6), F.col(column)).alias("t1"))


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A directed graph from the events: source, target, rating (cents), time."""
    return read("events")(spark, sf_dir).select(F.col("user_id").alias("source"), F.get_json_object("props", "$.k").cast("long").alias("target"), fixed("value").alias("rating"), F.col("ts").alias("time"))


def revenue() -> Column:
    return fixed("l_extendedprice") * (100 - fixed("l_discount"))


def part_supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stands for a supply relation: quantity by part and supplier."""
    return read("lineitem")(spark, sf_dir).groupBy("l_partkey", "l_suppkey").agg(F.sum(fixed("l_quantity")).alias("qty"))
