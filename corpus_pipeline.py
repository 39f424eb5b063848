"""A corpus pipeline: quality, near-duplicates, benchmark passages, personal data, packing.

Every stage takes rows with nulls in any column, empty and long texts, repeated rows, columns of other names and empty tables.
A null text is scored, kept and packed as an empty one, and has no duplicates, passages or personal data; a row without an id
stays unless its text decides otherwise. Without labels the quality stage keeps everything (the share of good rows is taken as
one half).
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from mpcrel.llm import decontam, near_dedup, packing, pii, quality
from mpcrel.llm.base import settle, small_batches, table


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    small_batches(spark)
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.with_scores(docs, model, prefix="__quality_").where("__quality_predicted = 1").select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays."""
    small_batches(spark)
    return near_dedup.drop_near_duplicates(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans that repeat test items are cut out; documents that mostly consist of them go."""
    small_batches(spark)
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and the terms that disclose them are replaced."""
    return pii.sanitise(docs)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their places in sequences."""
    small_batches(spark)
    return packing.pack(docs)


STAGES = [
    ("quality_classifier", quality_classifier),
    ("near_duplicates", near_duplicates),
    ("benchmark_decontamination", benchmark_decontamination),
    ("personal_data", personal_data),
    ("best_fit_packing", best_fit_packing),
]

#: The stages train models, hash and tokenise, which SQL cannot express; tests hold them against brute force.
ORACLE_SQL = None


def _drop(spark: SparkSession, path: str) -> None:
    """Deletes a folder on whatever file system it is."""
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents; each result is written to the shared folder and read again by the next stage, after which
    it is deleted."""
    settle(spark.range(1))  # sets a folder where the session has none
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            _drop(spark, f"{folder}/{k - 1}")
    return docs
