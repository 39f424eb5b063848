"""The thin queries of this subpackage and their SQL."""

from __future__ import annotations

from . import decontam, fingerprints, language, licenses, near_dedup, passages, pii, quality, toxicity
from .base import small_batches, table
from .packing import pack


def op1_toxicity(spark, sf_dir):
    documents = table(spark, sf_dir, "documents")
    return toxicity.score_toxicity(documents, toxicity.train(documents, table(spark, sf_dir, "labels")))


def op2_minhash_near_dedup(spark, sf_dir):
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"), near_dedup.NearConfig(shingle=3, percent=85, rows=5))


def op3_pii(spark, sf_dir):
    return pii.report(table(spark, sf_dir, "documents"))


def op4_substring_dedup(spark, sf_dir):
    small_batches(spark)
    return passages.passages(table(spark, sf_dir, "documents"))


def op5_language_id(spark, sf_dir):
    documents = table(spark, sf_dir, "documents")
    return language.identify(documents, language.train(documents))


def op6_document_fingerprints(spark, sf_dir):
    return fingerprints.fingerprints(table(spark, sf_dir, "documents"))


def op7_license_scan(spark, sf_dir):
    return licenses.scan(table(spark, sf_dir, "documents"))


def op8_benchmark_decontamination(spark, sf_dir):
    return decontam.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_quality_classifier(spark, sf_dir):
    documents = table(spark, sf_dir, "documents")
    return quality.score_quality(documents, quality.train(documents, table(spark, sf_dir, "labels")))


def op10_best_fit_packing(spark, sf_dir):
    return pack(table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_minhash_near_dedup": op2_minhash_near_dedup,
    "op3_pii": op3_pii,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_language_id": op5_language_id,
    "op6_document_fingerprints": op6_document_fingerprints,
    "op7_license_scan": op7_license_scan,
    "op8_benchmark_decontamination": op8_benchmark_decontamination,
    "op9_quality_classifier": op9_quality_classifier,
    "op10_best_fit_packing": op10_best_fit_packing,
}

ORACLE_SQL: dict[str, str] = {
    "op7_license_scan": licenses.oracle_sql(),
}
