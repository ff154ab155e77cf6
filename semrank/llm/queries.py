"""The subpackage's queries over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from semrank.exec.scratch import Scratch
from semrank.llm import bpe, license_scan, line_dedup, merkle, mixing, near_dup, quality_classifier, quality_rules, secret_scan, token_counts
from semrank.llm.oracle import ORACLES
from semrank.llm.text import load


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.maintain(load(spark, sf_dir, "documents"), Scratch(spark, "token-counts").root)


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.secret_scan(load(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs, counts=True)


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_rules(load(spark, sf_dir, "documents")).select(*quality_rules.QUERY_COLUMNS)


def op5_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(load(spark, sf_dir, "documents"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_counts(load(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(load(spark, sf_dir, "documents"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.license_scan(load(spark, sf_dir, "documents"))


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.classify(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op10_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merkle.fingerprints(load(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_token_counts, op2_secret_scan, op3_line_dedup, op4_quality_rules, op5_near_duplicates,
        op6_mixing, op7_byte_bpe, op8_license_scan, op9_quality_classifier, op10_fingerprints, pipeline,
    )
}


def oracles() -> dict[str, str]:
    return dict(ORACLES)
