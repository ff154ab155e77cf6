"""A corpus pipeline of five stages, each written as Parquet and reread as the next one's input.

Low-quality documents go, repeated chunks of lines are cut, one document of each near-duplicate group
stays, sources are mixed to their target weights, and texts become tokens.
Rows are (doc_id, text, lang, source, n_chars) with any extra columns until the last stage, which returns
the ids of tokens. Cases of nulls, empty texts and repeated rows are those of each operator.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec.scratch import Scratch
from semrank.llm import bpe, line_dedup, mixing, near_dup, quality_classifier


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_classifier.keep_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def cut_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(docs)
    # the count of code points follows the text
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.drop_near_duplicates(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.encode(docs)


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", cut_repeated_lines),
    ("near_dedup", drop_near_duplicates),
    ("mixing", mix_sources),
    ("byte_bpe", encode_tokens),
]

#: The classifier and the tokenizer have no SQL form: tests run the stages against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES[:-1]):
        docs = scratch.write(f"{k}-{name}", stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
