"""Structured replies: a schema per operation, parsed and repaired as columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

REPLY_SCHEMA = {
    "score": "value bigint",
    "score_many": "values array<bigint>",
    "compare": "better bigint",
    "order": "order array<bigint>",
    "inquiry": "world_fact boolean",
    "judge": "choice bigint",
}


def parse(reply: Column, op: str) -> Column:
    """A struct, null fields where the reply does not follow the schema."""
    return F.from_json(reply, REPLY_SCHEMA[op])


def repaired_order(reply: Column, shown: Column) -> Column:
    """A permutation of ``shown``: known ids of the reply, each once, then the missing ones in the order shown."""
    known = F.array_distinct(F.filter(F.coalesce(reply, F.array().cast("array<bigint>")), lambda x: F.array_contains(shown, x)))
    return F.concat(known, F.array_except(shown, known))


def parse_orders(replies: DataFrame) -> DataFrame:
    """(req_id, reply text, shown ids) -> order and whether it had to be repaired."""
    got = parse(F.col("reply"), "order")["order"]
    d = replies.withColumn("order", repaired_order(got, F.col("shown")))
    return d.withColumn("repaired", ~F.coalesce(got == F.col("order"), F.lit(False)))


def fit_batch(lengths: DataFrame, m: int, max_tokens: int, template_chars: int = 200) -> DataFrame:
    """Per task the largest batch up to ``m`` whose m longest keys fit a context window, 1 at least. lengths: task_id, chars."""
    from pyspark.sql import Window as W

    w = W.partitionBy("task_id").orderBy(F.col("chars").desc())
    d = lengths.withColumn("r", F.row_number().over(w)).where(F.col("r") <= m)
    d = d.withColumn("sum", F.sum("chars").over(w.rowsBetween(W.unboundedPreceding, W.currentRow)))
    fits = F.ceil((F.col("sum") + template_chars) / 4) <= max_tokens
    return d.groupBy("task_id").agg(F.greatest(F.max(F.when(fits, F.col("r"))), F.lit(1)).cast("int").alias("m"))
