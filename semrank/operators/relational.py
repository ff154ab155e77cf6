"""Joins that stand around the methods: as-of and interval joins, and orderings by several criteria."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.operators.fuse import UNIT


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, to: str) -> DataFrame:
    """``left`` with ``to``: the ``value`` of the last row of ``right`` with the same key at or before ``at``.

    One shuffle by key: both sides are stacked and the last value is carried forward. Of right rows at one instant the largest value holds.
    """
    cols = [c for c in left.columns]
    a = left.select(F.lit(1).alias("_side"), F.col(key).alias("_k"), F.col(at).alias("_at"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.struct(*cols).alias("_row"))
    b = right.select(F.lit(0).alias("_side"), F.col(key).alias("_k"), F.col(at).alias("_at"), F.col(value).alias("_v"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"))
    w = W.partitionBy("_k").orderBy("_at", "_side", "_v").rowsBetween(W.unboundedPreceding, W.currentRow)
    out = a.unionByName(b).withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return out.select("_row.*", F.col("_last").alias(to))


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs of the same key with right.at in (left.at, left.at + seconds]: columns of the right get the prefix r_.

    Time is cut into buckets as wide as the interval: a pair is in one bucket or in neighbours, so it is an equi-join, not a range join.
    """
    bucket = F.floor(F.unix_micros(F.col(at).cast("timestamp")) / (seconds * 1_000_000))
    a = left.withColumn("_b", F.explode(F.array(bucket, bucket + 1)))
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns], bucket.alias("_rb"))
    gap = F.unix_micros(F.col(f"r_{at}").cast("timestamp")) - F.unix_micros(F.col(at).cast("timestamp"))
    return a.join(b, (F.col(key) == F.col(f"r_{key}")) & (F.col("_b") == F.col("_rb"))).where((gap > 0) & (gap <= seconds * 1_000_000)).drop("_b", "_rb")


def rank_by_many(rankings: DataFrame, weights: dict[str, int], c: int = 60) -> DataFrame:
    """Several criteria at once: rankings (path_id names the criterion) fused by weighted reciprocal ranks; whole numbers decide ties."""
    table = F.create_map(*[x for k, v in weights.items() for x in (F.lit(k), F.lit(v))])
    s = rankings.where(F.col("path_id").isin(*weights)).groupBy("task_id", "item_id").agg(F.sum(F.expr(f"{UNIT} div ({c} + rnk)") * table[F.col("path_id")]).alias("fused"))
    w = W.partitionBy("task_id").orderBy(F.col("fused").desc(), "item_id")
    return s.select("task_id", "item_id", F.row_number().over(w).cast("bigint").alias("rnk"))
