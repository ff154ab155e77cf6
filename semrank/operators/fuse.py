"""Rank fusion: integer sums, so the order in which a shuffle delivers rows cannot change a tie."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.index import placed_by
from semrank.exec.scratch import Scratch

UNIT = 10**12


def _ranked(scores: DataFrame, path_id: str) -> DataFrame:
    w = W.partitionBy("task_id").orderBy(F.col("fused").desc(), "item_id")
    return scores.select("task_id", F.lit(path_id).alias("path_id"), "item_id", F.row_number().over(w).cast("bigint").alias("rnk"), "fused")


def fuse_rrf(rankings: DataFrame, c: int = 60, path_id: str = "rrf", wide: bool = False) -> DataFrame:
    """Reciprocal rank fusion: sum of 1 / (c + rank) over the rankings that list an item, in units of 10^-12.

    ``wide``: some tasks are too large for a window over all their items, and are numbered by ranges.
    """
    s = rankings.groupBy("task_id", "item_id").agg(F.sum(F.expr(f"{UNIT} div ({c} + rnk)")).alias("fused"))
    if wide:
        d = placed_by(s.withColumn("_behind", -F.col("fused")), ["_behind", "item_id"], Scratch(rankings.sparkSession, "fuse"), "rnk")
        return d.select("task_id", F.lit(path_id).alias("path_id"), "item_id", "rnk", "fused")
    return _ranked(s, path_id)


def fuse_borda(rankings: DataFrame, path_id: str = "borda") -> DataFrame:
    """Borda count: sum of (n - rank), n the length of the longest ranking of the task."""
    n = rankings.groupBy("task_id").agg(F.max("rnk").alias("n"))
    s = rankings.join(n, "task_id").groupBy("task_id", "item_id").agg(F.sum(F.col("n") - F.col("rnk")).alias("fused"))
    return _ranked(s, path_id)
