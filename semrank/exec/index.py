"""Global row numbers without one task that sees all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.scratch import Scratch


def indexed(df: DataFrame, order: list[str], scratch: Scratch, name: str = "pos", partitions: int | None = None) -> DataFrame:
    """Adds ``name``: 0-based place by ``order`` (columns that together are unique).

    Rows are range-partitioned once and written with their partition and place in it; partition counts (one row per
    partition) become offsets.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(n, *order).sortWithinPartitions(*order)
    # the low 33 bits of the monotonic id are the place within the partition, the high ones the partition
    ranged = scratch.write(f"{name}-ranged", ranged.withColumn("_mono", F.monotonically_increasing_id()))
    part = F.shiftright("_mono", 33)
    counts = ranged.groupBy(part.alias("_part")).agg(F.count("*").alias("_n"))
    offsets = counts.select("_part", (F.sum("_n").over(W.orderBy("_part")) - F.col("_n")).alias("_from"))
    out = ranged.withColumn("_part", part).join(F.broadcast(offsets), "_part")  # as many rows as partitions
    return out.withColumn(name, F.col("_from") + F.col("_mono").bitwiseAND(F.lit((1 << 33) - 1))).drop("_part", "_mono", "_from")


def placed_by(df: DataFrame, order: list[str], scratch: Scratch, name: str) -> DataFrame:
    """``df`` with ``name``: places from 1 by ``order`` within each task, by range partitions and counts."""
    d = indexed(df, ["task_id", *order], scratch, name)
    start = d.groupBy("task_id").agg(F.min(name).alias("_start"))
    return d.join(start, "task_id").withColumn(name, F.col(name) - F.col("_start") + 1).drop("_start")
