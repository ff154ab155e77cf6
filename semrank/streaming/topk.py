"""Ranking of streams: a running top-K per window, merged batch by batch with the two-way merge."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec.generators import merge_two
from semrank.exec.packed import rankings_of, run_paths
from semrank.exec.scratch import Scratch, file_system, path_exists
from semrank.plans.spec import EXT_MERGE, PathConfig
from semrank.sources.model import Key, ModelBackend, SimBackend, repair_order

TOPK = "task_id string, item_id bigint, rnk bigint, lat bigint, chars int, text string"


def read_events(spark: SparkSession, sf_dir: str, **options: str) -> DataFrame:
    """The events table as a stream, file by file."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    fs, where = file_system(spark, path)
    r = spark.readStream.schema(schema).options(**options)
    out = r.parquet(path) if fs.getFileStatus(where).isDirectory() else r.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return out.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need instants


class RunningTopK:
    """foreachBatch handler: ranks a micro-batch's items per task and merges them into the top K so far.

    State is a table per batch under ``root``, complete once Spark's success marker is there; a replayed batch starts from the state before it, so it
    changes nothing, and a handler that is started anew on the same ``root`` (with the same checkpoint) goes on from what is there.
    """

    def __init__(self, spark: SparkSession, k: int, backend: ModelBackend | None = None, path: PathConfig = EXT_MERGE, root: str | None = None):
        self.spark, self.k, self.path, self.backend = spark, k, path, backend or SimBackend()
        self.scratch = Scratch(spark, "stream")
        self.root = root.rstrip("/") if root else self.scratch.path("state")

    def batches(self) -> list[int]:
        """Batches whose state is complete."""
        fs, root = file_system(self.spark, self.root)
        names = [f.getPath().getName() for f in fs.listStatus(root)] if fs.exists(root) else []
        return sorted(int(n[4:]) for n in names if n.startswith("top-") and path_exists(self.spark, f"{self.root}/{n}/_SUCCESS"))

    def state(self, before: int | None = None) -> DataFrame:
        known = [b for b in self.batches() if before is None or b < before]
        return self.spark.read.schema(TOPK).parquet(f"{self.root}/top-{known[-1]}") if known else self.spark.createDataFrame([], TOPK)

    def __call__(self, items: DataFrame, batch: int) -> None:
        """``items``: task_id, item_id, pos, key, lat."""
        items = self.scratch.write(f"in{batch}", items.withColumn("k", F.lit(self.k).cast("bigint")))
        ranked = rankings_of(run_paths(items, [self.path], self.backend, scratch=self.scratch, name=f"run{batch}"))
        text = F.col("key") if self.backend.reads_text else F.lit("")
        new = ranked.join(items.select("task_id", "item_id", "lat", F.length("key").alias("chars"), text.alias("text")), ["task_id", "item_id"]).select("task_id", "item_id", "rnk", "lat", "chars", "text")
        k, m, backend = self.k, self.path.m, self.backend

        def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
            both = pd.concat([a, b])
            task = both["task_id"].iloc[0]
            keys = {int(i): Key(int(i), int(c), int(x), None, t) for i, c, x, t in zip(both["item_id"], both["chars"], both["lat"], both["text"], strict=True)}
            runs = [[int(i) for i in f.sort_values("rnk")["item_id"]] for f in (a, b)]
            g = merge_two(runs[0], runs[1], m, k)
            try:
                ask = next(g)
                while True:
                    shown = [keys[x] for x in ask]
                    ask = g.send(repair_order(backend.order(task, shown)[0], shown)[0])
            except StopIteration as end:
                ids = end.value
            return pd.DataFrame({"task_id": task, "item_id": ids, "rnk": range(1, len(ids) + 1), "lat": [keys[i].latent for i in ids], "chars": [keys[i].chars for i in ids], "text": [keys[i].text for i in ids]})

        merged = self.state(batch).groupBy("task_id").cogroup(new.groupBy("task_id")).applyInPandas(merge, TOPK)
        merged.write.mode("overwrite").parquet(f"{self.root}/top-{batch}")


def event_items(events: DataFrame) -> DataFrame:
    """Events as items of hourly tasks, by value."""
    return events.select(
        F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH").alias("task_id"), F.col("event_id").alias("item_id"), F.col("event_id").cast("int").alias("pos"), F.col("event_type").alias("key"), F.round(F.col("value") * 1000).cast("bigint").alias("lat")
    )


def stream_topk(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """(task_id, item_id, rnk): the k events of the largest value in each hour, after the whole stream."""
    top = RunningTopK(spark, k)
    q = event_items(read_events(spark, sf_dir)).writeStream.foreachBatch(top).trigger(availableNow=True).option("checkpointLocation", top.scratch.path("checkpoint")).start()
    q.awaitTermination()
    return top.state().select("task_id", "item_id", "rnk")


#: The instant of the row that closes a bounded stream.
END = "2200-01-01 00:00:00"


def stream_sessions(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n) of sessions, each given once the watermark has passed it; late rows older than the watermark are dropped.

    The stream is bounded, so a last row far ahead (of no user) closes the sessions that are open at its end; its own is never given.
    """
    scratch = Scratch(spark, "sessions")
    e = read_events(spark, sf_dir).select("user_id", "ts")
    last = spark.range(1).select(F.lit(None).cast(e.schema["user_id"].dataType).alias("user_id"), F.lit(END).cast("timestamp").alias("ts"))
    last.write.mode("overwrite").parquet(scratch.path("last"))
    e = e.unionByName(spark.readStream.schema(e.schema).parquet(scratch.path("last"))).withWatermark("ts", "1 hour")
    s = e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")
    out: dict[int, DataFrame] = {}

    def keep(batch: DataFrame, n: int) -> None:
        out[n] = scratch.write(f"batch{n}", batch)

    s.writeStream.outputMode("append").foreachBatch(keep).trigger(availableNow=True).option("checkpointLocation", scratch.path("checkpoint")).start().awaitTermination()
    every = spark.createDataFrame([], s.schema)
    for n in sorted(out):
        every = every.unionByName(out[n])
    return every


def score_stream(items: DataFrame, backend: ModelBackend | None = None, max_point: int = 10) -> DataFrame:
    """Stateless pointwise scores on a stream; repeated items within the watermark should be dropped before (dropDuplicatesWithinWatermark)."""
    from semrank.operators.sql import semantic_score

    score = semantic_score(items.sparkSession, backend, max_point)
    return items.withColumn("score", score(F.col("task_id"), F.col("item_id"), F.col("key"), F.col("lat")))
