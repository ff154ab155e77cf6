"""The one place where wave jobs talk to a model: requests in, responses out, each paid once.

requests:  req_hash, task_id, path_id, wave, op, keys array<struct<item_id, chars, lat, fact, text>>, extra (batch number)
responses: req_hash, reply array<bigint>, in_tok, out_tok, lookups, repairs

Cached responses are joined, misses are sent in Arrow batches, and the wave is written before anyone reads it. Requests are spread evenly, not
by segment, so a hot task keeps all workers busy; a partition is one worker, which has as many calls in flight as the backend has threads,
so ``max_in_flight`` bounds the calls at once, and a provider's limit per minute is dealt out to so many workers.
"""

from __future__ import annotations

import json
import math
from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec.packed import answer, request_key
from semrank.exec.scratch import Scratch, path_exists
from semrank.plans.spec import PathConfig
from semrank.sources.model import Key, ModelBackend, each

KEYS = "array<struct<item_id:bigint,chars:int,lat:bigint,fact:bigint,text:string>>"
RESPONSES = "req_hash string, reply array<bigint>, in_tok bigint, out_tok bigint, lookups bigint, repairs bigint"


def key_struct() -> Column:
    """Of columns as ``packed.shown`` gives them."""
    return F.struct(F.col("item_id").cast("bigint").alias("item_id"), "chars", "lat", "fact", "text")


def request_hash(op: str | Column, keys: Column, *more: Column) -> Column:
    """Of everything that decides the reply; ``more`` holds the backend's identity and the path's settings."""
    return F.sha2(F.to_json(F.struct(F.lit(op) if isinstance(op, str) else op, F.col("task_id"), keys.alias("keys"), *[c.cast("string").alias(f"m{i}") for i, c in enumerate(more)])), 256)


class ResponseCache:
    """Responses by request hash, in folders by the hash's first digit."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def read(self) -> DataFrame:
        if path_exists(self.spark, self.path):
            return self.spark.read.schema(RESPONSES + ", head string").parquet(self.path).drop("head")
        return self.spark.createDataFrame([], RESPONSES)

    def append(self, responses: DataFrame) -> None:
        responses.withColumn("head", F.substring("req_hash", 1, 1)).write.mode("append").partitionBy("head").parquet(self.path)


def _request(op: str, keys, extra) -> tuple:
    """A request as ``packed.answer`` takes it."""
    made = [Key(int(k["item_id"]), int(k["chars"]), int(k["lat"]), None if k["fact"] is None else int(k["fact"]), k["text"]) for k in keys]
    return (op, int(extra), *made) if op == "score_many" else (op, *made)


def _reusing(requests: DataFrame, path: PathConfig, backend: ModelBackend, scratch: Scratch, name: str, max_in_flight: int, known: DataFrame) -> DataFrame:
    """``call_model`` where packed runs have asked some requests: those are found by the packed runs' hash and are not asked again."""

    def named(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            req = [request_key(backend, t, _request(op, keys, extra), path) for t, op, keys, extra in zip(f["task_id"], f["op"], f["keys"], f["extra"], strict=True)]
            yield f[["req_hash", "task_id"]].assign(req=req)

    names = requests.select("req_hash", "task_id", "op", "keys", "extra").mapInPandas(named, "req_hash string, task_id string, req string")
    # at most a sample's requests per task: Catalyst broadcasts them while they are few
    had = scratch.write(f"{name}-known", names.join(known.select("task_id", "req", "reply").dropDuplicates(["task_id", "req"]), ["task_id", "req"]).select("req_hash", "reply").dropDuplicates(["req_hash"]))
    asked = call_model(requests.join(had.select("req_hash"), "req_hash", "left_anti"), path, backend, scratch, f"{name}-new", max_in_flight=max_in_flight)

    def read(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            replies = [json.loads(x) for x in f["reply"]]
            yield pd.DataFrame({"req_hash": f["req_hash"], "reply": [r if isinstance(r, list) else [r] for r in replies], **dict.fromkeys(("in_tok", "out_tok", "lookups", "repairs"), 0)})

    return asked.unionByName(had.mapInPandas(read, RESPONSES).withColumn("hit", F.lit(True)))


def call_model(requests: DataFrame, path: PathConfig, backend: ModelBackend, scratch: Scratch, name: str, *, cache: ResponseCache | None = None, max_in_flight: int = 100, known: DataFrame | None = None) -> DataFrame:
    """Responses to all requests, written once; with a cache or replies ``known`` from packed runs, ``hit`` tells which were not paid again."""
    requests = scratch.write(f"{name}-requests", requests)
    if known is not None:
        if cache:
            raise ValueError("a cache or known replies, not both")
        return _reusing(requests, path, backend, scratch, name, max_in_flight, known)
    known = cache.read() if cache else None
    todo = requests if known is None else requests.join(known.select("req_hash"), "req_hash", "left_anti")
    # equal requests within a wave are asked once
    workers = max(1, math.floor(max_in_flight / backend.threads))
    todo = todo.dropDuplicates(["req_hash"]).repartition(workers, "req_hash")
    limit = getattr(backend, "per_minute", None)
    model = replace(backend, per_minute=limit / workers) if limit else backend

    def one(row: tuple) -> tuple:
        h, task, op, keys, extra = row
        reply, used, repairs = answer(model, task, _request(op, keys, extra), path)
        return h, reply if isinstance(reply, list) else [reply], used.in_tok, used.out_tok, used.lookups, repairs

    def ask(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = each(model, one, list(zip(f["req_hash"], f["task_id"], f["op"], f["keys"], f["extra"], strict=True)))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in RESPONSES.split(", ")])

    got = scratch.write(f"{name}-responses", todo.select("req_hash", "task_id", "op", "keys", "extra").mapInPandas(ask, RESPONSES))
    if cache is None:
        return got.withColumn("hit", F.lit(False))
    hits = scratch.write(f"{name}-hits", known.join(requests.select("req_hash").distinct(), "req_hash"))
    cache.append(got)
    return got.withColumn("hit", F.lit(False)).unionByName(hits.withColumn("hit", F.lit(True)))
