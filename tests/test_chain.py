"""Long chains of calls: usage by operation, paths together in one worker, keys without their texts."""

import random

from pyspark.sql import functions as F

from semrank.exec.packed import rankings_of, run_path, run_paths, slim, usage_of
from semrank.plans.spec import EXT_BUBBLE, EXT_MERGE, POINT, QUICK_3
from semrank.sources.model import Key, SimBackend

PATHS = [POINT, QUICK_3, EXT_BUBBLE, EXT_MERGE]


def test_usage_summed():
    keys = [Key(i, 5 + i % 3, x) for i, x in enumerate(random.Random(3).sample(range(90), 90))]
    for path in PATHS:
        apart, waves = run_path(keys, path, 10, SimBackend("reasoning"), "t")
        summed, usage = run_path(keys, path, 10, SimBackend("reasoning"), "t", by_wave=False)
        assert summed == apart and {w for _, w in usage} == {None} and len(usage) == 1
        assert next(iter(usage.values())) == [sum(x) for x in zip(*waves.values(), strict=True)]


def test_together_and_slim(spark):
    items = spark.range(120).select(F.concat(F.lit("t"), F.col("id") % 2).alias("task_id"), F.col("id").alias("item_id"), F.floor(F.col("id") / 2).alias("pos"), F.format_string("key %d", "id").alias("key"), (F.col("id") * 37 % 101).alias("lat"))
    backend = SimBackend("reasoning")
    want, got = run_paths(items, PATHS, backend), run_paths(slim(items, backend), PATHS, backend, by_wave=False, together=True)
    rows = lambda d: sorted(map(tuple, d.collect()))
    assert rows(rankings_of(got)) == rows(rankings_of(want))
    # a chain has one usage row, not one per call
    assert usage_of(got).where("path_id = 'ext_bubble_4'").count() == 2 < usage_of(want).where("path_id = 'ext_bubble_4'").count()
    total = lambda d: rows(usage_of(d).groupBy("task_id", "path_id", "op").agg(*[F.sum(c) for c in ("calls", "in_tok", "out_tok", "nano_usd")]))
    assert total(got) == total(want)
    # keys that are not asked about stay out
    odd = items.withColumn("key", F.when(F.col("item_id") % 5 == 0, F.lit(None)).when(F.col("item_id") % 7 == 0, F.lit("")).otherwise(F.col("key")))
    assert slim(odd, backend).where("key is null").count() == 24 and slim(odd, backend).where("key = ''").count() == 14


def test_large_tasks_of_a_study(spark):
    """Beyond packed_max a study runs in waves, with the packed run's rankings and spending; keys that are empty leave no gap."""
    from semrank.exec.scratch import Scratch
    from semrank.plans.optimizer import run_static
    from semrank.plans.spec import EXT_POINT

    items = spark.range(150).select(F.when(F.col("id") < 120, "large").otherwise("small").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.when(F.col("id") % 11 == 3, "").otherwise(F.format_string("key %d", "id")).alias("key"), (F.col("id") * 37 % 101).alias("lat"), F.lit(10).cast("bigint").alias("k"))
    backend, paths = SimBackend("reasoning"), [POINT, EXT_POINT, *PATHS[1:]]
    want, got = run_paths(items, paths, backend), run_static(items, paths, backend, Scratch(spark, "t"), packed_max=50)
    rows = lambda d: sorted(map(tuple, d.collect()))
    assert rows(rankings_of(got)) == rows(rankings_of(want))
    total = lambda d: rows(usage_of(d).where("path_id <> 'quick_3'").groupBy("task_id", "path_id").agg(*[F.sum(c) for c in ("calls", "in_tok", "out_tok", "nano_usd")]))
    assert total(got) == total(want)


def test_probe_replies_in_waves(spark):
    """A task beyond packed_max does not pay its probe's scores again either."""
    from semrank.plans import optimizer as O
    from semrank.plans.spec import EXT_POINT

    items = spark.range(90).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.format_string("key %d", "id").alias("key"), (F.col("id") * 37 % 101).alias("lat"), F.lit(None).cast("bigint").alias("k"))
    tasks = items.select("task_id").distinct().select("task_id", F.lit("reasoning").alias("kind"), F.lit(None).cast("bigint").alias("k"))
    for path, hits, calls in ((POINT, 20, 70), (EXT_POINT, None, None)):
        waves, packed = (O.optimize(items, tasks, 10**12, SimBackend("reasoning"), inquiry=False, candidates=[path], packed_max=n) for n in (30, 5000))
        ledger = lambda r: [tuple(x) for x in r.ledger.where("phase = 'ranking'").select("hits", "calls", "nano_usd").collect()]
        assert ledger(waves) == ledger(packed)
        assert hits is None or ledger(waves)[0][:2] == (hits, calls)
        assert sorted(map(tuple, waves.ranking.collect())) == sorted(map(tuple, packed.ranking.collect()))
