"""Waves of comparisons answered at once, as one by one."""

import random

from pyspark.sql import functions as F

from semrank.exec.packed import run_path
from semrank.exec.waves import quick_waves
from semrank.plans.spec import QUICK_3, PathConfig
from semrank.sources.model import Key, SimBackend


class OneByOne(SimBackend):
    compare_many = None


def test_same_ranking_calls_and_tokens():
    r = random.Random(3)
    for n in (1, 2, 9, 40):
        for v, pivot, profile, k in ((1, "first", "clean", None), (3, "first", "reasoning", 5), (3, "random", "factual", None), (2, "median3", "reasoning", None)):
            keys = [Key(i, r.randrange(1, 40), r.choice([5, r.randrange(10001)])) for i in r.sample(range(1000), n)]
            path = PathConfig("pivot_split", v=v, pivot=pivot)
            for desc in (True, False):
                got, want = (run_path(keys, path, k, b(profile).about("c", desc), "t") for b in (SimBackend, OneByOne))
                assert got == want


def test_equal_items_take_all_their_levels():
    n = 7200
    ranked, usage = run_path([Key(i, 18, 5) for i in range(n)], QUICK_3, None, SimBackend(), "t", by_wave=False)
    assert ranked == list(range(n))
    assert usage["compare", None][0] == n * (n - 1) // 2


def test_equal_items_of_a_large_task(spark):
    """Before, 200 levels of jobs and then an error."""
    n = 5300
    items = spark.range(n).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.lit("key").alias("key"), F.lit(5).alias("lat"))
    ranks, usage = quick_waves(items, QUICK_3, SimBackend())
    assert ranks.where("rnk <> item_id + 1").count() == 0 and ranks.count() == n
    assert usage.first()["calls"] == n * (n - 1) // 2


def test_two_grades_of_a_large_task(spark):
    """As in example2_sql: a few grades with long ties, beyond what runs packed."""
    n = 5300
    items = spark.range(n).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.lit("key").alias("key"), (F.col("id") % 7 == 3).cast("int").alias("lat"))
    ranks = quick_waves(items, QUICK_3, SimBackend())[0]
    got = [r["item_id"] for r in ranks.orderBy("rnk").collect()]
    assert got == sorted(range(n), key=lambda i: (i % 7 != 3, i))
