"""Merges whose lists are answered at once, against those that ask one by one."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from semrank.exec import merges, waves
from semrank.exec.packed import run_path
from semrank.exec.split import split_merge
from semrank.exec.waves import merge_waves
from semrank.plans.spec import EXT_MERGE, PathConfig
from semrank.sources.model import Key, SimBackend


@pytest.mark.parametrize("wide", [1, 5, 10**9])
@pytest.mark.parametrize("m", [2, 3, 4, 8])
@pytest.mark.parametrize("descending", [True, False])
def test_same_result_and_calls_as_packed(monkeypatch, wide, m, descending):
    monkeypatch.setattr(merges, "WIDE", wide)
    rng, sim, path = random.Random(m), SimBackend().about("c", descending), PathConfig("run_merge", m)
    for n in (1, 2, m, m + 1, 37, 200, 333):
        for k in (None, 1, 3, 10, 150):
            keys = [Key(i, rng.randrange(40), rng.randrange(60)) for i in rng.sample(range(1000), n)]
            want, usage = run_path(keys, path, k, sim, "t")
            orders = sim.orders("t", *[np.array([getattr(x, c) for x in keys], dtype=np.int64) for c in ("item_id", "latent", "chars")])
            got = merges.merge_all(n, m, k, orders)
            assert [keys[p].item_id for p in got] == want
            if n > 1:
                assert (orders.calls, orders.in_tok, orders.out_tok) == tuple(sum(u[i] for u in usage.values()) for i in range(3))


def test_noise_is_not_answered_at_once():
    none = np.zeros(0, dtype=np.int64)
    assert SimBackend("reasoning").orders("t", none, none, none) is None


@pytest.fixture
def plain():
    """The simulator without what answers many requests at once; a local class, as workers do not see this file."""

    class OneByOne(SimBackend):
        compare_many = orders = property()

    return OneByOne()


@pytest.mark.parametrize("k", [None, 7])
def test_waves_and_splits_as_one_by_one(spark, plain, k):
    items = spark.range(700).select(F.lit("t").alias("task_id"), F.col("id").alias("item_id"), F.col("id").cast("int").alias("pos"), F.repeat(F.lit("x"), (F.col("id") % 7 + 1).cast("int")).alias("key"), (F.col("id") * 37 % 101).alias("lat"))
    assert not hasattr(plain, "orders")
    for run in (lambda b: merge_waves(items, EXT_MERGE, b, k, local=4), *([] if k else [lambda b: split_merge(items, b, 5)])):
        got, want = ([sorted(map(tuple, d.collect())) for d in run(b)] for b in (SimBackend(), plain))
        assert got == want


def test_splitters_travel_where_they_are_many(spark, monkeypatch):
    items = spark.range(300).select(F.format_string("t%d", F.col("id") % 3).alias("task_id"), F.col("id").alias("item_id"), F.floor(F.col("id") / 3).cast("int").alias("pos"), F.lit("xx").alias("key"), (F.col("id") * 37 % 101).alias("lat"))
    few = [sorted(map(tuple, d.collect())) for d in split_merge(items, SimBackend(), 4)]
    monkeypatch.setattr("semrank.exec.split.MOST_CUTS", 0)
    assert [sorted(map(tuple, d.collect())) for d in split_merge(items, SimBackend(), 4)] == few


def test_a_block_of_lists_at_once_is_large():
    assert waves.LOCAL_AT_ONCE > waves.LOCAL
