"""Sliding windows whose lists are answered at once, against those that ask one by one."""

import random
import time

import pytest

from semrank.exec import packed
from semrank.exec.packed import run_path
from semrank.plans.complexity import exact_calls
from semrank.plans.spec import EXT_BUBBLE, PathConfig
from semrank.sources.model import Key, SimBackend


def keys_for(n, seed):
    r = random.Random(seed)
    return [Key(i, r.randrange(1, 90), r.choice([5, r.randrange(10001)])) for i in r.sample(range(100_000), n)]


@pytest.mark.parametrize("m", [2, 3, 4, 5, 7, 8])
@pytest.mark.parametrize("more", [{}, {"rescan": True}, {"stop_when_stable": True}, {"rescan": True, "stop_when_stable": True}])
def test_same_ranking_calls_and_tokens(monkeypatch, m, more):
    monkeypatch.setattr(packed, "LEAST", 1)
    path = PathConfig("slide_window", m=m, **more)
    for n in (1, 2, 3, m - 1, m, m + 1, 2 * m, 2 * m + 1, 37, 64, 65):
        for k in (None, 0, 1, 3, 10):
            for sim in (SimBackend().about("c", True), SimBackend().about("", False), SimBackend(reasoning=True)):
                keys = keys_for(n, n)
                for given in (keys, sorted(keys, key=lambda x: (-x.latent, x.item_id))):
                    want, usage = run_path(given, path, k, sim, "t")
                    got, summed = run_path(given, path, k, sim, "t", by_wave=False)
                    assert got == want
                    assert [u[:6] for u in summed.values()] == ([[sum(u[i] for u in usage.values()) for i in range(6)]] if usage else [])


def test_a_long_chain_makes_all_its_calls_in_time():
    """Before, some 12 microseconds a call: a minute and more."""
    keys, n = keys_for(7000, 3), 7000
    t = time.time()
    ranked, usage = run_path(keys, EXT_BUBBLE, None, SimBackend(), "t", by_wave=False)
    assert time.time() - t < 15
    assert ranked == [x.item_id for x in sorted(keys, key=lambda x: (-x.latent, x.item_id))]
    assert usage["order", None][0] == exact_calls(EXT_BUBBLE, n, None)


def test_a_large_partition_takes_its_sliding_window(spark):
    """Before, an error beyond 5,000 rows; keys that are null stay out and come last."""
    from pyspark.sql import functions as F

    from semrank.operators.frame import llm_order_by

    d = spark.range(5600).select("id", (F.col("id") % 2 * (F.col("id") < 300).cast("int")).alias("p"), F.when(F.col("id") % 13 == 0, F.lit(None)).otherwise(F.lit("k")).alias("k"), (F.col("id") * 7919 % 997).alias("lat"))
    for desc in (True, False):
        got = llm_order_by(d, "k", "good", id_col="id", latent="lat", partition_by="p", desc=desc, path=EXT_BUBBLE).collect()
        want = {}
        for r in sorted(got, key=lambda r: (r.k is None, 0 if r.k is None else -r.lat if desc else r.lat, r.id)):
            want.setdefault(r.p, []).append(r.id)
        assert len(got) == 5600 and all(want[r.p][r.rnk - 1] == r.id for r in got)


@pytest.mark.parametrize("m", [2, 3, 4, 5])
@pytest.mark.parametrize("top", [40, 1000, 2_000_000])
def test_noise_of_many_lists_is_that_of_each(monkeypatch, m, top):
    monkeypatch.setattr(packed, "LEAST", 1)
    r = random.Random(top)
    for n in (1, m, m + 1, 2 * m + 1, 38):
        for k, more in ((None, {}), (3, {}), (None, {"rescan": True}), (None, {"stop_when_stable": True})):
            for sim in (SimBackend("reasoning"), SimBackend("factual", "small").about("c", False)):
                keys = [Key(i, r.randrange(1, 90), r.choice([5, r.randrange(10001)])) for i in r.sample(range(top), n)]
                for task in ("w1-3", "t" * 9, "a task of a name as long as this, which takes a second block"):
                    path = PathConfig("slide_window", m=m, **more)
                    want, usage = run_path(keys, path, k, sim, task)
                    got, summed = run_path(keys, path, k, sim, task, by_wave=False)
                    assert got == want
                    assert [u[:6] for u in summed.values()] == ([[sum(u[i] for u in usage.values()) for i in range(6)]] if usage else [])


def test_a_long_noisy_chain_in_time():
    """Before, some 26 microseconds a call: nearly a minute."""
    keys, t = keys_for(4000, 5), time.time()
    usage = run_path(keys, EXT_BUBBLE, None, SimBackend("reasoning"), "w1-3", by_wave=False)[1]
    assert time.time() - t < 15
    assert usage["order", None][0] == exact_calls(EXT_BUBBLE, 4000, None)
