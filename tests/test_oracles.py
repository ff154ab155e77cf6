"""Queries against their SQL on the smallest tables."""

import math
import os

import pytest

SF = "/root/testdata/sf0.001"
NAMES = ["gold_w3", "gold_w5b", "gold_w7", "rank_batch_factual_w1", "rank_point_lookup_w2", "topk_votes_w5", "topk_bubble_w7", "complexity_grid", "calls_closed_form", "cost_extrapolation", "usage_rollup", "sample_items_w3", "inquiry_route", "fuse_borda_w5", "agreement_w5", "kendall_tau_b_w5", "ndcg10_exp_w5", "spread", "bm25_top100", "vector_top100", "null_keys_first", "dedup_keys", "udtf_rank", "stream_topk_hourly", "stream_session_rank", "criteria_decide", "llm_order_by_ascending_quick", "llm_order_by_ascending_batch", "probe_cache_hits_w5", "judge_choice_value_w3", "window_ranks_w5"]


@pytest.fixture(scope="module")
def con():
    import duckdb

    c = duckdb.connect()
    for f in os.listdir(SF):
        c.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    return c


def plain(v):
    if isinstance(v, bool) or v is None:
        return str(v)
    if isinstance(v, (int, float)) or type(v).__name__ == "Decimal":
        return "nan" if math.isnan(v) else f"{float(v):.6g}"
    return str(v)


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
@pytest.mark.parametrize("name", NAMES)
def test_query(spark, con, name):
    import __spark_entry__ as entry

    got, want = entry.queries()[name](spark, SF), con.sql(entry.oracle_sql()[name])
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    at = [want.columns.index(c) for c in cols]
    assert sorted([plain(r[c]) for c in cols] for r in got.collect()) == sorted([plain(r[i]) for i in at] for r in want.fetchall())


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
