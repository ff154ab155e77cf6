"""Queries against their SQL on the smallest tables."""

import os

import pytest

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["op1_token_counts", "op3_line_dedup", "op4_quality_rules", "op5_near_duplicates", "op6_mixing", "op8_license_scan", "op10_fingerprints"])
def test_query(spark, name):
    import duckdb

    from semrank.llm.queries import QUERIES, oracles

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    got, want = QUERIES[name](spark, SF), con.sql(oracles()[name])
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    at = [want.columns.index(c) for c in cols]
    show = lambda v: f"{v:.9g}" if isinstance(v, float) else str(v)
    assert sorted([show(r[c]) for c in cols] for r in got.collect()) == sorted([show(r[i]) for i in at] for r in want.fetchall())
