"""Grids, curves and replies come from the given tables, with the SQL's results."""

import os

import pytest
from test_oracles import SF, con, plain  # noqa: F401

NAMES = ["calls_closed_form", "candidate_grid", "complexity_grid", "cost_extrapolation", "dips", "greedy_fit_skip", "greedy_fit_stop", "leaderboard", "log_fit", "pareto", "reply_repair"]


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, con, name):  # noqa: F811
    import __spark_entry__ as entry

    sql = entry.oracle_sql()[name]
    assert any(f"FROM {t}" in sql for t in ("customer", "supplier", "documents", "conversations"))
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, "/root/testdata/none").collect()
    got, want = entry.queries()[name](spark, SF), con.sql(sql)
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    at = [want.columns.index(c) for c in cols]
    rows = sorted([plain(r[c]) for c in cols] for r in got.collect())
    assert rows and rows == sorted([plain(r[i]) for i in at] for r in want.fetchall())
