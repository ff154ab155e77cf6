"""The first stage by numbers in a task, as by joins."""

import os

import pytest

from semrank.operators import retrieval
from semrank.sources import tables as T

SF = "/root/testdata/sf0.001"


def test_bm25_by_matrix(spark, monkeypatch):
    docs = spark.createDataFrame([(i, None if i == 7 else "" if i == 8 else " ".join(f"w{(i * j) % 11}" for j in range(1 + i % 6))) for i in range(40)], "doc_id long, text string")
    q = spark.createDataFrame([(1, "w1 w2 w2"), (2, "W4, w0"), (3, "nowhere")], "query_id long, text string")
    want = sorted(map(tuple, retrieval.bm25_topn(docs, q, 5, most=0).collect()))
    # before, all of it went by joins
    monkeypatch.setattr(retrieval, "_by_joins", None)
    assert want and sorted(map(tuple, retrieval.bm25_topn(docs, q, 5).collect())) == want


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_coverage_by_number(spark):
    got, want = (sorted(map(tuple, T.coverage(spark, SF, most=m).collect())) for m in (T.MOST_PAIRS, 0))
    assert want and got == want
