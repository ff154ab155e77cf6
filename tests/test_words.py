"""Words cut on Arrow's buffers, as Spark's split gives them."""

import os
import random

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from semrank.functions import words as W
from semrank.operators import retrieval
from semrank.sources import tables as T

SF = "/root/testdata/sf0.001"


def test_words_are_those_of_a_split(spark, monkeypatch):
    r = random.Random(1)
    letters = [*"abcXYZ 019_-.,\n\t\0", "é", "ß", "İ", "Σ", "中", "文", "ª", "½", "😀", "𝔸", "𐐀", "٣", "̀", "－", "ⅷ"]
    texts = ["".join(r.choices(letters, k=r.randrange(40))) for _ in range(600)] + [None, "", "a", "中", "😀"]
    rows = spark.createDataFrame(list(enumerate(texts)), "id int, t string").select("id", F.lower("t").alias("t"), retrieval.terms(F.col("t")).alias("w")).orderBy("id").collect()
    every = sorted({w for x in rows for w in x["w"] or []})
    number = {w: i for i, w in enumerate(every[::2])}
    edges = W.word_edges(spark)
    for piece in (10**6, 50, 1):
        monkeypatch.setattr(W, "PIECE", piece)
        got, low = [], pa.array([x["t"] for x in rows])
        for part in (low[:200], low[200:]):
            for _, _, lengths, found in W.Words(edges, list(number)).pieces(part):
                for n in lengths:
                    got.append(found[:n].tolist())
                    found = found[n:]
        assert got == [[number.get(w, -1) for w in x["w"] or []] for x in rows]


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_only_the_first_stage_is_graded(spark, monkeypatch):
    """Before, pairs were counted in all documents, most of which no query has among its best."""
    want = sorted(map(tuple, T.gold_w3(spark, SF, 2).collect()))
    seen, graded = [], T.coverage
    monkeypatch.setattr(T, "coverage", lambda s, d, **more: seen.append(more["docs"]) or graded(s, d, **more))
    got = sorted(map(tuple, T.gold_w3(spark, SF, 2).collect()))
    every = T.load(spark, SF, "documents")
    assert got == want and {x[1] for x in got} == {x["doc_id"] for x in seen[0].collect()} and seen[0].count() < every.count()
    share = {(q, i): x for q, i, x in graded(spark, SF).collect()}
    grade = lambda x: 3 if x >= 0.95 else 2 if x >= 0.10 else 1 if x >= 0.05 else 0
    assert all(g == grade(share.get((int(t[3:]), i), 0.0)) for t, i, _, g, _ in got)
