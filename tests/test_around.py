import random

import pytest
from pyspark.sql import functions as F

from semrank.exec.replies import fit_batch, parse_orders
from semrank.exec.split import split_merge
from semrank.operators.relational import as_of_join, interval_join, rank_by_many
from semrank.operators.retrieval import bm25_topn, vector_topn
from semrank.operators.sql import sem_extract, sem_filter, sem_join, semantic_score
from semrank.sources.model import SimBackend


def test_as_of(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c"), (None, 3, "d")], "k int, t int, x string")
    right = spark.createDataFrame([(1, 2, 10), (1, 5, 20), (1, 5, 15), (2, 10, 30), (1, 6, None)], "k int, t int, v int")
    got = {r.x: r.p for r in as_of_join(left, right, "k", "t", "v", "p").collect()}
    assert got == {"a": 20, "b": None, "c": None, "d": None}


def test_interval_join_against_all_pairs(spark):
    rng = random.Random(2)
    rows = [(i, rng.randrange(4), rng.randrange(4000)) for i in range(120)]
    d = spark.createDataFrame(rows, "id int, k int, s int").withColumn("t", F.timestamp_seconds("s"))
    got = sorted((r.id, r.r_id) for r in interval_join(d, d, "k", "t", 300).select("id", "r_id").collect())
    assert got == sorted((i, j) for i, k, s in rows for j, l, u in rows if k == l and 0 < u - s <= 300)


def test_weights(spark):
    r = spark.createDataFrame([("t", p, i, n) for p, ids in (("a", [1, 2, 3]), ("b", [3, 2, 1])) for n, i in enumerate(ids, 1)], "task_id string, path_id string, item_id bigint, rnk bigint")
    assert [x.item_id for x in rank_by_many(r, {"a": 5, "b": 1}).orderBy("rnk").collect()] == [1, 2, 3]
    assert [x.item_id for x in rank_by_many(r, {"a": 1, "b": 5}).orderBy("rnk").collect()] == [3, 2, 1]


def test_replies(spark):
    d = spark.createDataFrame([(1, '{"order": [2, 1]}', [1, 2]), (2, None, [4]), (3, '{"order": [2, 2, 7]}', [1, 2])], "req_id int, reply string, shown array<bigint>")
    assert {r.req_id: (r.order, r.repaired) for r in parse_orders(d).collect()} == {1: ([2, 1], False), 2: ([4], True), 3: ([2, 1], True)}


def test_batches_fit(spark):
    d = spark.createDataFrame([("a", 100)] * 9 + [("b", 10**6)] * 3, "task_id string, chars int")
    assert {r.task_id: r.m for r in fit_batch(d, 8, 150).collect()} == {"a": 4, "b": 1}


@pytest.mark.parametrize("parts", [2, 5])
def test_split_sort(spark, parts):
    lats = random.Random(4).sample(range(10000), 150)
    d = spark.createDataFrame([("t", i, i, f"k{i}", x) for i, x in enumerate(lats)], "task_id string, item_id bigint, pos bigint, key string, lat bigint")
    got = [r.item_id for r in split_merge(d, SimBackend(), parts)[0].orderBy("rnk").collect()]
    assert got == sorted(range(150), key=lambda i: -lats[i])
    noisy = split_merge(d, SimBackend("reasoning"), parts)[0].collect()
    assert sorted(r.item_id for r in noisy) == list(range(150)) and sorted(r.rnk for r in noisy) == list(range(1, 151))


def test_semantic_functions(spark):
    d = spark.createDataFrame([("t", 1, "good", 9000), ("t", 2, "bad", 100)], "task_id string, item_id bigint, key string, lat bigint")
    score = semantic_score(spark)("task_id", "item_id", "key", "lat")
    assert [r.item_id for r in sem_filter(d, score, 5).collect()] == [1]
    assert [r.extracted for r in sem_extract(d, "key", lambda ts: [len(t) for t in ts], "int").orderBy("item_id").collect()] == [4, 3]
    q = spark.createDataFrame([("good",), ("ugly",)], "word string")
    assert [(r.word, r.item_id) for r in sem_join(q, d, lambda f: f["word"] == f["key"]).collect()] == [("good", 1)]
    with pytest.raises(ValueError, match="narrow it"):
        sem_join(q, d, lambda f: f["word"] == f["key"], most_left=1)


def test_retrieval_edges(spark):
    docs = spark.createDataFrame([(1, "alpha beta"), (2, None), (3, ""), (4, "Alpha, ALPHA gamma")], "doc_id bigint, text string")
    q = spark.createDataFrame([(7, "alpha"), (8, "delta")], "query_id bigint, text string")
    assert [(r.query_id, r.doc_id, r.rnk) for r in bm25_topn(docs, q, 5).orderBy("rnk").collect()] == [(7, 4, 1), (7, 1, 2)]
    v = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0]), (3, [1.0, 0.1])], "vec_id bigint, embedding array<float>")
    assert [r.vec_id for r in vector_topn(v, v.where("vec_id = 1"), 2).orderBy("rnk").collect()] == [3, 2]
    pairs = lambda d: sorted((r.query_id, r.vec_id, r.rnk) for r in d.collect())
    assert pairs(vector_topn(v, v, 2, most=2)) == pairs(vector_topn(v, v, 2))
