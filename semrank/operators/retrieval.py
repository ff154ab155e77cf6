"""Narrowing before a semantic sort: BM25, vectors, a light proxy ranker."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.index import placed_by
from semrank.exec.scratch import Scratch
from semrank.functions.words import NOT_WORD, Words, word_edges

K1, B = 0.9, 0.4


def terms(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), NOT_WORD), lambda x: x != "")


def bm25_topn(corpus: DataFrame, queries: DataFrame, n: int = 100, k1: float = K1, b: float = B, most: int | None = None) -> DataFrame:
    """(query_id, doc_id, score, rnk): each query's n best documents; ties (scores rounded to 6 places) by id.

    One pass over the corpus: documents are cut to the terms that some query has and written as postings, from which document
    frequencies and scores are derived; lengths come along on a row per document. While terms x queries are at most ``most`` numbers, a document's
    postings stay on its row and scores are products of matrices, of which each task hands on the rows that can be among its n best; beyond that, or if ids
    repeat, postings and queries meet by joins. The window keeps n rows per query on each partition first (WindowGroupLimit).
    """
    scratch, most = Scratch(corpus.sparkSession, "bm25"), MOST_NUMBERS if most is None else most
    q = scratch.write("queries", queries.select("query_id", F.explode(F.array_distinct(terms(F.col("text")))).alias("term")))
    sizes = q.agg(F.count_distinct("term"), F.count_distinct("query_id")).first()
    ids = corpus.agg(F.count("*"), F.count_distinct("doc_id")).first()
    if 0 < sizes[0] * sizes[1] <= most and ids[0] == ids[1]:
        s = _by_matrix(corpus, q, n, k1, b, scratch)
    else:
        s = _by_joins(corpus, q, k1, b, scratch)
    w = W.partitionBy("query_id").orderBy(F.col("score").desc(), "doc_id")
    return s.withColumn("rnk", F.row_number().over(w).cast("bigint")).where(F.col("rnk") <= n)


def _by_joins(corpus: DataFrame, q: DataFrame, k1: float, b: float, scratch: Scratch) -> DataFrame:
    """All (query_id, doc_id, score)."""
    d = corpus.select("doc_id", terms(F.col("text")).alias("w")).select("doc_id", F.size("w").alias("dl"), "w")
    # an empty term marks the document itself, so that documents without a wanted term are counted too
    wanted = q.select("term").distinct().unionByName(q.sparkSession.createDataFrame([("",)], "term string"))
    tf = d.select("doc_id", "dl", F.explode(F.concat(F.array(F.lit("")), F.coalesce("w", F.array().cast("array<string>")))).alias("term")).join(wanted, "term")
    tf = scratch.write("postings", tf.groupBy("term", "doc_id", "dl").agg(F.count("*").alias("tf")))
    whole = tf.where("term = ''").agg(F.count("*").alias("docs"), F.avg("dl").alias("avgdl"))
    tf = tf.where("term <> ''")
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    idf = F.ln(1 + (F.col("docs") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    part = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("dl") / F.col("avgdl")))
    s = tf.join(df, "term").crossJoin(F.broadcast(whole)).select("term", "doc_id", part.alias("part"))  # one row
    return s.join(q, "term").groupBy("query_id", "doc_id").agg(F.round(F.sum("part"), 6).alias("score"))


#: Numbers of a block of documents by terms.
BLOCK = 2_000_000


def _by_matrix(corpus: DataFrame, q: DataFrame, n: int, k1: float, b: float, scratch: Scratch) -> DataFrame:
    """(query_id, doc_id, score) of each query's n best documents and some others; the caller has checked how many terms and queries there are."""
    spark = corpus.sparkSession
    rows = q.distinct().collect()
    words, names = sorted({r["term"] for r in rows}), list(dict.fromkeys(r["query_id"] for r in rows))
    at, of = {t: i for i, t in enumerate(words)}, {x: i for i, x in enumerate(names)}
    has = np.zeros((len(words), len(names)))
    for r in rows:
        has[at[r["term"]], of[r["query_id"]]] = 1.0
    size, edges = len(words), word_edges(spark)

    def post(batches):
        cut = Words(edges, words)
        for x in batches:
            texts = x.column("text")
            for lo, hi, lengths, term in cut.pieces(texts):
                row = np.repeat(np.arange(hi - lo, dtype=np.int64), lengths)
                key, tf = np.unique((row * size + term)[term >= 0], return_counts=True)
                ends = pa.array(np.searchsorted(key // size, np.arange(hi - lo + 1)).astype(np.int32))
                made = [pa.ListArray.from_arrays(ends, pa.array(v.astype(np.int32))) for v in (key % size, tf)]
                dl = pa.array(lengths.astype(np.int32), mask=texts.slice(lo, hi - lo).is_null().to_numpy(zero_copy_only=False))
                yield pa.RecordBatch.from_arrays([x.column("doc_id").slice(lo, hi - lo), dl, *made], ["doc_id", "dl", "terms", "tfs"])

    kind = corpus.schema["doc_id"].dataType.simpleString()
    d = corpus.select("doc_id", F.lower("text").alias("text"))
    posted = scratch.write("posted", d.mapInArrow(post, f"doc_id {kind}, dl int, terms array<int>, tfs array<int>"))
    docs, avgdl = posted.agg(F.count("*"), F.avg("dl")).first()
    df = np.zeros(size)
    for r in posted.select(F.explode("terms").alias("t")).groupBy("t").count().collect():  # a row per term
        df[r["t"]] = r["count"]
    idf = np.log(1 + (docs - df + 0.5) / (df + 0.5))

    def score(batches):
        best = np.zeros((0, len(names)))
        for x in batches:
            lengths = pc.list_value_length(x.column("terms")).to_numpy(zero_copy_only=False)
            term, tf = (x.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("terms", "tfs"))
            ends, dl = np.concatenate([[0], np.cumsum(lengths)]), pc.fill_null(x.column("dl"), 0).to_numpy(zero_copy_only=False)
            step = max(1, BLOCK // size)
            for lo in range(0, len(lengths), step):
                hi = min(lo + step, len(lengths))
                row, t, f = np.repeat(np.arange(hi - lo), lengths[lo:hi]), term[ends[lo] : ends[hi]], tf[ends[lo] : ends[hi]]
                block = np.zeros((hi - lo, size))
                block[row, t] = idf[t] * f * (k1 + 1) / (f + k1 * (1 - b + b * dl[lo:hi][row] / avgdl))
                found = block @ has
                best = np.concatenate([best, found])
                low = 0.0
                if len(best) > n:
                    best = -np.partition(-best, n - 1, axis=0)[:n]
                    # rounded to six places, a little less may be as good
                    low = best[n - 1] - 1e-5
                r, c = np.nonzero((found > 0) & (found >= low))
                yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int32)), x.column("doc_id").take(pa.array(r + lo)), pa.array(found[r, c])], ["_q", "doc_id", "score"])

    named = spark.createDataFrame(list(enumerate(names)), f"_q int, query_id {q.schema['query_id'].dataType.simpleString()}")
    found = posted.mapInArrow(score, f"_q int, doc_id {kind}, score double").withColumn("score", F.round("score", 6))
    return found.join(F.broadcast(named), "_q").select("query_id", "doc_id", "score")  # a row per query, checked above


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b)))


#: What may be broadcast: vectors of so many numbers in all.
MOST_NUMBERS = 4_000_000


def _against(vectors: DataFrame, few: DataFrame, column: str, most: int) -> DataFrame:
    """Every vector beside every row of ``few``, which holds an array ``column``: broadcast up to ``most`` numbers, beyond that in blocks of both."""
    numbers = few.agg(F.sum(F.size(column))).first()[0] or 0
    if numbers <= most:
        return vectors.crossJoin(F.broadcast(few))
    blocks = -(-numbers // most)
    spread = int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    a = vectors.withColumn("_b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("_s", F.pmod(F.xxhash64("vec_id"), F.lit(spread)).cast("int"))
    b = few.withColumn("_b", F.pmod(F.xxhash64(column), F.lit(blocks)).cast("int")).withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(spread - 1))))
    return a.join(b, ["_b", "_s"]).drop("_b", "_s")


def vector_topn(vectors: DataFrame, queries: DataFrame, n: int = 100, most: int = MOST_NUMBERS) -> DataFrame:
    """(query_id, vec_id, score, rnk) by cosine, the query itself left out: the stated query set against all vectors, exactly."""
    q = queries.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qe"))
    s = _against(vectors, q, "qe", most).where("vec_id <> query_id").select("query_id", "vec_id", F.round(cosine(F.col("embedding"), F.col("qe")), 6).alias("score"))
    w = W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return s.withColumn("rnk", F.row_number().over(w).cast("bigint")).where(F.col("rnk") <= n)


def proxy_rank(vectors: DataFrame, seeds: DataFrame, most: int = MOST_NUMBERS) -> DataFrame:
    """A light model fitted on a few scored items ranks all: items by cosine with the score-weighted centroid.

    ``seeds``: (task_id, vec_id, score). A task is one centroid row. A task of equal scores says nothing: its items go by id.
    """
    scratch = Scratch(vectors.sparkSession, "proxy")
    s = seeds.join(vectors, "vec_id").select("task_id", F.posexplode("embedding").alias("i", "x"), "score")
    mean = s.groupBy("task_id").agg(F.avg("score").alias("base"))
    c = s.join(mean, "task_id").groupBy("task_id", "i").agg(F.sum((F.col("score") - F.col("base")) * F.col("x")).alias("x"))
    c = scratch.write("centres", c.groupBy("task_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda e: e["x"]).alias("centre")))
    near = F.coalesce(F.round(cosine(F.col("embedding"), F.col("centre")), 6), F.lit(0.0))
    out = _against(vectors, c, "centre", most).select("task_id", F.col("vec_id").alias("item_id"), near.alias("score"))
    return placed_by(out.withColumn("_behind", -F.col("score")), ["_behind", "item_id"], scratch, "rnk").select("task_id", "item_id", "score", "rnk")
