"""Workloads on the given tables: items, truth, latent values.

A workload is (tasks, truth items): task_id, item_id, pos, key, grade. The simulator's latent value is the truth rank
scaled to 0..10000, ties broken by id so that a clean profile has one right order; it is never part of the key.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.functions.words import NOT_WORD, Words, word_edges
from semrank.sources.model import TOP, SimBackend


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_latent(items: DataFrame) -> DataFrame:
    """Adds lat: (place from behind) * 10000 div (n - 1), best grade first, the lower id before its equals."""
    w = W.partitionBy("task_id")
    behind = F.row_number().over(w.orderBy(F.col("grade"), F.col("item_id").desc())) - 1
    n = F.count("*").over(w)
    return items.withColumn("lat", F.when(n > 1, F.floor(behind * TOP / (n - 1))).otherwise(F.lit(0)).cast("bigint"))


def reverse(items: DataFrame) -> DataFrame:
    """For an ascending order: what was worst is best."""
    return items.withColumn("lat", TOP - F.col("lat"))


def _positions(items: DataFrame) -> DataFrame:
    return items.withColumn("pos", (F.row_number().over(W.partitionBy("task_id").orderBy("item_id")) - 1).cast("int"))


def gold_w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers by account balance in cents, a task per nation; the key is the name alone."""
    c = load(spark, sf_dir, "customer")
    return c.select(F.concat(F.lit("w1-"), "c_nationkey").alias("task_id"), F.col("c_custkey").cast("bigint").alias("item_id"), F.col("c_name").alias("key"), F.round(F.col("c_acctbal") * 100).cast("bigint").alias("grade"))


def gold_w2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations by the total price of their customers' orders, in cents."""
    n, c = load(spark, sf_dir, "nation"), load(spark, sf_dir, "customer")
    o = load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))
    by = c.join(o, c.c_custkey == o.o_custkey).groupBy("c_nationkey").agg(F.sum("cents").alias("cents"))
    return n.join(by, n.n_nationkey == by.c_nationkey, "left").select(
        F.lit("w2").alias("task_id"), F.col("n_nationkey").cast("bigint").alias("item_id"), F.col("n_name").alias("key"), F.coalesce("cents", F.lit(0)).cast("bigint").alias("grade")
    )


def bigrams(text: Column) -> Column:
    """Distinct neighbouring word pairs in lower case."""
    w = F.filter(F.split(F.lower(text), NOT_WORD), lambda x: x != "")
    pairs = F.transform(F.slice(w, F.lit(1), F.greatest(F.size(w) - 1, F.lit(0))), lambda x, i: F.concat(x, F.lit(" "), F.get(w, i + 1)))
    return F.array_distinct(pairs)


#: Benchmark items' word pairs are held in every task while they are so many at most.
MOST_PAIRS = 1_000_000


def coverage(spark: SparkSession, sf_dir: str, most: int = MOST_PAIRS, docs: DataFrame | None = None) -> DataFrame:
    """(query_id, doc_id, share) of a benchmark item's distinct word pairs that a document has; only pairs above 0.

    Documents' pairs are cut to those that any item has before they are counted, so only matches are shuffled. Up to ``most`` pairs of all items
    are looked up by number where a document's words are; more meet the documents by a join. ``docs`` are documents, if not all are wanted.
    """
    b = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("query_id"), bigrams(F.col("text")).alias("g"))
    n = b.select("query_id", F.size("g").alias("n"))
    b = b.select("query_id", F.explode("g").alias("pair"))
    d = load(spark, sf_dir, "documents") if docs is None else docs
    if b.count() <= most:
        hit = _hits(d.select("doc_id", F.lower("text").alias("text")), b)
    else:
        d = d.select("doc_id", F.filter(F.split(F.lower("text"), NOT_WORD), lambda x: x != "").alias("w"))
        d = d.select("doc_id", F.explode(F.array_distinct(F.transform("w", lambda x, i: F.concat_ws(" ", x, F.get("w", i + 1))))).alias("pair"))
        hit = d.join(b, "pair").groupBy("query_id", "doc_id").agg(F.count("*").alias("c"))
    return hit.join(n, "query_id").select("query_id", "doc_id", (F.col("c") / F.col("n")).alias("share"))


def _hits(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(query_id, doc_id, c): how many of a query's distinct pairs a document (its text in lower case) has. The caller has checked how many pairs there are."""
    rows = [(r["query_id"], *r["pair"].split(" ")) for r in pairs.collect()]
    words, names = sorted({w for r in rows for w in r[1:]}), list(dict.fromkeys(r[0] for r in rows))
    number, of, size = {w: i for i, w in enumerate(words)}, {x: i for i, x in enumerate(names)}, len(words)
    codes = np.array([number[x] * size + number[y] for _, x, y in rows], dtype=np.int64)
    order = np.argsort(codes, kind="stable")
    # distinct codes, and where the queries of each begin
    wanted, begin, many = np.unique(codes[order], return_index=True, return_counts=True)
    asks = np.array([of[r[0]] for r in rows], dtype=np.int64)[order]
    edges = word_edges(docs.sparkSession)

    def count(batches):
        cut = Words(edges, words)
        for lo, lengths, word, ids in ((lo, n, w, x.column("doc_id")) for x in batches for lo, _, n, w in cut.pieces(x.column("text"))):
            row = np.repeat(np.arange(len(lengths), dtype=np.int64), lengths)
            beside = (row[1:] == row[:-1]) & (word[1:] >= 0) & (word[:-1] >= 0)
            code, at = (word[:-1] * size + word[1:])[beside], row[:-1][beside]
            p = np.minimum(np.searchsorted(wanted, code), max(len(wanted) - 1, 0))
            met = wanted[p] == code if len(wanted) else np.zeros(len(code), dtype=bool)
            key = np.unique(at[met] * max(len(wanted), 1) + p[met])
            at, p = np.divmod(key, max(len(wanted), 1))
            own = many[p]
            # the places of all queries of each pair
            place = np.arange(own.sum()) - np.repeat(np.cumsum(own) - own, own) + np.repeat(begin[p], own)
            key, c = np.unique(np.repeat(at, own) * max(len(names), 1) + asks[place], return_counts=True)
            at, q = np.divmod(key, max(len(names), 1))
            yield pa.RecordBatch.from_arrays([pa.array(q.astype(np.int32)), ids.take(pa.array(at + lo)), pa.array(c.astype(np.int64))], ["_q", "doc_id", "c"])

    named = docs.sparkSession.createDataFrame(list(enumerate(names)), f"_q int, query_id {pairs.schema['query_id'].dataType.simpleString()}")
    found = docs.mapInArrow(count, f"_q int, doc_id {docs.schema['doc_id'].dataType.simpleString()}, c bigint")
    # a row per query, no more than there are pairs; rows that share an id add up
    return found.join(F.broadcast(named), "_q").groupBy("query_id", "doc_id").agg(F.sum("c").alias("c"))


def grade_of(share: Column) -> Column:
    return F.when(share >= 0.95, 3).when(share >= 0.10, 2).when(share >= 0.05, 1).otherwise(0)


#: Ids of first stages' documents that are broadcast at most.
MOST_FOUND = 1_000_000


def gold_w3(spark: SparkSession, sf_dir: str, n: int = 100, half: bool = False) -> DataFrame:
    """Each benchmark item's BM25 top n documents, graded by word-pair coverage. ``half`` (W4): the query is the second half of the item's words."""
    from semrank.exec.scratch import Scratch
    from semrank.operators.retrieval import bm25_topn, terms

    docs, queries = load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")
    words = terms(F.col("text"))
    asked = F.array_join(F.slice(words, F.floor(F.size(words) / 2).cast("int") + 1, F.size(words)), " ") if half else F.col("text")
    top = Scratch(spark, "w3").write("top", bm25_topn(docs.select("doc_id", "text"), queries.select(F.col("item_id").alias("query_id"), asked.alias("text")), n))
    # no other document is graded or shown; few ids go to where the texts are
    found = top.select("doc_id").distinct()
    docs = docs.join(F.broadcast(found) if found.count() <= MOST_FOUND else found, "doc_id", "left_semi")
    graded = top.join(coverage(spark, sf_dir, docs=docs), ["query_id", "doc_id"], "left")
    keyed = graded.join(docs.select("doc_id", F.col("text").alias("key")), "doc_id")
    name = F.format_string("w4-%d" if half else "w3-%d", "query_id")
    return keyed.select(name.alias("task_id"), F.col("doc_id").alias("item_id"), "key", grade_of(F.coalesce("share", F.lit(0.0))).cast("bigint").alias("grade"), (F.col("rnk") - 1).cast("int").alias("pos"))


def gold_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gold_w3(spark, sf_dir, half=True)


def gold_w5(spark: SparkSession, sf_dir: str, worst: bool = False) -> DataFrame:
    """Labelled documents, a task per source: 2 * quality + (1 - toxic); ``worst`` reverses the criterion."""
    lab = load(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    d = load(spark, sf_dir, "documents").join(lab, "doc_id")
    good = 2 * F.col("quality") + 1 - F.col("toxic")
    task = F.concat(F.lit("w5b-" if worst else "w5-"), F.coalesce("source", F.lit("")))
    return d.select(task.alias("task_id"), F.col("doc_id").alias("item_id"), F.col("text").alias("key"), (3 - good if worst else good).cast("bigint").alias("grade"))


def gold_w6(spark: SparkSession, sf_dir: str, queries: int = 3) -> DataFrame:
    """Three benchmark items that some document holds verbatim, against all documents: few are relevant."""
    cov = coverage(spark, sf_dir)
    full = cov.where("share >= 0.95").select("query_id").distinct().orderBy("query_id").limit(queries)
    pairs = load(spark, sf_dir, "documents").crossJoin(F.broadcast(full))  # three rows
    g = pairs.join(cov, ["query_id", "doc_id"], "left")
    return g.select(F.format_string("w6-%d", "query_id").alias("task_id"), F.col("doc_id").alias("item_id"), F.col("text").alias("key"), grade_of(F.coalesce("share", F.lit(0.0))).cast("bigint").alias("grade"))


#: Conversations whose answers make up one shared pool.
POOL = 100


def gold_w7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user turn that was answered as a context over a pool of answers, those of its hundred of conversations: the own next turn 2, the same conversation 1, else 0."""
    c = load(spark, sf_dir, "conversations")
    answers = c.where("role = 'assistant'").select("conv_id", "turn", F.col("text").alias("answer"))
    pool = answers.withColumn("p", F.floor(F.col("conv_id") / POOL))
    asked = c.where("role = 'user'").select("conv_id", "turn").join(answers.select("conv_id", (F.col("turn") - 1).alias("turn")), ["conv_id", "turn"])
    asked = asked.select(F.col("conv_id").alias("c1"), F.col("turn").alias("t1"), F.floor(F.col("conv_id") / POOL).alias("p"))
    g = asked.join(pool, "p")
    own = (F.col("c1") == F.col("conv_id")) & (F.col("turn") == F.col("t1") + 1)
    return g.select(
        F.format_string("w7-%d-%d", "c1", "t1").alias("task_id"), (F.col("conv_id") * 1000 + F.col("turn")).alias("item_id"), F.col("answer").alias("key"), F.when(own, 2).when(F.col("c1") == F.col("conv_id"), 1).otherwise(0).cast("bigint").alias("grade")
    )


def tasks_w8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inquiry set: templated questions on stored attributes (factual) and user turns (reasoning)."""
    users = load(spark, sf_dir, "conversations").where("role = 'user'")
    out = users.select(F.format_string("r-%d-%d", "conv_id", "turn").alias("task_id"), F.col("text").alias("criterion"), F.lit("reasoning").alias("kind"))
    about = {"nation": ("n_nationkey", "n_name", "population"), "region": ("r_regionkey", "r_name", "area"), "part": ("p_partkey", "p_name", "retail price"), "supplier": ("s_suppkey", "s_name", "account balance")}
    for t, (key, name, what) in about.items():
        out = out.unionByName(load(spark, sf_dir, t).select(F.concat(F.lit(f"f-{t}-"), F.col(key)).alias("task_id"), F.concat(F.lit(f"the {what} of "), name).alias("criterion"), F.lit("factual").alias("kind")))
    return out


WORKLOADS = {"w1": gold_w1, "w2": gold_w2, "w3": gold_w3, "w4": gold_w4, "w5": gold_w5, "w6": gold_w6, "w7": gold_w7}


def graded_w6(spark: SparkSession, sf_dir: str, queries: int = 3) -> DataFrame:
    """``gold_w6`` without keys, with pos and lat: a task has all documents, so places come from range partitions and counts, and no text is sorted."""
    from semrank.exec.index import placed_by
    from semrank.exec.scratch import Scratch

    scratch = Scratch(spark, "w6")
    cov = scratch.write("cover", coverage(spark, sf_dir))
    full = scratch.write("asked", cov.where("share >= 0.95").select("query_id").distinct().orderBy("query_id").limit(queries))
    few = F.broadcast(full)  # three rows
    found = cov.join(few, "query_id", "left_semi")
    g = load(spark, sf_dir, "documents").select("doc_id").crossJoin(few).join(found, ["query_id", "doc_id"], "left")
    g = g.select(F.format_string("w6-%d", "query_id").alias("task_id"), F.col("doc_id").alias("item_id"), grade_of(F.coalesce("share", F.lit(0.0))).cast("bigint").alias("grade"))
    g = placed_by(g.withColumn("_late", -F.col("item_id")), ["grade", "_late"], scratch, "_behind").drop("_late")
    g = placed_by(g, ["item_id"], scratch, "pos").withColumn("pos", (F.col("pos") - 1).cast("int"))
    n = scratch.write("sizes", g.groupBy("task_id").agg(F.count("*").alias("_n")))
    g = g.join(F.broadcast(n), "task_id")  # three rows
    lat = F.when(F.col("_n") > 1, F.floor((F.col("_behind") - 1) * TOP / (F.col("_n") - 1))).otherwise(F.lit(0)).cast("bigint")
    return g.select("task_id", "item_id", "grade", "pos", lat.alias("lat"))


def workload(spark: SparkSession, sf_dir: str, name: str, *, k: int | None = None, texts: bool = True) -> DataFrame:
    """Items of a workload with pos, lat, grade and (if given) a limit per task. Without ``texts`` keys are as ``packed.slim`` leaves them, before anything is sorted."""
    from semrank.exec.packed import slim

    bare = lambda d: d if texts else slim(d, SimBackend())
    if name == "w6":
        docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), F.col("text").alias("key"))
        g = graded_w6(spark, sf_dir).join(bare(docs), "item_id")
    else:
        g = bare(gold_w5(spark, sf_dir, worst=True) if name == "w5b" else WORKLOADS[name](spark, sf_dir))
        g = with_latent(g if "pos" in g.columns else _positions(g))
    return g if k is None else g.withColumn("k", F.lit(k).cast("bigint"))


def truth_of(items: DataFrame) -> DataFrame:
    return items.select("task_id", "item_id", "grade")


def tasks_of(items: DataFrame, kind: str = "reasoning", k: int | None = None) -> DataFrame:
    return items.select("task_id").distinct().select("task_id", F.lit(kind).alias("kind"), F.lit(k).cast("bigint").alias("k"))
