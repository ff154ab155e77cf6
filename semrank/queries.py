"""Every method, variant, baseline and measure as a query on the given tables, with the SQL that must agree.

A clean simulator makes every access path exact, so its oracle is an ordinary ORDER BY; noisy value paths are repeated in SQL from
the same MD5 noise; noisy comparison paths have no SQL form and are tested against brute force.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.call import ResponseCache
from semrank.exec.index import indexed
from semrank.exec.packed import measured, rankings_of, run_paths, slim, usage_of
from semrank.exec.replies import fit_batch, parse_orders
from semrank.exec.scratch import Scratch
from semrank.exec.split import split_merge
from semrank.exec.waves import merge_waves, quick_waves, score_waves
from semrank.functions import metrics as M
from semrank.operators.frame import llm_order_by
from semrank.operators.fuse import fuse_borda, fuse_rrf
from semrank.operators.relational import as_of_join, interval_join, rank_by_many
from semrank.operators.retrieval import bm25_topn, proxy_rank, vector_topn
from semrank.operators.sql import register_udtf, semantic_score, semantic_sql
from semrank.plans import optimizer as O
from semrank.plans.complexity import calls, calls_expr, candidates_frame, estimate, exact_calls, within_budget
from semrank.plans.spec import (
    EXT_BUBBLE, EXT_MERGE, EXT_POINT, EXT_POINT_SEARCH, POINT, POINT_SEARCH, QUICK, QUICK_3, PathConfig, candidate_grid,
)
from semrank.sources import tables as T
from semrank.sources.lookup import with_facts
from semrank.sources.model import PRICES, PROFILES, TIERS, SimBackend
from semrank.streaming.topk import stream_sessions, stream_topk

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
PATHS = {p.path_id: p for p in (POINT, EXT_POINT, QUICK, QUICK_3, EXT_BUBBLE, EXT_MERGE)}
FINE = {"max_point": 10000}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


# ---- workloads in SQL -------------------------------------------------------------------------------------------

_WORDS = r"list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '')"
_PAIRS = "list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i+1]))"
COVER = f"""
bw AS (SELECT item_id AS query_id, {_WORDS} AS w FROM benchmark),
bg AS (SELECT query_id, {_PAIRS} AS g FROM bw),
be AS (SELECT query_id, unnest(g) AS pair, len(g) AS n FROM bg),
dw AS (SELECT doc_id, {_WORDS} AS w FROM documents),
de AS (SELECT doc_id, unnest({_PAIRS}) AS pair FROM dw),
cover AS (SELECT query_id, doc_id, count(*) / any_value(n) AS share FROM de JOIN be USING (pair) GROUP BY ALL)"""
BM25 = f"""
qt AS (SELECT DISTINCT query_id, unnest(WORDS) AS term FROM (SELECT item_id AS query_id, {_WORDS} AS w FROM benchmark)),
dt AS (SELECT doc_id, {_WORDS} AS w FROM documents),
st AS (SELECT count(*) AS docs, avg(len(w)) AS avgdl FROM dt),
tf AS (SELECT term, doc_id, dl, count(*) AS tf FROM (SELECT doc_id, len(w) AS dl, unnest(w) AS term FROM dt) WHERE term IN (SELECT term FROM qt) GROUP BY ALL),
df AS (SELECT term, count(*) AS df FROM tf GROUP BY term),
sc AS (
  SELECT query_id, doc_id, round(sum(ln(1 + (docs - df + 0.5) / (df + 0.5)) * tf * 1.9 / (tf + 0.9 * (0.6 + 0.4 * dl / avgdl))), 6) AS score
  FROM tf JOIN df USING (term) JOIN qt USING (term), st GROUP BY ALL),
top AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rnk FROM sc QUALIFY rnk <= 100)"""
_GRADE = "CASE WHEN coalesce(share, 0) >= 0.95 THEN 3 WHEN coalesce(share, 0) >= 0.10 THEN 2 WHEN coalesce(share, 0) >= 0.05 THEN 1 ELSE 0 END"
_TURNS = """
us AS (SELECT u.conv_id, u.turn FROM conversations u JOIN conversations a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 AND a.role = 'assistant' WHERE u.role = 'user'),
po AS (SELECT conv_id, turn, text FROM conversations WHERE role = 'assistant')"""


def _passages(name: str, words: str) -> str:
    return f"""{COVER}, {BM25.replace('WORDS', words)},
g AS (SELECT '{name}-' || t.query_id AS task_id, t.doc_id AS item_id, d.text AS key, CAST({_GRADE} AS BIGINT) AS grade, t.rnk AS ord
      FROM top t JOIN documents d USING (doc_id) LEFT JOIN cover c ON c.query_id = t.query_id AND c.doc_id = t.doc_id)"""


GOLD = {
    "w1": "g AS (SELECT 'w1-' || c_nationkey AS task_id, c_custkey AS item_id, c_name AS key, CAST(round(c_acctbal * 100) AS BIGINT) AS grade, c_custkey AS ord FROM customer)",
    "w2": """oc AS (SELECT c_nationkey, sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS cents FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY ALL),
g AS (SELECT 'w2' AS task_id, CAST(n_nationkey AS BIGINT) AS item_id, n_name AS key, CAST(coalesce(cents, 0) AS BIGINT) AS grade, n_nationkey AS ord FROM nation LEFT JOIN oc ON c_nationkey = n_nationkey)""",
    "w3": _passages("w3", "w"),
    "w4": _passages("w4", "w[len(w) // 2 + 1:]"),
    "w5": """g AS (SELECT 'w5-' || coalesce(source, '') AS task_id, doc_id AS item_id, text AS key, CAST(2 * quality + 1 - toxic AS BIGINT) AS grade, doc_id AS ord FROM documents JOIN labels USING (doc_id))""",
    "w6": f"""{COVER},
fq AS (SELECT DISTINCT query_id FROM cover WHERE share >= 0.95 ORDER BY query_id LIMIT 3),
g AS (SELECT 'w6-' || f.query_id AS task_id, d.doc_id AS item_id, d.text AS key, CAST({_GRADE} AS BIGINT) AS grade, d.doc_id AS ord
      FROM documents d, fq f LEFT JOIN cover c ON c.query_id = f.query_id AND c.doc_id = d.doc_id)""",
    "w7": f"""{_TURNS},
g AS (SELECT 'w7-' || us.conv_id || '-' || us.turn AS task_id, po.conv_id * 1000 + po.turn AS item_id, po.text AS key,
      CAST(CASE WHEN po.conv_id = us.conv_id AND po.turn = us.turn + 1 THEN 2 WHEN po.conv_id = us.conv_id THEN 1 ELSE 0 END AS BIGINT) AS grade, po.conv_id * 1000 + po.turn AS ord FROM us JOIN po ON us.conv_id // 100 = po.conv_id // 100)""",
}
GOLD["w5b"] = GOLD["w5"].replace("'w5-'", "'w5b-'").replace("2 * quality + 1 - toxic", "3 - (2 * quality + 1 - toxic)")
ITEMS = """i AS (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY ord) - 1 AS pos, count(*) OVER (PARTITION BY task_id) AS n,
      CASE WHEN count(*) OVER (PARTITION BY task_id) > 1 THEN (row_number() OVER (PARTITION BY task_id ORDER BY grade, item_id DESC) - 1) * 10000 // (count(*) OVER (PARTITION BY task_id) - 1) ELSE 0 END AS lat FROM g)"""


def items_sql(w: str, rest: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' * recursive}{GOLD[w]}, {ITEMS}, {rest}" if rest.lstrip()[:6] != "SELECT" else f"WITH {GOLD[w]}, {ITEMS} {rest}"


def exact_sql(w: str, k: int | None = None) -> str:
    cut = f" QUALIFY rnk <= {k}" if k else ""
    return items_sql(w, f"SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY lat DESC, item_id) AS rnk FROM i WHERE key <> ''{cut}")


def noise_sql(expr: str, a: int) -> str:
    return f"(CAST('0x' || substr(md5({expr}), 1, 8) AS BIGINT) % {2 * a + 1} - {a})"


def score_sql(profile: str, batch: bool) -> str:
    p = PROFILES[profile]
    shown = "'7|b|' || task_id || '|' || (pos // 4) || '|' || item_id" if batch else "'7|s|' || task_id || '|' || item_id"
    return f"least(greatest(lat + {noise_sql(shown, p.score_many if batch else p.score)}, 0), 10000) * 10 // 10000"


def ranked(spark: SparkSession, sf: str, w: str, path: PathConfig, k: int | None = None, **backend) -> DataFrame:
    return rankings_of(run_paths(T.workload(spark, sf, w, k=k, texts=False), [path], SimBackend(**backend), by_wave=False)).drop("path_id")


# ---- gold ------------------------------------------------------------------------------------------------------

for _w in ("w1", "w2", "w3", "w4", "w5", "w5b", "w6", "w7"):
    query(f"gold_{_w}", items_sql(_w, "SELECT task_id, item_id, grade, lat FROM i"))(lambda s, d, w=_w: (T.graded_w6(s, d) if w == "w6" else T.workload(s, d, w, texts=False)).select("task_id", "item_id", "grade", "lat"))

# ---- access paths ----------------------------------------------------------------------------------------------

_CLEAN = {"point": PathConfig("score_each", **FINE), "batch": PathConfig("score_batch", **FINE), "quick": QUICK, "quick_votes": QUICK_3, "bubble": EXT_BUBBLE, "merge": EXT_MERGE}
for _n, _p in _CLEAN.items():
    query(f"rank_{_n}_clean_w1", exact_sql("w1"))(lambda s, d, p=_p: ranked(s, d, "w1", p))
for _n, _b, _p in (("rank_point_factual_w1", False, POINT), ("rank_batch_factual_w1", True, EXT_POINT)):
    query(_n, items_sql("w1", f"z AS (SELECT *, {score_sql('factual', _b)} AS score FROM i) SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY score DESC, item_id) AS rnk FROM z"))(
        lambda s, d, p=_p: ranked(s, d, "w1", p, profile="factual")
    )
for _n, _p in (("rank_point_lookup_w2", PathConfig("score_each", lookup=True, **FINE)), ("rank_batch_lookup_w2", PathConfig("score_batch", lookup=True, **FINE))):

    @query(_n, exact_sql("w2"))
    def _lookup(s, d, p=_p):
        items = T.workload(s, d, "w2")
        return rankings_of(run_paths(with_facts(items, items.select("key", F.col("lat").alias("value"))), [p], SimBackend("factual"))).drop("path_id")


for _n, _p in (("quick", QUICK), ("votes", QUICK_3), ("bubble", EXT_BUBBLE), ("merge", EXT_MERGE), ("point", PathConfig("score_each", **FINE))):
    query(f"topk_{_n}_w5", exact_sql("w5", 10))(lambda s, d, p=_p: ranked(s, d, "w5", p, 10))
query("topk_merge_w3", exact_sql("w3", 10))(lambda s, d: ranked(s, d, "w3", EXT_MERGE, 10))
query("topk_merge_w4", exact_sql("w4", 10))(lambda s, d: ranked(s, d, "w4", EXT_MERGE, 10))
# tasks as large as the corpus run in waves
query("topk_merge_w6", exact_sql("w6", 10))(lambda s, d: merge_waves(T.workload(s, d, "w6", texts=False), EXT_MERGE, SimBackend(), 10)[0].drop("path_id"))
query("topk_bubble_w7", exact_sql("w7", 10))(lambda s, d: ranked(s, d, "w7", EXT_BUBBLE, 10))
query("topk_quick_w5b", exact_sql("w5b", 10))(lambda s, d: ranked(s, d, "w5b", QUICK, 10))
query("rank_merge_w3_full", exact_sql("w3"))(lambda s, d: ranked(s, d, "w3", EXT_MERGE))
for _n, _p in (("quick", QUICK), ("quick_votes", QUICK_3), ("merge", EXT_MERGE), ("bubble", EXT_BUBBLE)):
    query(f"noisy_{_n}_w1")(lambda s, d, p=_p: ranked(s, d, "w1", p, profile="reasoning"))
query("rank_ascending_w1", items_sql("w1", "SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY lat, item_id) AS rnk FROM i"))(
    lambda s, d: rankings_of(run_paths(T.reverse(T.workload(s, d, "w1")), [EXT_MERGE], SimBackend())).drop("path_id")
)
for _n, _p in (("random_pivot", PathConfig("pivot_split", pivot="random")), ("median_pivot", PathConfig("pivot_split", pivot="median3")), ("bubble_stable", PathConfig("slide_window", stop_when_stable=True)), ("bubble_rescan", PathConfig("slide_window", rescan=True))):
    query(f"rank_{_n}_w1", exact_sql("w1"))(lambda s, d, p=_p: ranked(s, d, "w1", p))

# waves
query("wave_point_w1", exact_sql("w1"))(lambda s, d: score_waves(T.workload(s, d, "w1"), PathConfig("score_each", **FINE), SimBackend())[0].select("task_id", "item_id", "rnk"))
query("wave_merge_w1", exact_sql("w1"))(lambda s, d: merge_waves(T.workload(s, d, "w1"), EXT_MERGE, SimBackend(), local=2)[0].drop("path_id"))
query("wave_votes_w2_top3", exact_sql("w2", 3))(lambda s, d: quick_waves(T.workload(s, d, "w2"), QUICK_3, SimBackend(), 3, finish=8)[0].drop("path_id"))
query("wave_quick_w1_top10", exact_sql("w1", 10))(lambda s, d: quick_waves(T.workload(s, d, "w1"), QUICK, SimBackend(), 10, finish=16)[0].drop("path_id"))


LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def lineitem_items(spark: SparkSession, sf: str, texts: bool = True) -> DataFrame:
    """All order lines as one task, numbered by their key; the latent value is the extended price in cents. Without ``texts`` keys are as ``packed.slim`` leaves them before anything is sorted."""
    li = T.load(spark, sf, "lineitem").select(*LINE_KEY, F.concat_ws(" ", "l_orderkey", "l_linenumber", "l_shipdate").alias("key"), F.round(F.col("l_extendedprice") * 100).cast("bigint").alias("lat"))
    return indexed(li if texts else slim(li, SimBackend()), LINE_KEY, Scratch(spark, "lines")).withColumn("task_id", F.lit("w16")).withColumn("item_id", F.col("pos"))


_LINES = f"x AS (SELECT *, row_number() OVER (ORDER BY {', '.join(LINE_KEY)}) - 1 AS item_id FROM lineitem)"
query("w16_merge_top10", f"WITH {_LINES} SELECT 'w16' AS task_id, item_id, row_number() OVER (ORDER BY CAST(round(l_extendedprice * 100) AS BIGINT) DESC, item_id) AS rnk FROM x QUALIFY rnk <= 10")(
    lambda s, d: merge_waves(lineitem_items(s, d), EXT_MERGE, SimBackend(), 10)[0].drop("path_id")
)
_FULL = f"WITH {_LINES} SELECT 'w16' AS task_id, item_id, row_number() OVER (ORDER BY {{}} DESC, item_id) AS rnk FROM x"
query("w16_point_full", _FULL.format("least(CAST(round(l_extendedprice * 100) AS BIGINT) // 1200, 10000)"))(
    lambda s, d: score_waves(lineitem_items(s, d).withColumn("lat", F.floor(F.col("lat") / 1200)), PathConfig("score_each", **FINE), SimBackend())[0].select("task_id", "item_id", "rnk")
)
query("w16_merge_full", _FULL.format("CAST(round(l_extendedprice * 100) AS BIGINT)"))(lambda s, d: split_merge(lineitem_items(s, d, texts=False), SimBackend(), 24)[0].drop("path_id"))


@query("w16_optimized_top10", f"WITH {_LINES} SELECT 'all' AS task_id, item_id, row_number() OVER (ORDER BY CAST(round(l_extendedprice * 100) AS BIGINT) DESC, item_id) AS rnk FROM x QUALIFY rnk <= 10")
def w16_optimized(spark, sf):
    """A budgeted ordering of a task far beyond one worker: probe on a sample, the judge's choice, its run in waves. The budget is per line."""
    items = Scratch(spark, "w16").write("items", lineitem_items(spark, sf).select("item_id", "key", "lat"))
    out = llm_order_by(items, "key", "the dearest line", id_col="item_id", latent="lat", limit=10, budget_nano=60_000 * items.count(), policy="judge", backend=SimBackend())
    return out.select(F.lit("all").alias("task_id"), "item_id", F.col("rnk").cast("bigint").alias("rnk"))


query("w16_index", f"WITH {_LINES} SELECT l_orderkey, l_linenumber, l_partkey, item_id AS pos FROM x")(lambda s, d: lineitem_items(s, d).select("l_orderkey", "l_linenumber", "l_partkey", "pos"))

# ---- calls, cost ---------------------------------------------------------------------------------------------------


def segment_sizes(spark: SparkSession, sf: str) -> DataFrame:
    """Tasks of different sizes: customers of a nation and market segment."""
    return T.load(spark, sf, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


def _grid(spark: SparkSession, sf: str) -> DataFrame:
    p = candidates_frame(spark, [POINT, EXT_POINT, QUICK, QUICK_3, EXT_BUBBLE, EXT_MERGE]).select("path_id", "kind", "m", "v")
    k = spark.createDataFrame([(None,), (4,), (10,)], "k int")
    return segment_sizes(spark, sf).select("n").crossJoin(F.broadcast(p)).crossJoin(F.broadcast(k))  # literals: 18 rows


_GRID_SQL = """p(path_id, kind, m, v) AS (VALUES ('point', 'score_each', 4, 1), ('ext_point_4', 'score_batch', 4, 1), ('quick', 'pivot_split', 4, 1), ('quick_3', 'pivot_split', 4, 3), ('ext_bubble_4', 'slide_window', 4, 1), ('ext_merge_4', 'run_merge', 4, 1)),
n AS (SELECT count(*) AS n FROM customer GROUP BY c_nationkey, c_mktsegment), k(k) AS (VALUES (NULL), (4), (10))"""
_F = "CASE kind WHEN 'score_each' THEN n WHEN 'score_batch' THEN n / m WHEN 'pivot_split' THEN CASE WHEN k IS NULL THEN v * n * log2(n) ELSE v * (n + k * log2(k)) END WHEN 'slide_window' THEN CASE WHEN k IS NULL THEN n * n / (m * m) ELSE k * n / (m * m) END ELSE CASE WHEN k IS NULL THEN n / m * (1 + log2(greatest(n / m, 1))) ELSE n / m * (2 + log2(greatest(k / m, 1))) END END"


@query("complexity_grid", f"WITH {_GRID_SQL} SELECT path_id, n, k, round(CAST({_F} AS DOUBLE), 6) AS calls FROM p, n, k")
def complexity_grid(spark, sf):
    c = F.col
    return _grid(spark, sf).select("path_id", "n", "k", F.round(calls_expr(c("kind"), c("m"), c("v"), c("n"), c("k")), 6).alias("calls"))


@query("calls_closed_form", """WITH RECURSIVE p(path_id) AS (VALUES ('point'), ('ext_point_4'), ('ext_bubble_4')), k(k) AS (VALUES (NULL), (2), (3), (10)),
s AS (SELECT s_suppkey // 100 AS block, CAST(count(*) AS INT) AS n FROM supplier GROUP BY ALL), n AS (SELECT DISTINCT n FROM s),
b(n, k, done, calls) AS (SELECT n, k, 0, CASE WHEN n <= 4 THEN 1 ELSE 1 + CAST(ceil((n - 4) / 2.0) AS INT) END FROM n, k
  UNION ALL SELECT n, k, done + 2, CASE WHEN n - done - 2 <= 4 THEN 1 ELSE 1 + CAST(ceil((n - done - 2 - 4) / 2.0) AS INT) END FROM b
  WHERE done + 2 < coalesce(least(k, n), n) AND n - done > 4 AND n - done - 2 > 1),
t AS (SELECT n, k, sum(calls) AS c FROM b GROUP BY ALL)
SELECT block, path_id, s.n, k.k, CAST(CASE path_id WHEN 'point' THEN s.n WHEN 'ext_point_4' THEN ceil(s.n / 4.0) ELSE c END AS BIGINT) AS calls FROM p, s, k JOIN t ON t.n = s.n AND t.k IS NOT DISTINCT FROM k.k WHERE s.n > 1 OR path_id <> 'ext_bubble_4'""")
def calls_closed_form(spark, sf):
    """Calls as measured on suppliers in blocks of a hundred keys; the SQL has the closed forms."""
    block = F.floor(F.col("s_suppkey") / 100)
    base = T.load(spark, sf, "supplier").select(block.cast("bigint").alias("block"), F.col("s_suppkey").cast("bigint").alias("item_id"), (F.col("s_suppkey") % 100).cast("int").alias("pos"), F.col("s_name").alias("key"), F.round(F.col("s_acctbal") * 100).cast("bigint").alias("lat"))
    k = spark.createDataFrame([(None,), (2,), (3,), (10,)], "k bigint")
    items = base.crossJoin(F.broadcast(k)).withColumn("task_id", F.concat_ws("/", "block", F.coalesce(F.col("k").cast("string"), F.lit(""))))  # literals
    u = usage_of(run_paths(items, [POINT, EXT_POINT, EXT_BUBBLE], SimBackend(), by_wave=False)).groupBy("task_id", "path_id").agg(F.sum("calls").alias("calls"))
    u = u.select(F.split("task_id", "/")[0].cast("bigint").alias("block"), "path_id", F.expr("cast(nullif(split(task_id, '/')[1], '') as int)").alias("k"), "calls")
    return u.join(base.groupBy("block").agg(F.count("*").cast("int").alias("n")), "block").select("block", "path_id", "n", "k", "calls")


@query("cost_extrapolation", f"WITH {_GRID_SQL}, x AS (SELECT path_id, n AS n0, k AS k0, {_F} AS f FROM p, n, k), y AS (SELECT path_id, k AS k0, {_F} AS f20 FROM p, (SELECT 20 AS n), k) SELECT x.path_id, x.n0 AS n, x.k0 AS k, round(0.02 * f / f20, 6) AS est FROM x JOIN y ON x.path_id = y.path_id AND x.k0 IS NOT DISTINCT FROM y.k0")
def cost_extrapolation(spark, sf):
    """A sample of 20 items that cost two cents, carried to n."""
    c, twenty = F.col, F.lit(20)
    ks = F.when(c("k").isNotNull(), F.least("k", twenty))
    f, f20 = (calls_expr(c("kind"), c("m"), c("v"), n, k) for n, k in ((c("n"), c("k")), (twenty, ks)))
    return _grid(spark, sf).select("path_id", "n", "k", F.round(0.02 * f / f20, 6).alias("est"))


def value_usage(spark: SparkSession, sf: str) -> DataFrame:
    return usage_of(run_paths(T.workload(spark, sf, "w5"), [POINT, EXT_POINT], SimBackend()))


_SPENT = """u AS (
  SELECT task_id, 'point' AS path_id, 'score' AS op, 1 AS calls, CAST(ceil((160 + length(key)) / 4.0) AS BIGINT) AS in_tok, 6 AS out_tok FROM i WHERE key <> ''
  UNION ALL SELECT task_id, 'ext_point_4', 'score_many', 1, CAST(ceil((200 + sum(length(key))) / 4.0) AS BIGINT), 6 + 3 * count(*) FROM i WHERE key <> '' GROUP BY task_id, pos // 4),
m AS (SELECT *, in_tok * 250 + out_tok * 2000 AS nano_usd FROM u)"""
_VU = items_sql("w5", _SPENT)
query("usage_rollup", _VU + " SELECT path_id, op, CAST(sum(calls) AS BIGINT) AS calls, CAST(sum(in_tok) AS BIGINT) AS in_tok, CAST(sum(out_tok) AS BIGINT) AS out_tok, CAST(sum(nano_usd) AS BIGINT) AS nano_usd FROM m GROUP BY ROLLUP (path_id, op)")(lambda s, d: M.usage_rollup(value_usage(s, d)))
query("usage_cube", _VU + " SELECT path_id, op, CAST(sum(calls) AS BIGINT) AS calls, count(DISTINCT task_id) AS tasks FROM m GROUP BY CUBE (path_id, op)")(lambda s, d: M.usage_cube(value_usage(s, d)))

# ---- optimizer -----------------------------------------------------------------------------------------------------

query("sample_items_w3", items_sql("w3", "SELECT task_id, item_id FROM i QUALIFY row_number() OVER (PARTITION BY task_id ORDER BY CAST('0x' || substr(md5('7|' || item_id), 1, 12) AS BIGINT), item_id) <= 20"))(lambda s, d: O.sample_items(T.workload(s, d, "w3")).select("task_id", "item_id"))


@query("candidate_grid", "WITH n AS (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL) SELECT n.*, t.* FROM n, (VALUES ('point', 4, 1), ('ext_point_4', 4, 1), ('ext_point_8', 8, 1), ('quick', 4, 1), ('quick_3', 4, 3), ('ext_bubble_4', 4, 1), ('ext_merge_4', 4, 1), ('ext_bubble_8', 8, 1), ('ext_merge_8', 8, 1)) t(path_id, m, v)")
def grid(spark, sf):
    """The candidates of every task."""
    return segment_sizes(spark, sf).crossJoin(F.broadcast(candidates_frame(spark, candidate_grid((4, 8))).select("path_id", "m", "v")))  # nine rows


_INQ = "CAST('0x' || substr(md5('7|' || task_id), 1, 8) AS BIGINT) % 1000 < 100"
_W8 = """q AS (SELECT 'r-' || conv_id || '-' || turn AS task_id, 'reasoning' AS kind FROM conversations WHERE role = 'user'
      UNION ALL SELECT 'f-nation-' || n_nationkey, 'factual' FROM nation UNION ALL SELECT 'f-region-' || r_regionkey, 'factual' FROM region
      UNION ALL SELECT 'f-part-' || p_partkey, 'factual' FROM part UNION ALL SELECT 'f-supplier-' || s_suppkey, 'factual' FROM supplier),
a AS (SELECT *, CASE WHEN {f} THEN CASE kind WHEN 'factual' THEN 'reasoning' ELSE 'factual' END ELSE kind END AS answer FROM q)""".replace("{f}", _INQ)
query("inquiry_route", f"WITH {_W8} SELECT task_id, answer, CASE answer WHEN 'factual' THEN 'lookup' ELSE 'pool' END AS route FROM a")(lambda s, d: O.route_by_inquiry(T.tasks_w8(s, d)).select("task_id", "answer", "route"))
query("inquiry_accuracy", f"WITH {_W8} SELECT avg(CASE WHEN answer = kind THEN 1.0 ELSE 0.0 END) AS accuracy, count(*) AS n FROM a")(lambda s, d: M.accuracy(O.route_by_inquiry(T.tasks_w8(s, d)), "answer", "kind"))

_R2 = items_sql("w5", f"""z AS (SELECT *, {score_sql('reasoning', False)} AS s1, {score_sql('reasoning', True)} AS s2 FROM i WHERE key <> ''),
r AS (SELECT task_id, item_id, grade, 'point' AS path_id, row_number() OVER (PARTITION BY task_id ORDER BY s1 DESC, item_id) AS rnk FROM z
      UNION ALL SELECT task_id, item_id, grade, 'ext_point_4', row_number() OVER (PARTITION BY task_id ORDER BY s2 DESC, item_id) FROM z),
fu AS (SELECT task_id, item_id, sum(1000000000000 // (60 + rnk)) AS fused FROM r GROUP BY ALL),
px AS (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY fused DESC, item_id) AS rnk FROM fu),
tau AS (SELECT a.task_id, a.path_id, avg(sign(y.rnk - x.rnk)) AS agreement FROM r a JOIN r b ON a.task_id = b.task_id AND a.path_id = b.path_id AND a.rnk < b.rnk
        JOIN px x ON x.task_id = a.task_id AND x.item_id = a.item_id JOIN px y ON y.task_id = b.task_id AND y.item_id = b.item_id GROUP BY ALL)""")


def value_ranks(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    items = T.workload(spark, sf, "w5")
    return items, rankings_of(run_paths(items, [POINT, EXT_POINT], SimBackend("reasoning")))


query("fuse_rrf_w5", _R2 + " SELECT task_id, item_id, rnk, CAST(fused AS BIGINT) AS fused FROM px")(lambda s, d: fuse_rrf(value_ranks(s, d)[1]).drop("path_id"))
query("fuse_borda_w5", _R2 + ", n AS (SELECT task_id, max(rnk) AS n FROM r GROUP BY ALL), bo AS (SELECT r.task_id, item_id, CAST(sum(n - rnk) AS BIGINT) AS fused FROM r JOIN n USING (task_id) GROUP BY ALL) SELECT task_id, item_id, fused, row_number() OVER (PARTITION BY task_id ORDER BY fused DESC, item_id) AS rnk FROM bo")(lambda s, d: fuse_borda(value_ranks(s, d)[1]).drop("path_id"))


@query("agreement_w5", _R2 + " SELECT task_id, path_id, round(agreement, 6) AS agreement FROM tau")
def agreement_w5(spark, sf):
    r = value_ranks(spark, sf)[1]
    return O.agreement(r, fuse_rrf(r)).select("task_id", "path_id", F.round("agreement", 6).alias("agreement"))


# the budget of a task is a half, the whole or one and a half of what single scores cost, by its size
_GREEDY = _R2 + f""", {_SPENT}, e AS (SELECT task_id, path_id, sum(nano_usd) AS est, sum(calls) AS calls FROM m GROUP BY ALL),
b AS (SELECT task_id, est * (1 + calls % 3) / 2.0 AS funds FROM e WHERE path_id = 'point'),
o AS (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY agreement DESC, path_id) AS q FROM tau JOIN e USING (task_id, path_id) JOIN b USING (task_id)),
f AS (SELECT *, first_value(est) OVER (PARTITION BY task_id ORDER BY q) AS before FROM o)
SELECT task_id, path_id FROM f WHERE CASE WHEN q = 1 THEN est <= funds WHEN before <= funds THEN before + est <= funds ELSE {{}} END"""
for _how, _sql in (("skip", "est <= funds"), ("stop", "false")):

    @query(f"greedy_fit_{_how}", _GREEDY.format(_sql))
    def _greedy(spark, sf, how=_how):
        res = run_paths(written(spark, sf, "w5"), [POINT, EXT_POINT], SimBackend("reasoning"), by_wave=False)
        r, cost = rankings_of(res), M.total_cost(usage_of(res))
        funds = cost.where("path_id = 'point'").select("task_id", (F.col("nano_usd") * (1 + F.col("calls") % 3) / 2).alias("left_nano"))
        scored = O.agreement(r, fuse_rrf(r)).join(cost.withColumnRenamed("nano_usd", "est_nano"), ["task_id", "path_id"]).join(funds, "task_id")
        return O.greedy_fit(scored, None, how)


@query("budget_filter", _VU + ", c AS (SELECT task_id, path_id, sum(nano_usd) AS nano_usd FROM m GROUP BY ALL), nn AS (SELECT task_id, count(*) AS n FROM i GROUP BY ALL) SELECT task_id, path_id, CAST(nano_usd AS BIGINT) AS nano_usd, CAST(nano_usd * 2 AS DOUBLE) AS est_nano, nano_usd * 2 <= 4000000 AS fits FROM c JOIN nn USING (task_id)")
def budget_filter(spark, sf):
    """The value paths' cost on W5 carried to twice the items, against four thousandths of a dollar per task."""
    items = T.workload(spark, sf, "w5")
    cost = M.total_cost(usage_of(run_paths(items, [POINT, EXT_POINT], SimBackend()))).select("task_id", "path_id", "nano_usd")
    sizes = items.groupBy("task_id").agg(F.count("*").alias("s")).withColumn("n", F.col("s") * 2).withColumn("k", F.lit(None).cast("int"))
    return within_budget(estimate(cost, sizes, candidates_frame(spark, [POINT, EXT_POINT])).withColumn("est_nano", F.round("est_nano", 3)), 4_000_000)


BUDGET = 60_000_000


def written(spark: SparkSession, sf: str, w: str, k: int | None = None) -> DataFrame:
    """A workload that several jobs read, worked out once, without texts, which the simulator does not read."""
    return Scratch(spark, "workload").write(w, T.workload(spark, sf, w, k=k, texts=False))


def optimized(spark: SparkSession, sf: str, w: str, policy: str, budget: int = BUDGET, **more) -> O.RankResult:
    items = written(spark, sf, w, 10)
    return O.optimize(items, T.tasks_of(items, k=10), budget, SimBackend("reasoning"), policy=policy, inquiry=False, on_infeasible="cheapest", **more)


query("judge_choice_w3")(lambda s, d: optimized(s, d, "w3", "judge").choices)
query("optimize_judge_w3")(lambda s, d: optimized(s, d, "w3", "judge").ranking)
query("optimize_consensus_w5")(lambda s, d: optimized(s, d, "w5", "consensus").ranking)
query("optimize_ledger_w5")(lambda s, d: optimized(s, d, "w5", "consensus").ledger)
query("explain_rank_w5")(lambda s, d: O.explain_rank(optimized(s, d, "w5", "consensus", BUDGET // 4)))


_SAMPLED = f"""s AS (SELECT * FROM i WHERE key <> '' QUALIFY row_number() OVER (PARTITION BY task_id ORDER BY CAST('0x' || substr(md5('7|' || item_id), 1, 12) AS BIGINT), item_id) <= 20),
b AS (SELECT *, (row_number() OVER (PARTITION BY task_id ORDER BY pos) - 1) // 4 AS bt FROM s),
z AS (SELECT *, {score_sql('reasoning', False)} AS s1, {score_sql('reasoning', True).replace('(pos // 4)', 'bt')} AS s2, lat + {noise_sql("'7|j|' || task_id || '|' || item_id", PROFILES['reasoning'].judge)} AS v FROM b),
r AS (SELECT task_id, item_id, v, 'point' AS path_id, row_number() OVER (PARTITION BY task_id ORDER BY s1 DESC, item_id) AS rnk FROM z
      UNION ALL SELECT task_id, item_id, v, 'ext_point_4', row_number() OVER (PARTITION BY task_id ORDER BY s2 DESC, item_id) FROM z),
tau AS (SELECT a.task_id, a.path_id, sum(sign(a.v - c.v)) / count(*) AS tau FROM r a JOIN r c ON a.task_id = c.task_id AND a.path_id = c.path_id AND a.rnk < c.rnk GROUP BY ALL)"""


@query("judge_choice_value_w3", items_sql("w3", _SAMPLED + " SELECT task_id, path_id FROM tau QUALIFY row_number() OVER (PARTITION BY task_id ORDER BY tau DESC, CAST('0x' || substr(md5('7|' || task_id || '|' || path_id), 1, 8) AS BIGINT), path_id) = 1"))
def judge_choice_value(spark, sf):
    """The judge between the two value paths, on full sample rankings."""
    items = written(spark, sf, "w3")
    r = O.optimize(items, T.tasks_of(items), 10**12, SimBackend("reasoning"), policy="judge", candidates=[POINT, EXT_POINT], inquiry=False)
    return r.choices.select("task_id", "path_id")


@query("optimize_consensus_value_w5", items_sql("w5", f"""z AS (SELECT *, {score_sql('reasoning', False)} AS s1, {score_sql('reasoning', True)} AS s2 FROM i WHERE key <> ''),
r AS (SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY s1 DESC, item_id) AS rnk FROM z
      UNION ALL SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY s2 DESC, item_id) FROM z),
fu AS (SELECT task_id, item_id, sum(1000000000000 // (60 + rnk)) AS fused FROM r WHERE rnk <= 10 GROUP BY ALL)
SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY fused DESC, item_id) AS rnk FROM fu QUALIFY rnk <= 10"""))
def optimize_consensus_value(spark, sf):
    """Both value paths fit the budget: their cut rankings are fused."""
    return optimized(spark, sf, "w5", "consensus", 10**12, candidates=[POINT, EXT_POINT]).ranking


@query("optimize_factual_w2", exact_sql("w2"))
def optimize_factual(spark, sf):
    """An inquiry sends a factual task to grounded scores, here fine ones, so that they make no ties."""
    items = T.workload(spark, sf, "w2")
    items = with_facts(items, items.select("key", F.col("lat").alias("value")))
    grounded = PathConfig("score_each", lookup=True, **FINE)
    return O.optimize(items, T.tasks_of(items, "factual"), BUDGET, SimBackend("clean"), candidates=[EXT_MERGE, QUICK], grounded=grounded).ranking


@query("llm_order_by_lookup_w1", "SELECT c_custkey, c_nationkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey % 1000, c_custkey) AS rnk FROM customer")
def order_by_lookup(spark, sf):
    """The surface with facts: ascending by a value that only the lookup source knows."""
    c = T.load(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_name")
    facts = c.select(F.col("c_name").alias("key"), (F.col("c_custkey") % 1000).alias("value"))
    out = llm_order_by(c, "c_name", "account number", id_col="c_custkey", desc=False, partition_by="c_nationkey", facts=facts, path=PathConfig("score_each", lookup=True, **FINE), backend=SimBackend("factual"))
    return out.select("c_custkey", "c_nationkey", "rnk")


_ASC = {"point": PathConfig("score_each", **FINE), "batch": PathConfig("score_batch", **FINE), "quick": QUICK, "votes": QUICK_3, "bubble": EXT_BUBBLE, "merge": EXT_MERGE}
for _n, _p in _ASC.items():

    @query(f"llm_order_by_ascending_{_n}", "SELECT c_custkey, c_nationkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY (CAST(floor(c_acctbal) AS BIGINT) + 1000) // 2, c_custkey) AS rnk FROM customer")
    def _ascending(spark, sf, path=_p):
        c = T.load(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_name", F.expr("(cast(floor(c_acctbal) as bigint) + 1000) div 2").alias("known"))
        out = llm_order_by(c, "c_name", "account balance", id_col="c_custkey", desc=False, partition_by="c_nationkey", latent="known", path=path)
        return out.select("c_custkey", "c_nationkey", "rnk")


@query("criteria_decide", "SELECT c_custkey, row_number() OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY (CAST(floor(c_acctbal) AS BIGINT) + 1000) // 2 DESC, c_custkey) AS by_balance, row_number() OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY length(c_name) DESC, c_custkey) AS by_name FROM customer")
def criteria_decide(spark, sf):
    """Two criteria over one key column give two orders."""
    c = T.load(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_mktsegment", "c_name", F.expr("(cast(floor(c_acctbal) as bigint) + 1000) div 2").alias("balance"), F.length("c_name").alias("size"))
    known = {"account balance": "balance", "length of the name": "size"}
    by = lambda criterion, to: llm_order_by(c, "c_name", criterion, id_col="c_custkey", partition_by=["c_nationkey", "c_mktsegment"], latent=known).select("c_custkey", F.col("rnk").alias(to))
    return by("account balance", "by_balance").join(by("length of the name", "by_name"), "c_custkey")


# ---- measures --------------------------------------------------------------------------------------------------------

_TAU = "sum(sign(a.grade - b.grade)) / {den}"
query("kendall_tau_w5", _R2 + " SELECT a.task_id, a.path_id, round(avg(sign(a.grade - b.grade)), 6) AS tau FROM r a JOIN r b ON a.task_id = b.task_id AND a.path_id = b.path_id AND a.rnk < b.rnk GROUP BY ALL")(
    lambda s, d: (lambda x: M.kendall_tau(x[1], T.truth_of(x[0])).select("task_id", "path_id", F.round("tau", 6).alias("tau")))(value_ranks(s, d))
)
for _n, _f in (("kendall_tau_b_w5", M.kendall_tau), ("kendall_tau_b_sorted_w5", M.kendall_tau_sorted)):
    query(_n, _R2 + " SELECT a.task_id, a.path_id, round(coalesce(sum(sign(a.grade - b.grade)) / nullif(sqrt(count(*)::DOUBLE * count(*) FILTER (a.grade <> b.grade)), 0), 0), 6) AS tau FROM r a JOIN r b ON a.task_id = b.task_id AND a.path_id = b.path_id AND a.rnk < b.rnk GROUP BY ALL")(
        lambda s, d, f=_f: (lambda x: f(x[1], T.truth_of(x[0]), "b").select("task_id", "path_id", F.round("tau", 6).alias("tau")))(value_ranks(s, d))
    )


def ndcg_sql(gain: str) -> str:
    return f"""id AS (SELECT task_id, sum({gain} / log2(1.0 + q)) AS ideal FROM (SELECT *, row_number() OVER (PARTITION BY task_id ORDER BY grade DESC, item_id) AS q FROM i) WHERE q <= 10 GROUP BY ALL),
dc AS (SELECT task_id, path_id, sum({gain} / log2(1.0 + rnk)) AS dcg FROM r WHERE rnk <= 10 GROUP BY ALL),
nd AS (SELECT task_id, path_id, CASE WHEN coalesce(ideal, 0) > 0 THEN round(dcg / ideal, 9) ELSE 0 END AS ndcg, coalesce(ideal, 0) > 0 AS relevant FROM dc LEFT JOIN id USING (task_id))"""


_FIRST = items_sql("w3", "r AS (SELECT task_id, item_id, grade, 'first_stage' AS path_id, pos + 1 AS rnk FROM i), " + ndcg_sql("grade"))


def first_stage(items: DataFrame) -> DataFrame:
    """The unranked input as a baseline."""
    return items.select("task_id", F.lit("first_stage").alias("path_id"), "item_id", (F.col("pos") + 1).cast("bigint").alias("rnk"))


def random_order(items: DataFrame, seed: int = 7) -> DataFrame:
    """A floor: items by hash."""
    w = W.partitionBy("task_id").orderBy(O.md5_number(seed, F.lit("floor"), F.col("item_id").cast("string")), "item_id")
    return items.select("task_id", F.lit("random").alias("path_id"), "item_id", F.row_number().over(w).cast("bigint").alias("rnk"))


def _rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in cols})


@query("ndcg10_w3_bm25", _FIRST + " SELECT task_id, path_id, round(ndcg, 6) AS ndcg, relevant FROM nd")
def ndcg_bm25(spark, sf):
    items = T.workload(spark, sf, "w3")
    return _rounded(M.ndcg_at(first_stage(items), T.truth_of(items)), "ndcg")


query("ndcg10_exp_w5", _R2 + ", " + ndcg_sql("(pow(2.0, grade) - 1)") + " SELECT task_id, path_id, round(ndcg, 6) AS ndcg, relevant FROM nd")(lambda s, d: (lambda x: _rounded(M.ndcg_at(x[1], T.truth_of(x[0]), gain="exp"), "ndcg"))(value_ranks(s, d)))
_ND5 = _R2 + ", " + ndcg_sql("grade")


def quality_points(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """(nDCG per task and path, cost per task and path) of the value paths on W5."""
    items = T.workload(spark, sf, "w5")
    res = run_paths(items, [POINT, EXT_POINT], SimBackend("reasoning"))
    return M.ndcg_at(rankings_of(res), T.truth_of(items)), M.total_cost(usage_of(res))


query("ndcg_mean_ci", _ND5 + " SELECT path_id, count(*) AS n, round(avg(ndcg), 6) AS mean, round(avg(ndcg) - 1.2815515655446004 * coalesce(stddev_samp(ndcg), 0) / sqrt(count(*)), 6) AS lo, round(avg(ndcg) + 1.2815515655446004 * coalesce(stddev_samp(ndcg), 0) / sqrt(count(*)), 6) AS hi FROM nd GROUP BY path_id")(lambda s, d: _rounded(M.mean_ci(quality_points(s, d)[0], "ndcg"), "mean", "lo", "hi"))
query("bootstrap_ci", _ND5 + """, d AS (SELECT path_id, task_id, ndcg, unnest(range(1, 201)) AS round FROM nd),
u AS (SELECT *, CAST('0x' || substr(md5('7|' || round || '|' || task_id), 1, 8) AS BIGINT) / 4294967296.0 AS u FROM d),
w AS (SELECT *, CASE WHEN u < 0.367879 THEN 0 WHEN u < 0.735759 THEN 1 WHEN u < 0.919699 THEN 2 WHEN u < 0.981012 THEN 3 WHEN u < 0.996340 THEN 4 ELSE 5 END AS w FROM u),
m AS (SELECT path_id, round, sum(ndcg * w) / nullif(sum(w), 0) AS m FROM w GROUP BY ALL)
SELECT path_id, round(quantile_cont(m, 0.1), 6) AS lo, round(quantile_cont(m, 0.9), 6) AS hi FROM m GROUP BY path_id""")(lambda s, d: _rounded(M.bootstrap_ci(quality_points(s, d)[0], "ndcg"), "lo", "hi"))
query("spread", _ND5 + ", be AS (SELECT *, ndcg = max(ndcg) OVER (PARTITION BY task_id) AS b FROM nd), al AS (SELECT *, b AND count(*) FILTER (b) OVER (PARTITION BY task_id) = 1 AS alone FROM be) SELECT path_id, round(min(ndcg), 6) AS lo, round(quantile_cont(ndcg, 0.25), 6) AS q1, round(quantile_cont(ndcg, 0.5), 6) AS median, round(quantile_cont(ndcg, 0.75), 6) AS q3, round(max(ndcg), 6) AS hi, round(avg(ndcg), 6) AS mean, count(*) FILTER (alone) AS wins FROM al GROUP BY path_id")(
    lambda s, d: _rounded(M.spread(quality_points(s, d)[0], "ndcg"), "lo", "q1", "median", "q3", "hi", "mean")
)
query("match_rate", _ND5 + ", mn AS (SELECT path_id, avg(ndcg) AS m FROM nd GROUP BY path_id ORDER BY m DESC, path_id LIMIT 1), re AS (SELECT task_id, ndcg AS ref FROM nd JOIN mn USING (path_id)) SELECT avg(CASE WHEN ndcg >= ref THEN 1.0 ELSE 0.0 END) AS share, count(*) AS n FROM nd JOIN re USING (task_id) WHERE path_id = 'ext_point_4'")(
    lambda s, d: (lambda x: M.match_rate(x.where("path_id = 'ext_point_4'"), x))(quality_points(s, d)[0])
)

# curves: what the value paths cost on tasks, and the mean quality at that cost
_CURVE_SQL = _ND5 + f""", {_SPENT}, pc AS (SELECT task_id, path_id, sum(nano_usd) AS cost FROM m GROUP BY ALL),
c AS (SELECT path_id AS path, CAST(cost AS DOUBLE) AS cost, round(avg(ndcg), 6) AS quality FROM nd JOIN pc USING (task_id, path_id) GROUP BY ALL)"""


def _curve(spark: SparkSession, sf: str) -> DataFrame:
    got, cost = quality_points(spark, sf)
    d = got.join(cost, ["task_id", "path_id"]).groupBy(F.col("path_id").alias("path"), F.col("nano_usd").cast("double").alias("cost"))
    return d.agg(F.round(F.avg("ndcg"), 6).alias("quality"))


query("pareto", f"{_CURVE_SQL}, w AS (SELECT *, max(quality) OVER (PARTITION BY path ORDER BY cost, quality DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM c) SELECT path, cost, quality, b IS NULL OR quality > b AS efficient FROM w")(lambda s, d: M.pareto(_curve(s, d), "quality", "cost", "path"))
query("dips", f"{_CURVE_SQL}, w AS (SELECT path, quality, lag(quality) OVER (PARTITION BY path ORDER BY cost) AS b FROM c) SELECT path, count(*) FILTER (quality < b) AS dips FROM w GROUP BY path")(lambda s, d: M.dips(_curve(s, d), "quality", "cost", "path"))
query("log_fit", f"{_CURVE_SQL} SELECT path, round(regr_intercept(quality, ln(cost)), 6) AS a, round(regr_slope(quality, ln(cost)), 6) AS b, round(regr_r2(quality, ln(cost)), 6) AS r2, count(*) AS n FROM c GROUP BY path")(lambda s, d: _rounded(M.log_fit(_curve(s, d), "quality", "cost", ("path",)), "a", "b", "r2"))


@query("leaderboard", _R2 + ", r4 AS (SELECT task_id, item_id, grade, path_id, rnk FROM r UNION ALL SELECT task_id, item_id, grade, 'random', row_number() OVER (PARTITION BY task_id ORDER BY CAST('0x' || substr(md5('7|floor|' || item_id), 1, 8) AS BIGINT), item_id) FROM i UNION ALL SELECT task_id, item_id, grade, 'first_stage', pos + 1 FROM i), " + ndcg_sql("grade").replace("FROM r WHERE", "FROM r4 WHERE") + " SELECT task_id AS dataset, 'medium' AS model, path_id, round(ndcg, 6) AS mean, row_number() OVER (PARTITION BY task_id ORDER BY ndcg DESC, path_id) AS place FROM nd QUALIFY place <= 3")
def leaderboard(spark, sf):
    """The three best of the value paths and the floors, for each source."""
    items = written(spark, sf, "w5")
    r = rankings_of(run_paths(items, [POINT, EXT_POINT], SimBackend("reasoning"), by_wave=False))
    got = M.ndcg_at(r.unionByName(random_order(items)).unionByName(first_stage(items)), T.truth_of(items))
    return _rounded(M.leaderboard(got.select(F.col("task_id").alias("dataset"), F.lit("medium").alias("model"), "path_id", F.col("ndcg").alias("q")), "q"), "mean")


query("latency_waves", _VU + ", w AS (SELECT task_id, path_id, sum(calls) AS c, sum(out_tok) AS o FROM m GROUP BY ALL) SELECT task_id, path_id, round(ceil(c / 100) * (800 + 20 * o / c) / 1000, 6) AS seconds, CAST(ceil(c / 100) AS BIGINT) AS depth FROM w")(lambda s, d: _rounded(M.latency(value_usage(s, d)), "seconds"))
query("mape_paths", _VU + ", a AS (SELECT task_id, path_id, sum(nano_usd) AS actual FROM m GROUP BY ALL), e AS (SELECT path_id, avg(actual) AS est FROM a GROUP BY path_id) SELECT a.path_id, round(avg(abs(est - actual) / actual) * 100, 6) AS mape, count(*) AS n FROM a JOIN e USING (path_id) GROUP BY a.path_id")(
    lambda s, d: (lambda a: _rounded(M.mape(a.select("task_id", "path_id", F.avg("nano_usd").over(W.partitionBy("path_id")).alias("est_nano")), a), "mape"))(M.total_cost(value_usage(s, d)))
)


@query("overlap_at_10", _R2 + " SELECT a.task_id, count(*) AS overlap FROM r a JOIN r b ON a.task_id = b.task_id AND a.item_id = b.item_id AND a.path_id = 'point' AND b.path_id = 'ext_point_4' WHERE a.rnk <= 10 AND b.rnk <= 10 GROUP BY ALL")
def overlap(spark, sf):
    top = value_ranks(spark, sf)[1].where("rnk <= 10")
    a, b = (top.where(F.col("path_id") == p).select("task_id", "item_id") for p in ("point", "ext_point_4"))
    return a.intersect(b).groupBy("task_id").agg(F.count("*").alias("overlap"))


@query("dropped_items", items_sql("w5", "SELECT task_id, item_id FROM i QUALIFY row_number() OVER (PARTITION BY task_id ORDER BY lat DESC, item_id) > 10"))
def dropped(spark, sf):
    items = T.workload(spark, sf, "w5", k=10)
    kept = rankings_of(run_paths(items, [EXT_MERGE], SimBackend()))
    return items.select("task_id", "item_id").exceptAll(kept.select("task_id", "item_id"))


_TAU_W1 = f"""z AS (SELECT *, {score_sql('factual', False)} AS score FROM i), r AS (SELECT task_id, item_id, grade, row_number() OVER (PARTITION BY task_id ORDER BY score DESC, item_id) AS rnk FROM z)
SELECT a.task_id, 'point' AS path_id, round({{}}, 6) AS tau FROM r a JOIN r b ON a.task_id = b.task_id AND a.rnk < b.rnk GROUP BY a.task_id"""
for _n, _w, _v, _e in (("kendall_tau_w1", "w1", "a", "avg(sign(a.grade - b.grade))"), ("kendall_tau_b_w2", "w2", "b", "sum(sign(a.grade - b.grade)) / sqrt(count(*)::DOUBLE * count(*) FILTER (a.grade <> b.grade))")):
    query(_n, items_sql(_w, _TAU_W1.format(_e)))(
        lambda s, d, w=_w, v=_v: (lambda i: M.kendall_tau(rankings_of(run_paths(i, [POINT], SimBackend("factual"))), T.truth_of(i), v).select("task_id", "path_id", F.round("tau", 6).alias("tau")))(T.workload(s, d, w))
    )

_FLOOR = items_sql("w5b", "r AS (SELECT task_id, item_id, grade, 'random' AS path_id, row_number() OVER (PARTITION BY task_id ORDER BY CAST('0x' || substr(md5('7|floor|' || item_id), 1, 8) AS BIGINT), item_id) AS rnk FROM i UNION ALL SELECT task_id, item_id, grade, 'first_stage', pos + 1 FROM i), " + ndcg_sql("grade"))


@query("floors_w5b", _FLOOR + " SELECT task_id, path_id, round(ndcg, 6) AS ndcg FROM nd")
def floors(spark, sf):
    """Input order and random order: what any path must beat."""
    items = T.workload(spark, sf, "w5b")
    return M.ndcg_at(random_order(items).unionByName(first_stage(items)), T.truth_of(items)).select("task_id", "path_id", F.round("ndcg", 6).alias("ndcg"))


# ---- experiments --------------------------------------------------------------------------------------------------------

#: Workload -> noise profile and limit, as the experiments run it.
SETUPS = {"w1": ("factual", None), "w2": ("factual", None), "w3": ("reasoning", 10), "w4": ("reasoning", 10), "w5b": ("reasoning", 10), "w6": ("reasoning", 10), "w7": ("reasoning", 10)}


def static_study(spark: SparkSession, sf: str, w: str, tier: str = "medium", paths: list[PathConfig] | None = None, by_wave: bool = False) -> tuple[DataFrame, DataFrame]:
    """All static paths on a workload: (items, result). Factual workloads have grounded value paths too."""
    scratch = Scratch(spark, "study")
    profile, k = SETUPS[w]
    items = T.workload(spark, sf, w, k=k, texts=profile == "factual")
    if profile == "factual":
        items = with_facts(items, items.select("key", F.col("lat").alias("value")))
    items = scratch.write("items", slim(items, SimBackend(profile, tier)))
    paths = paths or [*PATHS.values(), *([POINT_SEARCH, EXT_POINT_SEARCH] if profile == "factual" else [])]
    return items, O.run_static(items, paths, SimBackend(profile, tier), scratch, by_wave=by_wave)


def quality(w: str, rankings: DataFrame, items: DataFrame) -> DataFrame:
    """(task_id, path_id, quality): tau for attribute orders, nDCG@10 elsewhere, over tasks that have a relevant item."""
    if w in ("w1", "w2"):
        return M.kendall_tau(rankings, T.truth_of(items)).withColumnRenamed("tau", "quality")
    return M.ndcg_at(rankings, T.truth_of(items)).where("relevant").select("task_id", "path_id", F.col("ndcg").alias("quality"))


def study(spark: SparkSession, sf: str, w: str) -> DataFrame:
    """Per static path: mean quality with its interval, calls and dollars per task."""
    items, res = static_study(spark, sf, w)
    cost = M.total_cost(usage_of(res)).groupBy("path_id").agg(F.avg("calls").alias("calls"), (F.avg("nano_usd") / 1e9).alias("usd"))
    return M.mean_ci(quality(w, rankings_of(res), items), "quality").join(cost, "path_id")


for _w in SETUPS:
    query(f"study_{_w}")(lambda s, d, w=_w: study(s, d, w))
query("log_fit_w4")(lambda s, d: M.log_fit(study(s, d, "w4"), "mean", "usd"))
query("spread_w3")(lambda s, d: (lambda x: M.spread(quality("w3", rankings_of(x[1]), x[0]), "quality"))(static_study(s, d, "w3")))


def cells(d: DataFrame, *names: str) -> DataFrame:
    """Task ids that hold the setting too, so that all settings are decided in the same jobs."""
    return d.withColumn("task_id", F.concat_ws("|", *names, "task_id"))


def sweep(spark: SparkSession, sf: str, w: str, tier: str = "medium", budgets: int | list[int] = 4, judges: dict[str, SimBackend] | None = None, samples: tuple[int, ...] = (O.SAMPLE,), policies: tuple[str, ...] = ("judge", "consensus")) -> tuple[DataFrame, DataFrame]:
    """Both policies over a grid of budgets: (static (task_id, path_id, quality, nano_usd), chosen (policy, sample, budget_nano, task_id, quality, nano_usd, probe_nano)).

    The simulator answers a request the same way whenever it is asked, so a path's full run is the same under every budget: it is made
    once, as is the probe; what differs is which runs a budget and a policy take, and their fusion. ``budgets``: nano-dollars per task, or how many, on a log
    grid from the cheapest path's mean estimate to the sum of all.
    """
    profile, k = SETUPS[w]
    scratch, backend, paths = Scratch(spark, "sweep"), SimBackend(profile, tier), list(PATHS.values())
    items = scratch.write("items", T.workload(spark, sf, w, k=k, texts=False))
    full = O.run_static(items, paths, backend, scratch, "full")
    truth, table = T.truth_of(items), candidates_frame(spark, paths)
    length = F.avg(measured(items)).alias
    out = None
    for n in samples:
        own = Scratch(spark, "sweep-sample")
        sample = own.write("sample", O.sample_items(items, n))
        probe = O.run_static(sample, paths, backend, own, "probe")
        sizes = items.groupBy("task_id").agg(F.count("*").alias("n"), F.first("k").alias("k"), length("chars")).join(sample.groupBy("task_id").agg(F.count("*").alias("s"), length("sample_chars")), "task_id")
        spent = M.total_cost(usage_of(probe))
        est = own.write("est", estimate(spent, sizes, table, "per_call", PRICES[tier][0]).select("task_id", "path_id", "est_nano"))
        if isinstance(budgets, int):
            # two numbers
            g = est.groupBy("path_id").agg(F.avg("est_nano").alias("e")).agg(F.min("e").alias("lo"), F.sum("e").alias("hi")).first()
            budgets = [int(g["lo"] * (1.05 * g["hi"] / g["lo"]) ** (i / (budgets - 1)) * 1.02) for i in range(budgets)]
        grid = spark.createDataFrame([(b,) for b in budgets], "budget_nano bigint")
        fits = est.crossJoin(F.broadcast(grid)).withColumn("left_nano", F.col("budget_nano").cast("double"))  # a few budgets
        fits = own.write("fits", cells(fits.withColumn("fits", F.col("est_nano") <= F.col("left_nano")), "budget_nano").drop("budget_nano"))
        spread_out = lambda d: cells(d.crossJoin(F.broadcast(grid)), "budget_nano").drop("budget_nano")
        shown = own.write("shown", spread_out(sample))
        ranks = own.write("ranks", spread_out(rankings_of(probe)).join(fits.where("fits").select("task_id", "path_id"), ["task_id", "path_id"]))
        choices = {}
        for policy in policies:
            if policy == "judge":
                for name, judge in (judges or {"judge": backend}).items():
                    choices[name] = O.judge_choice(shown, ranks, fits, judge).select("task_id", "path_id")
            else:
                scored = O.agreement(ranks, fuse_rrf(ranks)).join(fits.where("fits"), ["task_id", "path_id"])
                choices[policy] = O.greedy_fit(scored)
        every = None
        for name, c in choices.items():
            c = c.select(F.lit(name).alias("policy"), "task_id", "path_id")
            every = c if every is None else every.unionByName(c)
        # where nothing fits a task takes its cheapest path
        cheapest = fits.groupBy("task_id").agg(F.min_by("path_id", F.struct("est_nano", "path_id")).alias("path_id"), F.max("fits").alias("any")).where("not any").drop("any")
        every = every.unionByName(cheapest.crossJoin(F.broadcast(spark.createDataFrame([(n,) for n in choices], "policy string"))).select("policy", "task_id", "path_id"))
        every = own.write("choices", every.withColumn("budget_nano", F.substring_index("task_id", "|", 1).cast("bigint")).withColumn("task", F.expr("substr(task_id, instr(task_id, '|') + 1)")))
        runs = rankings_of(full).withColumnRenamed("task_id", "task").join(every, ["task", "path_id"])
        fused = fuse_rrf(runs.withColumn("task_id", F.concat_ws("|", "policy", "task_id")))
        cell_truth = truth.withColumnRenamed("task_id", "task").join(every.select("policy", "task_id", "task").distinct(), "task").select(F.concat_ws("|", "policy", "task_id").alias("task_id"), "item_id", "grade")
        got = quality(w, fused if k is None else fused.where(F.col("rnk") <= k), cell_truth).drop("path_id")
        cost = every.join(M.total_cost(usage_of(full)).withColumnRenamed("task_id", "task"), ["task", "path_id"]).groupBy("policy", "budget_nano", "task", "task_id").agg(F.sum("nano_usd").alias("nano_usd"))
        probe_cost = spent.groupBy(F.col("task_id").alias("task")).agg(F.sum("nano_usd").alias("probe_nano"))
        part = cost.withColumn("task_id", F.concat_ws("|", "policy", "task_id")).join(got, "task_id").join(probe_cost, "task")
        part = own.write("chosen", part.select("policy", F.lit(n).alias("sample"), "budget_nano", F.col("task").alias("task_id"), "quality", "nano_usd", "probe_nano"))
        out = part if out is None else out.unionByName(part)
    static = quality(w, rankings_of(full), items).join(M.total_cost(usage_of(full)).select("task_id", "path_id", "nano_usd"), ["task_id", "path_id"])
    return static, out


def curve(chosen: DataFrame) -> DataFrame:
    """Per policy, sample size and budget: mean quality with its interval, dollars per task for ranking and for the probe."""
    by = ("policy", "sample", "budget_nano")
    return M.mean_ci(chosen, "quality", by).join(chosen.groupBy(*by).agg((F.avg("nano_usd") / 1e9).alias("usd"), (F.avg("probe_nano") / 1e9).alias("probe_usd")), list(by))


for _w in ("w3", "w4", "w5b", "w6", "w7"):
    query(f"budget_sweep_{_w}")(lambda s, d, w=_w: curve(sweep(s, d, w)[1]).drop("sample"))


@query("pareto_w4")
def pareto_w4(spark, sf):
    """Measured points, static paths and both policies' budgets, and which of them no cheaper one reaches."""
    static, chosen = sweep(spark, sf, "w4")
    points = static.groupBy(F.col("path_id").alias("name")).agg(F.avg("quality").alias("quality"), (F.avg("nano_usd") / 1e9).alias("usd"))
    more = chosen.groupBy(F.concat_ws("@", "policy", "budget_nano").alias("name")).agg(F.avg("quality").alias("quality"), (F.avg("nano_usd") / 1e9).alias("usd"))
    return M.pareto(points.unionByName(more).withColumn("all", F.lit("w4")), "quality", "usd", "all").drop("all")


query("dips_w4")(lambda s, d: M.dips(curve(sweep(s, d, "w4", budgets=6)[1]), "mean", "budget_nano", "policy"))


@query("main_table_w4")
def main_table(spark, sf):
    """Per tier: the three best static paths and the best of each policy over the budgets."""
    out = None
    for tier in TIERS:
        static, chosen = sweep(spark, sf, "w4", tier)
        three = M.leaderboard(static.select(F.lit("w4").alias("dataset"), F.lit(tier).alias("model"), "path_id", "quality"), "quality").select("model", F.concat(F.lit("static "), "place").alias("what"), F.col("path_id").alias("name"), "mean")
        best = curve(chosen).groupBy("policy").agg(F.max("mean").alias("mean"), F.max_by("budget_nano", "mean").alias("b")).select(F.lit(tier).alias("model"), F.col("policy").alias("what"), F.concat(F.lit("budget "), "b").alias("name"), "mean")
        rows = three.unionByName(best)
        out = rows if out is None else out.unionByName(rows)
    return out


def cost_error(spark: SparkSession, sf: str, w: str, tier: str = "medium") -> DataFrame:
    """Mean absolute error of the estimates from 20 items, per path and form."""
    profile, k = SETUPS[w]
    items = T.workload(spark, sf, w, k=k, texts=False)
    backend, paths, scratch = SimBackend(profile, tier), list(PATHS.values()), Scratch(spark, "cost")
    items = scratch.write("items", items)
    sample = scratch.write("sample", O.sample_items(items))
    probe = M.total_cost(usage_of(O.run_static(sample, paths, backend, scratch, "probe")))
    actual = M.total_cost(usage_of(O.run_static(items, paths, backend, scratch, "actual")))
    length = F.avg(measured(items))
    sizes = items.groupBy("task_id").agg(F.count("*").alias("n"), F.first("k").alias("k"), length.alias("chars")).join(sample.groupBy("task_id").agg(F.count("*").alias("s"), length.alias("sample_chars")), "task_id")
    out = [M.mape(estimate(probe, sizes, candidates_frame(spark, paths), form, PRICES[tier][0]), actual).withColumn("form", F.lit(form)) for form in ("ratio", "per_call")]
    return out[0].unionByName(out[1]).withColumn("tier", F.lit(tier))


for _w in ("w3", "w6", "w7"):
    query(f"cost_error_{_w}")(lambda s, d, w=_w: cost_error(s, d, w))


@query("cost_error_w4")
def cost_error_w4(spark, sf):
    out = None
    for tier in TIERS:
        part = cost_error(spark, sf, "w4", tier)
        out = part if out is None else out.unionByName(part)
    return out


@query("latency_w4")
def latency_w4(spark, sf):
    """Mean depth in sequential calls and seconds: each path, and both policies at the third of four budgets (their runs go side by side)."""
    items, res = static_study(spark, sf, "w4", by_wave=True)
    lat = M.latency(usage_of(res))
    out = lat.groupBy("path_id").agg(F.avg("depth").alias("depth"), F.avg("seconds").alias("seconds"))
    for policy in ("judge", "consensus"):
        r = O.optimize(items, T.tasks_of(items, k=10), BUDGET, SimBackend("reasoning"), policy=policy, inquiry=False, on_infeasible="cheapest")
        own = r.choices.join(lat, ["task_id", "path_id"]).groupBy("task_id").agg(F.max("depth").alias("depth"), F.max("seconds").alias("seconds"))
        out = out.unionByName(own.agg(F.avg("depth").alias("depth"), F.avg("seconds").alias("seconds")).select(F.lit(policy).alias("path_id"), "depth", "seconds"))
    return out


@query("latency_bound_w5")
def latency_bound(spark, sf):
    """What a bound on waiting time leaves to choose from."""
    r = optimized(spark, sf, "w5", "consensus", 10**12, max_latency_s=60)
    return r.estimates.where("fits").groupBy("path_id").agg(F.count("*").alias("tasks"))


@query("call_ratios_w3")
def call_ratios(spark, sf):
    """Full sorts: votes against plain quick sort, bubble against merge."""
    items = T.workload(spark, sf, "w3")
    c = M.total_cost(usage_of(run_paths(items, [QUICK, QUICK_3, EXT_BUBBLE, EXT_MERGE], SimBackend("clean"))))
    return M.ratio(c, "quick_3", "quick").unionByName(M.ratio(c, "ext_bubble_4", "ext_merge_4"))


@query("judge_ablation_w4")
def judge_ablation(spark, sf):
    """Share of tasks that match or beat the best static path, by judge and budget, beside rank fusion."""
    static, chosen = sweep(spark, sf, "w4", "small", judges={f"judge {t}": SimBackend("reasoning", t) for t in TIERS})
    best = static.groupBy("path_id").agg(F.avg("quality").alias("m")).orderBy(F.col("m").desc(), "path_id").limit(1)
    ref = static.join(F.broadcast(best.select("path_id")), "path_id").select("task_id", F.col("quality").alias("ref"))
    return chosen.join(ref, "task_id").groupBy("policy", "budget_nano").agg(F.avg((F.col("quality") >= F.col("ref")).cast("double")).alias("share"), F.avg("quality").alias("mean"), F.count("*").alias("n"))


query("sample_size_w4")(lambda s, d: curve(sweep(s, d, "w4", budgets=[BUDGET], samples=(16, 20, 24, 28))[1]).drop("budget_nano"))


# ---- retrieval, surfaces, streams ---------------------------------------------------------------------------------------

query("bm25_top100", f"WITH {BM25.replace('WORDS', 'w')} SELECT query_id, doc_id, score, rnk FROM top")(lambda s, d: bm25_topn(T.load(s, d, "documents").select("doc_id", "text"), T.load(s, d, "benchmark").select(F.col("item_id").alias("query_id"), "text")))
_COS = "round(list_dot_product({a}::DOUBLE[], {b}::DOUBLE[]) / sqrt(list_dot_product({a}::DOUBLE[], {a}::DOUBLE[]) * list_dot_product({b}::DOUBLE[], {b}::DOUBLE[])), 6)"
query("vector_top100", f"WITH x AS (SELECT q.vec_id AS query_id, e.vec_id, {_COS.format(a='e.embedding', b='q.embedding')} AS score FROM embeddings e, embeddings q WHERE q.vec_id % 100 = 0 AND e.vec_id <> q.vec_id) SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rnk FROM x QUALIFY rnk <= 100")(
    lambda s, d: (lambda e: vector_topn(e, e.where("vec_id % 100 = 0")))(T.load(s, d, "embeddings"))
)


def proxy_w14(spark: SparkSession, sf: str) -> DataFrame:
    """Rank all vectors for each of ten labels from the scores (same label: 10, else 0) of every tenth."""
    e = T.load(spark, sf, "embeddings")
    labels = spark.range(10).select(F.concat(F.lit("label-"), "id").alias("task_id"), F.col("id").alias("want"))
    seeds = e.where("vec_id % 10 = 0").crossJoin(labels).select("task_id", "vec_id", F.when(F.col("label") == F.col("want"), 10).otherwise(0).alias("score"))  # ten tasks
    return proxy_rank(e.select("vec_id", "embedding"), seeds)


query("proxy_rank_w14")(lambda s, d: proxy_w14(s, d).select("task_id", "item_id", "rnk"))


@query("proxy_ndcg_w14")
def proxy_ndcg(spark, sf):
    """nDCG@10 of the light ranker and of the input order; relevant: the same label."""
    r = proxy_w14(spark, sf).select("task_id", F.lit("proxy").alias("path_id"), "item_id", "rnk")
    e = T.load(spark, sf, "embeddings")
    truth = r.select("task_id", "item_id").join(e.select(F.col("vec_id").alias("item_id"), "label"), "item_id").select("task_id", "item_id", (F.concat(F.lit("label-"), "label") == F.col("task_id")).cast("bigint").alias("grade"))
    plain = r.select("task_id", F.lit("input").alias("path_id"), "item_id", (F.col("item_id") + 1).alias("rnk"))
    return M.mean_ci(M.ndcg_at(r.unionByName(plain), truth), "ndcg")


@query("example1_sql", "SELECT doc_id, row_number() OVER (ORDER BY n_chars DESC, doc_id) AS rnk FROM documents WHERE lang = 'en' AND n_chars BETWEEN 200 AND 4000 QUALIFY rnk <= 10")
def example1(spark, sf):
    """Filter first, then the semantic order with a limit."""
    T.load(spark, sf, "documents").createOrReplaceTempView("passages")
    text = "SELECT doc_id, text, n_chars AS hidden FROM passages WHERE lang = 'en' AND n_chars BETWEEN 200 AND 4000 ORDER BY LLM_ORDER_BY(text, 'how much the passage says about the topic') DESC LIMIT 10"
    return semantic_sql(spark, text, id_col="doc_id", latent="hidden", path=EXT_MERGE).select("doc_id", F.col("rnk").cast("bigint").alias("rnk"))


@query("example2_sql", "SELECT doc_id, row_number() OVER (ORDER BY 2 * quality + 1 - toxic DESC, doc_id) AS rnk FROM documents JOIN labels USING (doc_id) WHERE source = 'src3' AND text <> ''")
def example2(spark, sf):
    """Rank all reviews of one source."""
    T.load(spark, sf, "documents").createOrReplaceTempView("reviews")
    T.load(spark, sf, "labels").createOrReplaceTempView("review_labels")
    text = "SELECT r.doc_id, r.text, 2 * quality + 1 - toxic AS hidden FROM reviews r JOIN review_labels l ON r.doc_id = l.doc_id WHERE r.source = 'src3' ORDER BY LLM_ORDER_BY(text, 'good and civil writing') DESC"
    return semantic_sql(spark, text, id_col="doc_id", latent="hidden", path=QUICK_3).select("doc_id", "rnk")


@query("udtf_rank", exact_sql("w5", 5))
def udtf_rank(spark, sf):
    register_udtf(spark)
    T.workload(spark, sf, "w5").select("task_id", "item_id", "key", "lat").createOrReplaceTempView("udtf_items")
    return spark.sql("SELECT task_id, item_id, CAST(rnk AS BIGINT) AS rnk FROM semantic_rank(TABLE(udtf_items) PARTITION BY (task_id), 'good writing', 5)")


@query("scalar_score_w5", items_sql("w5", f"SELECT task_id, item_id, CAST({score_sql('reasoning', False)} AS INT) AS score FROM i"))
def scalar_score(spark, sf):
    score = semantic_score(spark, SimBackend("reasoning"))
    return T.workload(spark, sf, "w5").select("task_id", "item_id", score("task_id", "item_id", "key", "lat").alias("score"))


_NULLED = "x AS (SELECT c_custkey AS item_id, c_nationkey, CASE WHEN c_custkey % 7 = 0 THEN NULL WHEN c_custkey % 11 = 0 THEN '' ELSE c_name END AS key, CAST(round(c_acctbal) AS BIGINT) AS lat FROM customer)"
for _n in ("last", "first"):
    _flag = "(coalesce(key, '') = '')" if _n == "last" else "(coalesce(key, '') <> '')"

    @query(f"null_keys_{_n}", f"WITH {_NULLED} SELECT item_id, c_nationkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY {_flag}, CASE WHEN coalesce(key, '') <> '' THEN lat END DESC, item_id) AS rnk FROM x QUALIFY rnk <= 55")
    def _nulls(spark, sf, where=_n):
        c = F.col("c_custkey")
        d = T.load(spark, sf, "customer")
        d = d.select(c.alias("item_id"), "c_nationkey", F.when(c % 7 == 0, F.lit(None)).when(c % 11 == 0, F.lit("")).otherwise(F.col("c_name")).alias("key"), F.round("c_acctbal").cast("bigint").alias("lat"))
        out = llm_order_by(d, "key", "account balance", id_col="item_id", partition_by="c_nationkey", latent="lat", nulls=where, limit=55)
        return out.select("item_id", "c_nationkey", "rnk")


@query("ties_by_id", "SELECT c_custkey AS item_id, row_number() OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY c_custkey) AS rnk FROM customer")
def ties_by_id(spark, sf):
    d = T.load(spark, sf, "customer").select(F.col("c_custkey").alias("item_id"), "c_nationkey", "c_mktsegment", F.col("c_name").alias("key"), F.lit(5).alias("lat"))
    return llm_order_by(d, "key", "nothing tells them apart", id_col="item_id", partition_by=["c_nationkey", "c_mktsegment"], latent="lat", path=QUICK_3).select("item_id", "rnk")


@query("dedup_keys", "WITH x AS (SELECT c_custkey AS item_id, c_nationkey, c_mktsegment AS key FROM customer), k AS (SELECT c_nationkey, key, length(key) AS lat, min(item_id) AS f FROM x GROUP BY ALL) SELECT item_id, row_number() OVER (PARTITION BY c_nationkey ORDER BY lat DESC, f, item_id) AS rnk FROM x JOIN k USING (c_nationkey, key)")
def dedup_keys(spark, sf):
    d = T.load(spark, sf, "customer").select(F.col("c_custkey").alias("item_id"), "c_nationkey", F.col("c_mktsegment").alias("key"), F.length("c_mktsegment").alias("lat"))
    return llm_order_by(d, "key", "longest name", id_col="item_id", partition_by="c_nationkey", latent="lat", dedup_keys=True).select("item_id", "rnk")


@query("cache_hits", "SELECT 'first' AS run, false AS hit, count(*) AS n FROM customer UNION ALL SELECT 'second', true, count(*) FROM customer UNION ALL SELECT 'other criterion', false, count(*) FROM customer")
def cache_hits(spark, sf):
    """The same wave twice: the second run pays nothing; another criterion pays again."""
    items, scratch = T.workload(spark, sf, "w1"), Scratch(spark, "cache")
    cache = ResponseCache(spark, scratch.path("responses"))
    out = None
    for name, backend in (("first", SimBackend("factual")), ("second", SimBackend("factual")), ("other criterion", SimBackend("factual").about("another"))):
        _, got = score_waves(items, POINT, backend, cache=cache, scratch=Scratch(spark, "cache-run"))
        run = got.groupBy("hit").agg(F.count("*").alias("n")).select(F.lit(name).alias("run"), "hit", "n")
        out = run if out is None else out.unionByName(run)
    return out


@query("probe_cache_hits_w5", items_sql("w5", "SELECT task_id, least(count(*), 20) AS hits, count(*) - least(count(*), 20) AS calls FROM i WHERE key <> '' GROUP BY task_id"))
def probe_cache_hits(spark, sf):
    """With single scores as the one candidate, the final run asks only what the probe has not asked."""
    items = written(spark, sf, "w5")
    r = O.optimize(items, T.tasks_of(items), 10**12, SimBackend("reasoning"), inquiry=False, candidates=[POINT])
    return r.ledger.where("phase = 'ranking'").select("task_id", "hits", "calls")


query("stream_topk_hourly", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS task_id, event_id AS item_id, row_number() OVER (PARTITION BY date_trunc('hour', ts) ORDER BY CAST(round(value * 1000) AS BIGINT) DESC, event_id) AS rnk FROM events WHERE event_type <> '' QUALIFY rnk <= 3")(lambda s, d: stream_topk(s, d, 3))


@query("stream_session_rank", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g), c AS (SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, no) SELECT user_id, n, row_number() OVER (PARTITION BY user_id ORDER BY n DESC, start) AS rnk FROM c")
def stream_session_rank(spark, sf):
    s = stream_sessions(spark, sf)
    w = W.partitionBy("user_id").orderBy(F.col("n").desc(), "start")
    return s.select("user_id", "n", F.row_number().over(w).cast("bigint").alias("rnk"))


# ---- around the methods ------------------------------------------------------------------------------------------------

query("split_merge_w1", exact_sql("w1"))(lambda s, d: split_merge(T.workload(s, d, "w1"), SimBackend(), 5)[0].drop("path_id"))


@query("as_of_price", "WITH p AS (SELECT user_id, ts, value AS price FROM events WHERE event_type = (SELECT min(event_type) FROM events)), e AS (SELECT event_id, user_id, ts FROM events WHERE event_type <> (SELECT min(event_type) FROM events)) SELECT event_id, (SELECT max_by(price, (ts, price)) FROM p WHERE p.user_id = e.user_id AND p.ts <= e.ts) AS price FROM e")
def as_of_price(spark, sf):
    """For each event the value of the user's last event of the first type."""
    e = T.load(spark, sf, "events")
    first = e.agg(F.min("event_type").alias("t"))
    e = e.crossJoin(F.broadcast(first))  # one row
    return as_of_join(e.where("event_type <> t").select("event_id", "user_id", "ts"), e.where("event_type = t").select("user_id", "ts", "value"), "user_id", "ts", "value", "price").select("event_id", "price")


query("events_within_an_hour", "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")(
    lambda s, d: (lambda e: interval_join(e, e, "user_id", "ts", 3600).groupBy("user_id").agg(F.count("*").alias("pairs")))(T.load(s, d, "events").select("user_id", "ts"))
)
query("weighted_criteria_w5", _R2 + ", wf AS (SELECT task_id, item_id, sum(1000000000000 // (60 + rnk) * CASE path_id WHEN 'point' THEN 3 ELSE 1 END) AS f FROM r GROUP BY ALL) SELECT task_id, item_id, row_number() OVER (PARTITION BY task_id ORDER BY f DESC, item_id) AS rnk FROM wf")(
    lambda s, d: rank_by_many(value_ranks(s, d)[1], {"point": 3, "ext_point_4": 1})
)
@query("reply_repair", "WITH x AS (SELECT conv_id AS req_id, list(DISTINCT turn ORDER BY turn) AS s FROM conversations GROUP BY conv_id) SELECT req_id, array_to_string(CASE req_id % 4 WHEN 0 THEN list_reverse(s) WHEN 1 THEN list_concat([s[len(s)]], s[1:len(s) - 1]) ELSE s END, ',') AS fixed, req_id % 4 <> 0 AS repaired FROM x")
def reply_repair(spark, sf):
    """Replies that order the turns of a conversation: right ones, ones with an unknown and a repeated number, no JSON, a number for a list."""
    c = T.load(spark, sf, "conversations").groupBy(F.col("conv_id").alias("req_id")).agg(F.array_sort(F.collect_set(F.col("turn").cast("bigint"))).alias("shown"))
    last, how = F.element_at("shown", -1), F.col("req_id") % 4
    right, wrong = F.array_join(F.reverse("shown"), ","), F.concat_ws(",", last, F.lit(-9), last)
    reply = F.when(how == 0, F.concat(F.lit('{"order": ['), right, F.lit("]}"))).when(how == 1, F.concat(F.lit('{"order": ['), wrong, F.lit("]}"))).when(how == 2, "no json").otherwise('{"order": "3"}')
    return parse_orders(c.withColumn("reply", reply)).select("req_id", F.array_join(F.transform("order", lambda x: x.cast("string")), ",").alias("fixed"), "repaired")


query("fit_batch_w5", items_sql("w5", "x AS (SELECT task_id, length(key) AS c, row_number() OVER (PARTITION BY task_id ORDER BY length(key) DESC) AS q FROM i), y AS (SELECT *, sum(c) OVER (PARTITION BY task_id ORDER BY q) AS t FROM x WHERE q <= 8) SELECT task_id, CAST(greatest(coalesce(max(q) FILTER (ceil((t + 200) / 4.0) <= 6000), 1), 1) AS INT) AS m FROM y GROUP BY task_id"))(
    lambda s, d: fit_batch(T.workload(s, d, "w5").select("task_id", F.length("key").alias("chars")), 8, 6000)
)


@query("formats_w2", exact_sql("w2").replace("SELECT task_id, item_id, row_number()", "SELECT format, task_id, item_id, row_number()", 1).replace("FROM i WHERE", "FROM i, (VALUES ('parquet'), ('orc'), ('json'), ('csv')) f(format) WHERE").replace("PARTITION BY task_id ORDER BY lat", "PARTITION BY format, task_id ORDER BY lat"))
def formats(spark, sf):
    """A ranking written and read in every format."""
    from semrank.sources.files import FORMATS, read_items, write_ranking

    scratch, out = Scratch(spark, "formats"), None
    found = scratch.write("ranked", ranked(spark, sf, "w2", EXT_MERGE))
    for fmt in FORMATS:
        write_ranking(found, scratch.path(fmt), fmt)
        back = read_items(spark, scratch.path(fmt), fmt, "task_id string, item_id bigint, rnk bigint").withColumn("format", F.lit(fmt))
        out = back if out is None else out.unionByName(back)
    return out


@query("window_ranks_w5", _R2 + " SELECT task_id, path_id, item_id, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS upto, lag(item_id) OVER w AS ahead FROM r WINDOW w AS (PARTITION BY task_id, path_id ORDER BY rnk)")
def window_ranks(spark, sf):
    """What window functions make of rankings."""
    w = W.partitionBy("task_id", "path_id").orderBy("rnk")
    r = value_ranks(spark, sf)[1]
    return r.select("task_id", "path_id", "item_id", F.ntile(4).over(w).cast("bigint").alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("upto"), F.lag("item_id").over(w).alias("ahead"))


__all__ = ["ORACLES", "QUERIES", "calls", "exact_calls"]
