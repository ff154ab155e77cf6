"""Measures of quality, cost and latency as DataFrame expressions.

Rankings are (task_id, path_id, item_id, rnk); truth is (task_id, item_id, grade). Ties in truth count for
neither side in tau-a and are corrected for in tau-b.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

KEY = ("task_id", "path_id")
IN_FLIGHT = 100
Z80 = 1.2815515655446004


def kendall_tau(rankings: DataFrame, truth: DataFrame, variant: str = "a") -> DataFrame:
    """tau per (task, path). Pairs meet by task and path, so the cost is quadratic in a task's items: for large tasks use ``kendall_tau_sorted``."""
    r = rankings.join(truth, ["task_id", "item_id"]).select(*KEY, "rnk", "grade")
    b = r.select(*KEY, F.col("rnk").alias("rnk2"), F.col("grade").alias("grade2"))
    # ahead in the ranking (smaller rank) should mean a higher grade
    s = r.join(b, list(KEY)).where("rnk < rnk2").select(*KEY, F.signum(F.col("grade") - F.col("grade2")).alias("s"))
    g = s.groupBy(*KEY).agg(F.sum("s").alias("d"), F.count("*").alias("pairs"), F.count_if(F.col("s") == 0).alias("tied"))
    return g.select(*KEY, _tau(F.col("d"), F.col("pairs"), F.col("tied"), variant).alias("tau"))


def _tau(d: Column, pairs: Column, tied: Column, variant: str) -> Column:
    if variant == "a":
        return d / pairs
    # the ranking itself has no ties
    return F.when(pairs > tied, d / F.sqrt(pairs.cast("double") * (pairs - tied))).otherwise(F.lit(0.0))


def kendall_tau_sorted(rankings: DataFrame, truth: DataFrame, variant: str = "a") -> DataFrame:
    """The same in n log n: discordant pairs are inversions, counted by merging in one worker per (task, path)."""
    r = rankings.join(truth, ["task_id", "item_id"]).select(*KEY, "rnk", "grade")

    def count(f):
        import pandas as pd

        grades = [-int(x) for x in f.sort_values("rnk")["grade"]]
        n, wrong = len(grades), 0

        def sort(x):
            nonlocal wrong
            if len(x) < 2:
                return x
            a, b, out = sort(x[: len(x) // 2]), sort(x[len(x) // 2 :]), []
            i = j = 0
            while i < len(a) and j < len(b):
                if a[i] <= b[j]:
                    out.append(a[i])
                    i += 1
                else:
                    wrong += len(a) - i
                    out.append(b[j])
                    j += 1
            return out + a[i:] + b[j:]

        sort(grades)
        tied = sum(c * (c - 1) // 2 for c in pd.Series(grades).value_counts())
        pairs = n * (n - 1) // 2
        return pd.DataFrame({"task_id": [f["task_id"].iloc[0]], "path_id": [f["path_id"].iloc[0]], "d": [pairs - tied - 2 * wrong], "pairs": [pairs], "tied": [int(tied)]})

    g = r.groupBy(*KEY).applyInPandas(count, "task_id string, path_id string, d bigint, pairs bigint, tied bigint").where("pairs > 0")
    return g.select(*KEY, _tau(F.col("d"), F.col("pairs"), F.col("tied"), variant).alias("tau"))


def _gain(grade: Column, gain: str) -> Column:
    return grade.cast("double") if gain == "linear" else F.pow(F.lit(2.0), grade) - 1


def ndcg_at(rankings: DataFrame, truth: DataFrame, at: int = 10, gain: str = "linear") -> DataFrame:
    """nDCG@at per (task, path). Items without a grade count 0; a task without a relevant item gets 0 and relevant = false.
    Rounded to 9 places, so that the order of summation decides no tie."""
    place = lambda rank: F.log2(rank + 1.0)
    best = truth.select("task_id", "grade", F.row_number().over(W.partitionBy("task_id").orderBy(F.col("grade").desc(), "item_id")).alias("r")).where(F.col("r") <= at)
    ideal = best.groupBy("task_id").agg(F.sum(_gain(F.col("grade"), gain) / place(F.col("r"))).alias("ideal"))
    top = rankings.where(F.col("rnk") <= at).join(truth, ["task_id", "item_id"], "left")
    got = top.groupBy(*KEY).agg(F.sum(_gain(F.coalesce("grade", F.lit(0)), gain) / place(F.col("rnk"))).alias("dcg"))
    out = got.join(ideal, "task_id", "left")
    has = F.coalesce(F.col("ideal"), F.lit(0.0)) > 0
    return out.select(*KEY, F.when(has, F.round(F.col("dcg") / F.col("ideal"), 9)).otherwise(F.lit(0.0)).alias("ndcg"), has.alias("relevant"))


def mean_ci(df: DataFrame, value: str, by: tuple[str, ...] = ("path_id",), z: float = Z80) -> DataFrame:
    """Mean over tasks with a normal 80% interval; one task has an interval of width 0."""
    g = df.groupBy(*by).agg(F.avg(value).alias("mean"), F.count(value).alias("n"), F.coalesce(F.stddev_samp(value), F.lit(0.0)).alias("sd"))
    half = z * F.col("sd") / F.sqrt("n")
    return g.select(*by, "n", "mean", (F.col("mean") - half).alias("lo"), (F.col("mean") + half).alias("hi"))


def bootstrap_ci(df: DataFrame, value: str, by: tuple[str, ...] = ("path_id",), id_col: str = "task_id", rounds: int = 200, level: float = 0.8, seed: int = 7) -> DataFrame:
    """Mean with a seeded bootstrap interval: in each round a task counts as often as MD5 draws it (Poisson weights)."""
    u = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), "round", id_col)), 1, 8), 16, 10).cast("double") / 4294967296.0
    # inverse of the Poisson(1) distribution, fixed values of its cumulative sums
    weight = F.when(u < 0.367879, 0).when(u < 0.735759, 1).when(u < 0.919699, 2).when(u < 0.981012, 3).when(u < 0.996340, 4).otherwise(5)
    d = df.select(*by, id_col, value, F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round")).withColumn("w", weight)
    means = d.groupBy(*by, "round").agg(F.try_divide(F.sum(F.col(value) * F.col("w")), F.sum("w")).alias("m"))
    tail = (1 - level) / 2
    return means.groupBy(*by).agg(F.percentile("m", F.lit(tail)).alias("lo"), F.percentile("m", F.lit(1 - tail)).alias("hi"))


def usage_rollup(usage: DataFrame) -> DataFrame:
    """Calls, tokens and nano-dollars by path, by path and operation, and in all (null: all)."""
    return usage.rollup("path_id", "op").agg(*[F.sum(c).alias(c) for c in ("calls", "in_tok", "out_tok", "nano_usd")])


def usage_cube(usage: DataFrame) -> DataFrame:
    return usage.cube("path_id", "op").agg(F.sum("calls").alias("calls"), F.countDistinct("task_id").alias("tasks"))


def total_cost(usage: DataFrame, by: tuple[str, ...] = KEY) -> DataFrame:
    return usage.groupBy(*by).agg(F.sum("calls").alias("calls"), F.sum("nano_usd").alias("nano_usd"))


def mape(estimates: DataFrame, actual: DataFrame, by: tuple[str, ...] = ("path_id",)) -> DataFrame:
    """Mean absolute error of estimated cost in percent; actual: (task_id, path_id, nano_usd) without cache hits."""
    d = estimates.select(*KEY, "est_nano").join(actual.select(*KEY, F.col("nano_usd").alias("actual")), list(KEY)).where("actual > 0")
    return d.groupBy(*by).agg((F.avg(F.abs(F.col("est_nano") - F.col("actual")) / F.col("actual")) * 100).alias("mape"), F.count("*").alias("n"))


def latency(usage: DataFrame, in_flight: int = IN_FLIGHT, base_ms: int = 800, ms_per_token: int = 20) -> DataFrame:
    """Seconds and sequential depth per (task, path): waves follow one another, a wave runs ``in_flight`` calls at once."""
    wave = usage.groupBy(*KEY, "wave").agg(F.sum("calls").alias("calls"), F.sum("out_tok").alias("out_tok"))
    turns = F.ceil(F.col("calls") / in_flight)
    each = base_ms + F.coalesce(F.try_divide(ms_per_token * F.col("out_tok"), F.col("calls")), F.lit(0.0))
    return wave.groupBy(*KEY).agg((F.sum(turns * each) / 1000).alias("seconds"), F.sum(turns).alias("depth"))


def log_fit(points: DataFrame, quality: str, cost: str, by: tuple[str, ...] = ()) -> DataFrame:
    """quality = a + b ln(cost) and R squared."""
    x = F.ln(F.col(cost))
    return points.where(F.col(cost) > 0).groupBy(*by).agg(F.regr_intercept(quality, x).alias("a"), F.regr_slope(quality, x).alias("b"), F.regr_r2(quality, x).alias("r2"), F.count("*").alias("n"))


def match_rate(chosen: DataFrame, static: DataFrame, best: str = "mean", value: str = "ndcg") -> DataFrame:
    """Share of tasks where the chosen ranking is at least as good as the best static path: the one of the
    highest mean over tasks, or (best='per_query') the best of each task."""
    mine = chosen.select("task_id", F.col(value).alias("mine"))
    if best == "per_query":
        ref = static.groupBy("task_id").agg(F.max(value).alias("ref"))
    else:
        top = static.groupBy("path_id").agg(F.avg(value).alias("m")).orderBy(F.col("m").desc(), "path_id").limit(1).select("path_id")
        ref = static.join(F.broadcast(top), "path_id").select("task_id", F.col(value).alias("ref"))
    return mine.join(ref, "task_id").agg(F.avg((F.col("mine") >= F.col("ref")).cast("double")).alias("share"), F.count("*").alias("n"))


def accuracy(pred: DataFrame, pred_col: str, gold_col: str) -> DataFrame:
    return pred.agg(F.avg((F.col(pred_col) == F.col(gold_col)).cast("double")).alias("accuracy"), F.count("*").alias("n"))


def leaderboard(results: DataFrame, value: str, top: int = 3) -> DataFrame:
    """The best static paths per (dataset, model) by mean value, ties by name."""
    g = results.groupBy("dataset", "model", "path_id").agg(F.avg(value).alias("mean"))
    w = W.partitionBy("dataset", "model").orderBy(F.col("mean").desc(), "path_id")
    return g.withColumn("place", F.row_number().over(w).cast("bigint")).where(F.col("place") <= top)


def pareto(points: DataFrame, quality: str, cost: str, by: str) -> DataFrame:
    """Points that no other has both cheaper and better: quality above everything cheaper."""
    w = W.partitionBy(by).orderBy(cost, F.col(quality).desc()).rowsBetween(W.unboundedPreceding, -1)
    best = F.max(quality).over(w)
    return points.withColumn("efficient", best.isNull() | (F.col(quality) > best))


def dips(curve: DataFrame, quality: str, budget: str, by: str) -> DataFrame:
    """How often quality falls as the budget rises."""
    before = F.lag(quality).over(W.partitionBy(by).orderBy(budget))
    return curve.withColumn("before", before).groupBy(by).agg(F.count_if(F.col(quality) < F.col("before")).alias("dips"))


def spread(results: DataFrame, value: str) -> DataFrame:
    """Per path: quartiles over tasks, mean, and on how many tasks it is the sole best."""
    best = F.max(value).over(W.partitionBy("task_id"))
    ties = F.sum(F.col("is_best").cast("int")).over(W.partitionBy("task_id"))
    d = results.withColumn("is_best", F.col(value) == best).withColumn("alone", F.col("is_best") & (ties == 1))
    q = lambda p: F.percentile(value, F.lit(p))
    return d.groupBy("path_id").agg(F.min(value).alias("lo"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.max(value).alias("hi"), F.avg(value).alias("mean"), F.count_if("alone").alias("wins"))


def ratio(costs: DataFrame, a: str, b: str, value: str = "calls") -> DataFrame:
    """Mean over tasks of a path's cost relative to another's, from totals."""
    g = costs.groupBy().agg(F.sum(F.when(F.col("path_id") == a, F.col(value))).alias("x"), F.sum(F.when(F.col("path_id") == b, F.col(value))).alias("y"))
    return g.select(F.lit(a).alias("a"), F.lit(b).alias("b"), (F.col("x") / F.col("y")).alias("ratio"))
