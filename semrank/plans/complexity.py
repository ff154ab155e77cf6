"""Model calls of each access path: growth functions, exact counts, and cost estimates from a probe.

Growth functions have unit constants, so only their ratios for one path mean anything; estimates
use the ratio of the full input to the sample, in which constants cancel. Where the answers decide the number of calls,
it can be found without a model by running the path on items in random order with a perfect comparator.
"""

from __future__ import annotations

import math
import random

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec.generators import PATHS
from semrank.plans.spec import PathConfig
from semrank.sources.model import Key


def calls(path: PathConfig, n: int, k: int | None = None) -> float:
    """The growth function at n items, with a limit of k."""
    if n <= 0:
        return 0.0
    log = lambda x: math.log2(x) if x > 1 else 0.0
    m, v = path.m, path.v
    if path.kind == "score_each":
        return float(n)
    if path.kind == "score_batch":
        return n / m
    if path.kind == "pivot_split":
        return v * n * log(n) if k is None else v * (n + k * log(k))
    if path.kind == "slide_window":
        return n * n / (m * m) if k is None else k * n / (m * m)
    return n / m * (1 + log(n / m)) if k is None else n / m * (2 + log(k / m))


def calls_expr(kind: Column, m: Column, v: Column, n: Column, k: Column) -> Column:
    """The same as a column; k null for a full sort."""
    log = lambda x: F.when(x > 1, F.log2(x)).otherwise(F.lit(0.0))
    full = k.isNull()
    quick = F.when(full, v * n * log(n)).otherwise(v * (n + k * log(k)))
    bubble = F.when(full, n * n / (m * m)).otherwise(k * n / (m * m))
    merge = F.when(full, n / m * (1 + log(n / m))).otherwise(n / m * (2 + log(k / m)))
    out = F.when(kind == "score_each", n.cast("double")).when(kind == "score_batch", n / m).when(kind == "pivot_split", quick).when(kind == "slide_window", bubble)
    return F.when(n <= 0, F.lit(0.0)).otherwise(out.otherwise(merge)).cast("double")


def exact_calls(path: PathConfig, n: int, k: int | None = None) -> int | None:
    """Calls that n and k alone decide; None where they depend on the answers."""
    if n <= 0 or k == 0:
        return 0
    if path.kind == "score_each":
        return n
    if path.kind == "score_batch":
        return math.ceil(n / path.m)
    if path.kind != "slide_window":
        return None
    h, total, done = max(path.m // 2, 1), 0, 0
    if n == 1:
        return 0
    want = n if k is None else min(k, n)
    while done < want and n - done > 1:
        left = n if path.rescan else n - done
        total += 1 if left <= path.m else 1 + math.ceil((left - path.m) / h)
        if left <= path.m:
            break
        done += h
    return total


def exact_calls_expr(kind: Column, m: Column, n: Column, k: Column) -> Column:
    """``exact_calls`` as a column (for plain passes, without rescans): null where the answers decide."""
    h = F.greatest(F.floor(m / 2), F.lit(1))
    want = F.least(F.coalesce(k, n), n)
    windows = lambda x: F.when(x <= m, F.lit(1)).otherwise(1 + F.ceil((x - m) / h))
    # passes until enough places are fixed, or one window covers the rest
    passes = F.least(F.ceil(want / h), F.ceil((n - 1) / h), F.when(n > m, F.ceil((n - m) / h) + 1).otherwise(F.lit(1))).cast("int")
    bubble = F.aggregate(F.sequence(F.lit(0), F.greatest(passes, F.lit(1)) - 1), F.lit(0).cast("bigint"), lambda a, r: a + windows(n - r * h))
    out = F.when(kind == "score_each", n.cast("bigint")).when(kind == "score_batch", F.ceil(n / m)).when(kind == "slide_window", F.when(n == 1, F.lit(0)).otherwise(bubble))
    return F.when((n <= 0) | F.coalesce(k == 0, F.lit(False)), F.lit(0)).otherwise(out).cast("bigint")


def candidates_frame(spark: SparkSession, paths: list[PathConfig]) -> DataFrame:
    rows = [(p.path_id, p.kind, p.m, p.v, p.lookup, p.max_point, p.pivot, p.rescan, p.stop_when_stable, p.peer_override) for p in paths]
    return spark.createDataFrame(rows, "path_id string, kind string, m int, v int, lookup boolean, max_point int, pivot string, rescan boolean, stop_when_stable boolean, peer_override boolean")


#: Expected calls are found by runs up to so many items, beyond them by the growth function from there.
MOST_RUN, TRIALS = 2000, 3


#: What ``expected_calls`` has found; a few numbers per shape of task.
_FOUND: dict[tuple, float] = {}


def expected_calls(kind: str, m: int, v: int, n: int, k: int | None = None) -> float:
    """Mean calls over seeded random orders with a perfect comparator."""
    shape = (kind, m, v, n, k)
    if shape not in _FOUND:
        _FOUND[shape] = _expected_calls(PathConfig(kind, m, v), n, k)
    return _FOUND[shape]


def _expected_calls(path: PathConfig, n: int, k: int | None) -> float:
    exact = exact_calls(path, n, k)
    if exact is not None:
        return float(exact)
    size, total = min(n, MOST_RUN), 0
    for seed in range(TRIALS):
        keys = [Key(i, 1, x) for i, x in enumerate(random.Random(seed).sample(range(size), size))]
        value, steps = [x.latent for x in keys], PATHS[path.kind](keys, path, k)
        reply = None
        try:
            while True:
                wave = steps.send(reply)
                total += len(wave)
                reply = [(1 if value[r[1].item_id] > value[r[2].item_id] else -1) if r[0] == "compare" else sorted((x.item_id for x in r[1:]), key=lambda i: -value[i]) for r in wave]
        except StopIteration:
            pass
    base = calls(path, size, k)
    return total / TRIALS * (calls(path, n, k) / base if base else 1.0)


def extrapolate(sample_cost: float, path: PathConfig, s: int, n: int, k: int | None = None, *, form: str = "ratio", sample_calls: int | None = None) -> float:
    """Cost at n items from the cost of a sample of s.

    ``ratio``: by the growth function, with the limit on the sample too. ``per_call``: the sample's cost per call
    times the calls at n: exact ones where n and k decide them, else the sample's, grown as expected calls grow.
    """
    ks = None if k is None else min(k, s)
    if form == "ratio":
        base = calls(path, s, ks)
        return sample_cost * (calls(path, n, k) / base if base else 0.0)
    if form != "per_call" or not sample_calls:
        raise ValueError("form is ratio, or per_call with the sample's calls")
    exact, base = exact_calls(path, n, k), expected_calls(path.kind, path.m, path.v, s, ks)
    grown = expected_calls(path.kind, path.m, path.v, n, k) / base if base else 0.0
    return sample_cost / sample_calls * (sample_calls * grown if exact is None else exact)


def estimate(probe_costs: DataFrame, sizes: DataFrame, candidates: DataFrame, form: str = "ratio", nano_per_token: int | None = None) -> DataFrame:
    """(task_id, path_id, nano_usd, and calls for the second form) of the sample -> est_nano for the full task; sizes: (task_id, s, n, k).

    ``ratio``: by the growth functions. ``per_call``: by the sample's cost per call and the calls of the full task, see ``extrapolate``; with
    the price of a token and mean key lengths (sizes: chars, sample_chars), which cost nothing to know, a call's keys are
    priced at their length in the full task.
    """
    if form not in ("ratio", "per_call"):
        raise ValueError("form is ratio or per_call")
    d = probe_costs.join(F.broadcast(candidates.select("path_id", "kind", "m", "v")), "path_id").join(sizes, "task_id")
    c = F.col
    d = d.withColumn("_ks", F.when(c("k").isNotNull(), F.least("k", "s")))
    if form == "ratio":
        full, part = calls_expr(c("kind"), c("m"), c("v"), c("n"), c("k")), calls_expr(c("kind"), c("m"), c("v"), c("s"), c("_ks"))
        est = F.when(part > 0, c("nano_usd") * full / part).otherwise(F.lit(0.0))
    else:
        shape = ["kind", "m", "v", "n", "k", "s", "_ks"]

        def count(frames):
            for f in frames:
                whole = lambda x: None if pd.isna(x) else int(x)
                rows = [(expected_calls(r.kind, int(r.m), int(r.v), int(r.n), whole(r.k)), expected_calls(r.kind, int(r.m), int(r.v), int(r.s), whole(r.ks))) for r in f.itertuples()]
                yield f.assign(full=[x for x, _ in rows], part=[x for _, x in rows])

        shapes = d.select(*shape).distinct().withColumnRenamed("_ks", "ks")
        schema = "kind string, m int, v int, n bigint, k bigint, s bigint, ks bigint, full double, part double"
        grown = shapes.select("kind", "m", "v", *[c(x).cast("bigint").alias(x) for x in ("n", "k", "s", "ks")]).mapInPandas(count, schema).withColumnRenamed("ks", "_ks")
        grown = grown.select(*[c(x).alias(f"_{x}_") for x in shape], "full", "part")
        same = [d[x].eqNullSafe(grown[f"_{x}_"]) if x in ("k", "_ks") else d[x] == grown[f"_{x}_"] for x in shape]
        condition = same[0]
        for x in same[1:]:
            condition = condition & x
        d = d.join(grown, condition)
        # exact calls are counted as such; for the others the answers of the sample say how far they are from expected
        at_n = F.when(c("kind").isin("score_each", "score_batch", "slide_window") | (c("part") == 0), c("full")).otherwise(c("calls") * c("full") / c("part"))
        each = F.try_divide(c("nano_usd"), c("calls"))
        if nano_per_token is not None and "sample_chars" in sizes.columns:
            shown = F.when(c("kind") == "score_each", 1).when(c("kind") == "pivot_split", 2).otherwise(F.least("m", "s"))
            each = F.greatest(each + shown * (c("chars") - c("sample_chars")) / 4 * nano_per_token, F.lit(0.0))
        est = F.coalesce(each * at_n, F.lit(0.0))
    # a sample that holds the whole task is the full run
    return d.select("task_id", "path_id", "nano_usd", F.when(c("n") <= c("s"), c("nano_usd").cast("double")).otherwise(est).alias("est_nano"))


def within_budget(est: DataFrame, budget_nano: int | Column) -> DataFrame:
    limit = budget_nano if isinstance(budget_nano, Column) else F.lit(budget_nano)
    return est.withColumn("fits", F.col("est_nano") <= limit)
