"""The budgeted optimizer: sample, inquire, probe, estimate, choose, execute, fuse.

Decisions are rows, one or a few per task: thousands of tasks are decided in the same jobs. Nothing about items is
collected; every job that calls a model is written once. Inquiry and judge are calls of the backend like all others.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semrank.exec.index import placed_by
from semrank.exec.packed import PACKED_MAX, RESULT, measured, rankings_of, replies_of, run_paths, shown, slim, usage_of
from semrank.exec.scratch import Scratch
from semrank.exec.split import MOST_PARTS, split_merge
from semrank.exec.waves import merge_waves, quick_waves, score_waves
from semrank.functions.metrics import latency, ndcg_at, total_cost
from semrank.operators.fuse import fuse_rrf
from semrank.plans.complexity import candidates_frame, estimate, within_budget
from semrank.plans.spec import POINT_SEARCH, PathConfig, candidate_grid
from semrank.sources.model import PER_ITEM, PRICES, REASONING, REPLY, TEMPLATE, Key, ModelBackend, SimBackend, nano_usd

SAMPLE, INQUIRY_SAMPLE, SEED = 20, 5, 7
#: A full order of a larger task by merges is split first, so that its last merge is not one chain of calls.
SPLIT_FROM = 200_000


def md5_number(*parts: Column | str | int, digits: int = 8) -> Column:
    """The first hex digits of md5(part|part|...) as a number: DuckDB gives the same."""
    cols = [F.lit(str(p)) if isinstance(p, int) else p for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, digits), 16, 10).cast("bigint")


def noise_column(amplitude: int, *parts: Column | str | int) -> Column:
    return md5_number(*parts) % (2 * amplitude + 1) - amplitude


def sample_items(items: DataFrame, s: int = SAMPLE, seed: int = SEED) -> DataFrame:
    """s items per task, those of the least md5(seed|item)."""
    w = W.partitionBy("task_id").orderBy(md5_number(seed, F.col("item_id").cast("string"), digits=12), "item_id")
    return items.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= s).drop("_r")


def sample_upstream(plan, s: int, seed: int = SEED, over: int = 50) -> DataFrame:
    """A sample of a plan that has not run: its first over * s rows (the limit stops the scan), then those of the least hash.

    ``plan`` is a function that returns the upstream DataFrame. Rows come from its first files: biased by file order, cheap by design.
    """
    return sample_items(plan().limit(over * s), s, seed)


def _sample_keys(sample: DataFrame, backend: ModelBackend) -> DataFrame:
    """(task_id, criterion, keys): a sample's keys as one array per task, in input order. Samples are small by construction."""
    e = F.struct("pos", "item_id", "chars", "lat", "text")
    return shown(sample, backend).groupBy("task_id").agg(F.first("criterion", ignorenulls=True).alias("criterion"), F.array_sort(F.collect_list(e)).alias("keys"))


def _keys(found) -> list[Key]:
    return [] if found is None else [Key(int(k["item_id"]), int(k["chars"]), int(k["lat"]), None, k["text"]) for k in found]


def _bound(backend: ModelBackend, criterion) -> ModelBackend:
    return backend.about(criterion, backend.descending) if isinstance(criterion, str) and criterion else backend


CALL = "in_tok bigint, out_tok bigint, nano_usd bigint"


def route_by_inquiry(tasks: DataFrame, backend: ModelBackend | None = None, sample: DataFrame | None = None) -> DataFrame:
    """One call per task: does world knowledge settle it? Adds answer, route ('lookup' or 'pool') and what the call cost.

    ``tasks``: task_id, kind (the truth, for the simulator) and optional criterion. The call is shown the keys of ``sample``, of which there should
    be ``INQUIRY_SAMPLE`` a task.
    """
    model = backend or SimBackend("reasoning")
    d = tasks if "criterion" in tasks.columns else tasks.withColumn("criterion", F.lit(None).cast("string"))
    if sample is None:
        d = d.withColumn("keys", F.lit(None).cast("array<struct<pos:int,item_id:bigint,chars:int,lat:bigint,text:string>>"))
    else:
        d = d.join(_sample_keys(sample, model).select("task_id", "keys", F.col("criterion").alias("_crit")), "task_id", "left").withColumn("criterion", F.coalesce("criterion", "_crit")).drop("_crit")
    schema = T.StructType([*(f for f in d.schema.fields if f.name != "keys"), *T._parse_datatype_string("answer string, " + CALL).fields])

    def ask(frames):
        for f in frames:
            got = [_bound(model, c).inquire(t, _keys(k), kind) for t, k, c, kind in zip(f["task_id"], f["keys"], f["criterion"], f["kind"], strict=True)]
            f = f.drop(columns=["keys"]).assign(answer=[a for a, _ in got], in_tok=[u.in_tok for _, u in got], out_tok=[u.out_tok for _, u in got])
            yield f.assign(nano_usd=[nano_usd(u.in_tok, u.out_tok, u.lookups, model.tier) for _, u in got])

    out = d.mapInPandas(ask, schema)
    return out.withColumn("route", F.when(F.col("answer") == "factual", "lookup").otherwise("pool"))


def judge_choice(sample: DataFrame, rankings: DataFrame, fits: DataFrame, judge: ModelBackend) -> DataFrame:
    """(task_id, path_id, and what the call cost): one call per task, which is shown the sample and the surviving candidates' rankings of it."""
    ids = rankings.join(fits.where("fits").select("task_id", "path_id"), ["task_id", "path_id"])
    ids = ids.groupBy("task_id", "path_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("rnk", "item_id"))), lambda x: x["item_id"]).alias("ids"))
    lists = ids.groupBy("task_id").agg(F.array_sort(F.collect_list(F.struct("path_id", "ids"))).alias("results"))

    def ask(frames):
        for f in frames:
            rows = []
            for t, results, keys, criterion in zip(f["task_id"], f["results"], f["keys"], f["criterion"], strict=True):
                path_id, u = _bound(judge, criterion).judge(t, _keys(keys), {r["path_id"]: [int(i) for i in r["ids"]] for r in results})
                rows.append((t, path_id, u.in_tok, u.out_tok, nano_usd(u.in_tok, u.out_tok, u.lookups, judge.tier)))
            yield pd.DataFrame(rows, columns=["task_id", "path_id", "in_tok", "out_tok", "nano_usd"])

    return lists.join(_sample_keys(sample, judge), "task_id").mapInPandas(ask, "task_id string, path_id string, " + CALL)


def agreement(rankings: DataFrame, proxy: DataFrame, how: str = "tau") -> DataFrame:
    """(task_id, path_id, agreement) of candidates' sample rankings with the proxy ranking.

    An item that a candidate leaves out (its ranking was cut by a limit) counts as behind all that it lists; two such items
    tell nothing, but are counted: tau is (right pairs - wrong pairs) / all pairs of the proxy.
    """
    n = proxy.groupBy("task_id").agg(F.max("rnk").alias("n"))
    p = proxy.join(n, "task_id").select("task_id", "item_id", F.col("rnk").alias("p"), "n")
    full = p.join(rankings.select("task_id", "path_id").distinct(), "task_id").join(rankings.select("task_id", "path_id", "item_id", "rnk"), ["task_id", "path_id", "item_id"], "left")
    key = ["task_id", "path_id"]
    if how == "tau":
        a = full.select(*key, "p", F.coalesce("rnk", F.col("n") + 1).alias("r"))
        b = a.select(*key, F.col("p").alias("p2"), F.col("r").alias("r2"))
        s = a.join(b, key).where("p < p2").groupBy(*key).agg(F.avg(F.signum(F.col("r2") - F.col("r"))).alias("agreement"))
        return s.select(*key, "agreement")
    if how == "ndcg":
        grade = p.select("task_id", "item_id", (F.col("n") - F.col("p")).alias("grade"))
        return ndcg_at(rankings, grade).select(*key, F.col("ndcg").alias("agreement"))
    if how == "footrule":
        # those left out share the places behind the listed ones
        listed = rankings.groupBy(*key).agg(F.count("*").alias("listed"))
        d = full.join(listed, key).withColumn("r", F.coalesce(F.col("rnk").cast("double"), (F.col("listed") + 1 + F.col("n")) / 2))
        d = d.groupBy(*key).agg(F.sum(F.abs(F.col("r") - F.col("p"))).alias("d"), F.count("*").alias("c"))
        worst = F.greatest(F.floor(F.col("c") * F.col("c") / 2), F.lit(1))
        return d.select(*key, (1 - F.col("d") / worst).alias("agreement"))
    raise ValueError("agreement is tau, ndcg or footrule")


def run_in_waves(items: DataFrame, path: PathConfig, backend: ModelBackend, k: int | None, scratch: Scratch, known: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """((task_id, item_id, rnk), (task_id, path_id, calls, in_tok, out_tok, lookups, hits)) of tasks too large for one worker; items: with dense places ``pos``.

    ``known``: (task_id, req, reply) of scores that are not paid again; comparisons and lists are all asked, as those of a sample hardly recur in a large task.
    """
    if path.kind == "slide_window":
        raise ValueError("a sliding window is one sequential chain: for tasks this large take another path")
    own = Scratch(scratch.spark, "waves")
    if path.kind == "run_merge":
        most = items.groupBy("task_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
        if k is None and most > SPLIT_FROM:
            out, usage = split_merge(items, backend, min(MOST_PARTS, math.ceil(most / PACKED_MAX)), path, scratch=own)
        else:
            out, usage = merge_waves(items, path, backend, k, scratch=own)
    elif path.kind == "pivot_split":
        out, usage = quick_waves(items, path, backend, k, scratch=own)
    else:
        out, got = score_waves(items, path, backend, scratch=own, known=known)
        paid = lambda c: F.sum(F.when(F.col("hit"), 0).otherwise(F.col(c))).alias(c)
        usage = got.groupBy("task_id", "path_id").agg(F.count_if(~F.col("hit")).alias("calls"), *[paid(c) for c in ("in_tok", "out_tok", "lookups")], F.count_if("hit").alias("hits"))
    if "hits" not in usage.columns:
        usage = usage.withColumn("hits", F.lit(0).cast("bigint"))
    out = out.select("task_id", "item_id", "rnk")
    return (out if k is None else out.where(F.col("rnk") <= k)), usage


#: A study runs tasks of up to so many items packed; their keys fit a worker beside the other one of its machine.
STUDY_PACKED = 50_000
#: With more tasks than this all paths of one run in the same worker.
MANY = 500


def run_static(items: DataFrame, paths: list[PathConfig], backend: ModelBackend, scratch: Scratch, name: str = "static", *, by_wave: bool = False, packed_max: int = STUDY_PACKED) -> DataFrame:
    """``run_paths`` for written items of any size: tasks beyond ``packed_max`` run in waves, their sliding windows as one chain in a worker.

    Items of a task share one limit ``k``. Results are those of packed runs; usage of waves is summed by path.
    """
    items = items if "k" in items.columns else items.withColumn("k", F.lit(None).cast("bigint"))
    sizes = scratch.write(f"{name}-sizes", items.groupBy("task_id").agg(F.count_if((F.col("key") != "")).alias("n"), F.first("k").alias("k")))
    large = F.col("n") > packed_max
    tasks, most = sizes.agg(F.count("*"), F.max("n")).first()
    if (most or 0) <= packed_max:
        return run_paths(items, paths, backend, scratch=scratch, name=name, by_wave=by_wave, together=tasks > MANY)
    out = [run_paths(items.join(sizes.where(~large).select("task_id"), "task_id", "left_semi"), paths, backend, scratch=scratch, name=name, by_wave=by_wave)]
    big = items.join(sizes.where(large).select("task_id"), "task_id", "left_semi")
    chains = [p for p in paths if p.kind == "slide_window"]
    if chains:
        out.append(run_paths(big, chains, backend, scratch=scratch, name=f"{name}-chains", by_wave=by_wave))
    # a limit or two by construction
    limits = [r["k"] for r in sizes.where(large).select("k").distinct().collect()]
    a, b, fee = PRICES[backend.tier]
    none = lambda have: [F.lit(None).cast(f.dataType).alias(f.name) for f in T._parse_datatype_string(RESULT).fields if f.name not in have]
    for i, k in enumerate(limits):
        mine = big.where(F.col("k").eqNullSafe(F.lit(k)) & (F.col("key") != "")).drop("k")
        # empty keys leave gaps in the places, which a packed run closes too
        mine = placed_by(mine, ["pos", "item_id"], scratch, f"{name}-at{i}").withColumn("pos", (F.col(f"{name}-at{i}") - 1).cast("int")).drop(f"{name}-at{i}")
        for p in paths:
            if p.kind == "slide_window":
                continue
            r, u = run_in_waves(mine, p, backend, k, scratch)
            r = r.select(F.lit("rank").alias("part"), "task_id", F.lit(p.path_id).alias("path_id"), "item_id", F.col("rnk").cast("bigint").alias("rnk"))
            money = (F.col("in_tok") * a + F.col("out_tok") * b + F.col("lookups") * fee * 1000).alias("nano_usd")
            u = u.select(F.lit("usage").alias("part"), "task_id", F.lit(p.path_id).alias("path_id"), F.lit(p.kind).alias("op"), "calls", "in_tok", "out_tok", "lookups", money)
            out += [d.select(*d.columns, *none(d.columns)) for d in (r, u)]
    every = out[0]
    for d in out[1:]:
        every = every.unionByName(d.select(*every.columns))
    return every


def greedy_fit(scored: DataFrame, budget_nano: int | None = None, on_overflow: str = "skip") -> DataFrame:
    """Candidates (task_id, path_id, agreement, est_nano) by falling agreement while their estimates fit jointly.

    The budget is one for all tasks, or (None) the column ``left_nano`` of each. 'skip' passes over one that is too dear and goes on; 'stop' ends there. The candidates of a task are few, so the
    greedy walk is a fold over one sorted array.
    """
    if on_overflow not in ("skip", "stop"):
        raise ValueError("on_overflow is skip or stop")
    entry = F.struct((-F.col("agreement")).alias("order"), F.col("path_id").alias("path_id"), F.col("est_nano").alias("est"))
    left = F.lit(budget_nano) if budget_nano is not None else F.first("left_nano")
    lists = scored.groupBy("task_id").agg(F.array_sort(F.collect_list(entry)).alias("c"), left.cast("double").alias("left"))
    start = F.struct(F.lit(0.0).alias("spent"), F.lit(False).alias("over"), F.array().cast("array<string>").alias("took"))

    def walk(a: Column, x: Column) -> Column:
        fits = (a["spent"] + x["est"] <= F.col("left")) & (~a["over"] if on_overflow == "stop" else F.lit(True))
        return F.struct(
            F.when(fits, a["spent"] + x["est"]).otherwise(a["spent"]).alias("spent"),
            (a["over"] | ~fits).alias("over"),
            F.when(fits, F.array_append(a["took"], x["path_id"])).otherwise(a["took"]).alias("took"),
        )

    return lists.select("task_id", F.explode(F.aggregate("c", start, walk)["took"]).alias("path_id"))


@dataclass
class RankResult:
    """ranking: (task_id, item_id, rnk). ledger: calls, replies reused and nano-dollars by phase. estimates, choices: why."""

    ranking: DataFrame
    ledger: DataFrame
    estimates: DataFrame
    choices: DataFrame


def optimize(
    items: DataFrame,
    tasks: DataFrame,
    budget_nano: int,
    backend: ModelBackend,
    *,
    policy: str = "consensus",
    candidates: list[PathConfig] | None = None,
    judge: ModelBackend | None = None,
    sample: int = SAMPLE,
    inquiry: bool = True,
    grounded: PathConfig = POINT_SEARCH,
    agreement_by: str = "tau",
    on_overflow: str = "skip",
    on_infeasible: str = "error",
    budget_covers: str = "ranking",
    estimate_form: str = "per_call",
    max_latency_s: float | None = None,
    packed_max: int = PACKED_MAX,
    max_in_flight: int | None = None,
    seed: int = SEED,
    scratch: Scratch | None = None,
) -> RankResult:
    """Rank every task within a budget of nano-dollars per task.

    ``items``: task_id, item_id, pos, key, lat and optional fact and criterion. ``tasks``: task_id, kind, k (null: full order).
    The budget covers the ranking calls; with budget_covers='all' the inquiry, the probe and the judge count against it too. A task for which
    nothing fits is an error, or takes its cheapest path (on_infeasible='cheapest'). Tasks that an inquiry calls factual are
    ranked by ``grounded`` at once. The final run does not pay again for what the probe asked. Tasks of more than ``packed_max`` items run in
    waves; a sliding window is no candidate for them.
    """
    if policy not in ("judge", "consensus") or on_infeasible not in ("error", "cheapest") or budget_covers not in ("ranking", "all"):
        raise ValueError("policy is judge or consensus; on_infeasible is error or cheapest; budget_covers is ranking or all")
    spark = items.sparkSession
    scratch = scratch or Scratch(spark, "optimize")
    # read by six jobs, so worked out once; texts stay out where nobody reads them
    readers = backend.reads_text or (judge or backend).reads_text
    items = scratch.write("asked", items if readers else slim(items, backend))
    candidates, judge = candidates or candidate_grid(), judge or backend
    # one path id can stand for several settings only if they differ in nothing that it names
    table = candidates_frame(spark, list({p.path_id: p for p in [grounded, *candidates]}.values()))
    routed = route_by_inquiry(tasks, backend, sample_items(items.where("key is not null and key <> ''"), INQUIRY_SAMPLE, seed)) if inquiry else tasks.withColumn("route", F.lit("pool")).withColumn("nano_usd", F.lit(0).cast("bigint"))
    routed = scratch.write("routed", routed)
    full = items.drop("k").join(routed.select("task_id", "k", "route"), "task_id")
    pool = full.where("route = 'pool' and key is not null and key <> ''").drop("route")
    s_items = scratch.write("sample", sample_items(pool, sample, seed))
    probe = run_paths(s_items, candidates, backend, scratch=scratch, name="probe", keep=True, max_in_flight=max_in_flight)
    lengths = lambda d, n, chars: d.groupBy("task_id").agg(F.count("*").alias(n), F.avg(measured(d)).alias(chars))
    sizes = lengths(pool, "n", "chars").join(routed.select("task_id", "k"), "task_id").join(lengths(s_items, "s", "sample_chars"), "task_id")
    sizes = scratch.write("sizes", sizes)
    spent = total_cost(usage_of(probe))
    est = estimate(spent.select("task_id", "path_id", "nano_usd", "calls"), sizes, table, estimate_form, PRICES[backend.tier][0])
    p_in, p_out, _ = PRICES[judge.tier]
    # what the judge may cost: the sample once, and each candidate's ranking of it
    judging = F.ceil((TEMPLATE["judge"] + F.col("s") * (F.col("sample_chars") + 4 * len(candidates))) / 4 + 1) * p_in + (REPLY["judge"] + REASONING + PER_ITEM["order"] * F.col("s")) * p_out
    left = F.lit(budget_nano)
    if budget_covers == "all":
        est = est.join(spent.groupBy("task_id").agg(F.sum("nano_usd").alias("probe_nano")), "task_id").join(routed.select("task_id", F.col("nano_usd").alias("asked_nano")), "task_id").join(sizes.select("task_id", "s", "sample_chars"), "task_id")
        left = budget_nano - F.col("probe_nano") - F.col("asked_nano") - (judging if policy == "judge" else 0)
    est = est.withColumn("left_nano", left.cast("double"))
    fits = within_budget(est, F.col("left_nano")).join(sizes.select("task_id", "n"), "task_id").join(F.broadcast(table.select("path_id", "kind")), "path_id")
    fits = fits.withColumn("fits", F.col("fits") & ~((F.col("kind") == "slide_window") & (F.col("n") > packed_max)))
    if max_latency_s is not None:
        lat = latency(usage_of(probe)).join(sizes, "task_id").join(F.broadcast(table.select("path_id", "kind")), "path_id")
        # value paths stay one wave deep; the others deepen no faster than their calls
        grown = F.when(F.col("kind").startswith("score"), F.col("seconds")).otherwise(F.col("seconds") * F.col("n") / F.col("s"))
        slow = lat.where(grown > max_latency_s).select("task_id", "path_id")
        fits = fits.join(slow.withColumn("slow", F.lit(True)), ["task_id", "path_id"], "left").withColumn("fits", F.col("fits") & F.col("slow").isNull()).drop("slow")
    fits = scratch.write("fits", fits.select("task_id", "path_id", "nano_usd", "est_nano", "left_nano", "fits", (F.col("n") > packed_max).alias("large"), "kind"))
    none = fits.groupBy("task_id").agg(F.max("fits").alias("any")).where("not any").select("task_id")
    if on_infeasible == "error":
        lost = [r["task_id"] for r in none.limit(3).collect()]
        if lost:
            raise ValueError(f"no access path fits a budget of {budget_nano} nano-dollars for {', '.join(lost)}")
    cheap = F.min_by("path_id", F.struct("est_nano", "path_id")).alias("path_id")
    cheapest = fits.where("not large or kind <> 'slide_window'").join(none, "task_id", "left_semi").groupBy("task_id").agg(cheap)
    within = fits.where("fits")
    # what does not fit has no voice: the proxy fuses the sample rankings of the others
    sample_ranks = scratch.write("sample-ranks", rankings_of(probe).join(within.select("task_id", "path_id"), ["task_id", "path_id"]))
    judged = None
    if policy == "judge":
        judged = scratch.write("judged", judge_choice(s_items, sample_ranks, fits, judge))
        chosen = judged.select("task_id", "path_id")
    else:
        proxy = fuse_rrf(sample_ranks)
        scored = agreement(sample_ranks, proxy, agreement_by).join(within, ["task_id", "path_id"])
        chosen = greedy_fit(scored, None, on_overflow)
        # a task of one item agrees with everything: take the cheapest
        chosen = chosen.unionByName(within.join(chosen, "task_id", "left_anti").groupBy("task_id").agg(cheap))
    choices = chosen.unionByName(cheapest)
    if inquiry:
        choices = choices.unionByName(routed.where("route = 'lookup'").select("task_id", F.lit(grounded.path_id).alias("path_id")))
    choices = scratch.write("choices", choices)
    sized = lengths(full.where("key is not null and key <> ''"), "n", "chars").where(F.col("n") > packed_max).select("task_id")
    big = scratch.write("big", choices.join(sized, "task_id"))
    packed = choices.join(big.select("task_id").distinct(), "task_id", "left_anti")
    replies = replies_of(probe)
    known = scratch.write("known", replies.join(packed, "task_id").select("task_id", "path_id", "req", "reply"))
    final = run_paths(full.drop("route"), packed.join(F.broadcast(table), "path_id"), backend, scratch=scratch, name="final", cached=known, max_in_flight=max_in_flight)
    ranks, reused = [rankings_of(final)], [usage_of(final).select("task_id", "hits")]
    paid = [total_cost(usage_of(final), ("task_id",)).select("task_id", "calls", "nano_usd")]
    by_id = {p.path_id: p for p in [grounded, *candidates]}
    # large tasks: one run in waves per path and limit that any of them takes, a few by construction
    for row in big.join(routed.select("task_id", "k"), "task_id").select("path_id", "k").distinct().orderBy("path_id", "k").collect():
        mine = big.where(F.col("path_id") == row["path_id"]).join(routed.select("task_id", "k").where(F.col("k").eqNullSafe(F.lit(row["k"]))), "task_id").select("task_id")
        r, u = run_in_waves(full.drop("route", "k").join(mine, "task_id"), by_id[row["path_id"]], backend, row["k"], scratch, replies.join(mine, "task_id"))
        ranks.append(r.select("task_id", F.lit(row["path_id"]).alias("path_id"), "item_id", "rnk"))
        a, b, fee = PRICES[backend.tier]
        reused.append(u.select("task_id", "hits"))
        paid.append(u.select("task_id", "calls", (F.col("in_tok") * a + F.col("out_tok") * b + F.col("lookups") * fee * 1000).alias("nano_usd")))
    every, cost = ranks[0], paid[0]
    for r, u in zip(ranks[1:], paid[1:], strict=True):
        every, cost = every.unionByName(r), cost.unionByName(u)
    # one ranking fuses to itself
    fused = fuse_rrf(every, wide=len(ranks) > 1).join(routed.select("task_id", "k"), "task_id")
    ranking = fused.where(F.col("k").isNull() | (F.col("rnk") <= F.col("k"))).select("task_id", "item_id", "rnk")
    hits = reused[0]
    for h in reused[1:]:
        hits = hits.unionByName(h)
    ledger = _ledger(probe, hits, cost, routed if inquiry else None, judged)
    return RankResult(ranking, ledger, fits.select("task_id", "path_id", "nano_usd", "est_nano", "left_nano", "fits"), choices)


def _ledger(probe: DataFrame, hits: DataFrame, cost: DataFrame, asked: DataFrame | None, judged: DataFrame | None) -> DataFrame:
    """(task_id, phase, calls, hits, nano_usd): probe, ranking, inquiry and judge spend kept apart; hits are replies of the probe that were not paid again."""
    one = lambda d, name: d.select("task_id", F.lit(name).alias("phase"), F.lit(1).cast("bigint").alias("calls"), F.lit(0).cast("bigint").alias("hits"), "nano_usd")
    hits = hits.groupBy("task_id").agg(F.sum("hits").alias("hits"))
    ranking = cost.groupBy("task_id").agg(F.sum("calls").alias("calls"), F.sum("nano_usd").alias("nano_usd")).join(hits, "task_id", "left")
    ranking = ranking.select("task_id", F.lit("ranking").alias("phase"), "calls", F.coalesce("hits", F.lit(0)).alias("hits"), "nano_usd")
    out = total_cost(usage_of(probe), ("task_id",)).select("task_id", F.lit("probe").alias("phase"), "calls", F.lit(0).cast("bigint").alias("hits"), "nano_usd").unionByName(ranking)
    for d, name in ((asked, "inquiry"), (judged, "judge")):
        out = out if d is None else out.unionByName(one(d, name))
    return out


def explain_rank(result: RankResult) -> DataFrame:
    """Why: per task and candidate the estimate and 'chosen', 'not chosen' or 'over budget'."""
    c = result.choices.withColumn("chosen", F.lit(True))
    d = result.estimates.join(c, ["task_id", "path_id"], "full")
    verdict = F.when(F.col("chosen"), F.when(F.col("est_nano").isNull(), "chosen by inquiry").otherwise("chosen")).when(F.col("fits"), "not chosen").otherwise("over budget")
    return d.select("task_id", "path_id", F.col("est_nano"), verdict.alias("verdict"))
