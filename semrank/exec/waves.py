"""Wave execution for tasks too large for one worker: a wave of calls is a job over all tasks.

The results equal those of packed execution with the same settings. A key's text travels with it only for backends
that read it. Each function gives (rankings, usage): usage is (task_id, path_id, calls, in_tok, out_tok, lookups).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semrank.exec.call import ResponseCache, call_model, key_struct, request_hash
from semrank.exec.generators import merge_round, merge_two, peer_slots, settle
from semrank.exec.index import indexed, placed_by
from semrank.exec.merges import Orders, merge_all, merge_pair
from semrank.exec.packed import answer, keys_of, run_path, shown, spread
from semrank.exec.scratch import Scratch
from semrank.plans.spec import PathConfig
from semrank.sources.model import Key, ModelBackend, each

RUN = "task_id string, block bigint, seq bigint, item_id bigint, chars int, lat bigint, text string, calls bigint, in_tok bigint, out_tok bigint"
SPENT = ("calls", "in_tok", "out_tok")
#: Runs of m are merged to blocks of m * 2^LOCAL rows within one task of a job.
LOCAL = 10
#: The same for backends that answer many lists at once: a block is arrays of a million items.
LOCAL_AT_ONCE = 18


def score_waves(items: DataFrame, path: PathConfig, backend: ModelBackend, *, cache: ResponseCache | None = None, scratch: Scratch | None = None, known: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Value paths as one wave: (rankings with scores, responses). ``known``: packed runs' replies (task_id, req, reply) that are not paid again."""
    scratch = scratch or Scratch(items.sparkSession, "waves")
    m = path.m if path.kind == "score_batch" else 1
    d = shown(items, backend).select("task_id", F.floor(F.col("pos") / m).alias("extra"), F.struct("pos", key_struct().alias("k")).alias("e"))
    d = d.groupBy("task_id", "extra").agg(F.transform(F.array_sort(F.collect_list("e")), lambda e: e["k"]).alias("keys"))
    op = "score_many" if path.kind == "score_batch" else "score"
    # a single score does not depend on its place
    batch = F.col("extra") if op == "score_many" else F.lit(0)
    d = d.withColumn("req_hash", request_hash(op, F.col("keys"), batch, F.lit(path.max_point), F.lit(path.lookup), F.lit(backend.identity())))
    d = d.select("req_hash", "task_id", F.lit(path.path_id).alias("path_id"), F.lit(0).alias("wave"), F.lit(op).alias("op"), "keys", "extra")
    got = call_model(d, path, backend, scratch, "score", cache=cache, known=known)
    asked = scratch.spark.read.schema(d.schema).parquet(scratch.path("score-requests"))
    scored = asked.join(got, "req_hash").select("task_id", "path_id", F.explode(F.arrays_zip("keys", "reply")).alias("z")).select("task_id", "path_id", F.col("z.keys.item_id").alias("item_id"), F.col("z.reply").alias("score"))
    # an unknown score comes last
    ranked = placed_by(scored.withColumn("_behind", -F.coalesce("score", F.lit(-1))), ["_behind", "item_id"], scratch, "rnk").drop("_behind")
    return ranked.select("task_id", "path_id", "item_id", "score", "rnk"), got.join(asked.select("req_hash", "task_id", "path_id"), "req_hash")


def _order(backend: ModelBackend, task: str, path: PathConfig, spent: list[int]):
    def order(keys: list[Key]) -> list[int]:
        reply, used, _ = answer(backend, task, ("order", *keys), path)
        for i, x in enumerate((1, used.in_tok, used.out_tok)):
            spent[i] += x
        return reply

    return order


def merge_waves(items: DataFrame, path: PathConfig, backend: ModelBackend, k: int | None = None, *, local: int | None = None, scratch: Scratch | None = None) -> tuple[DataFrame, DataFrame]:
    """External merge of any number of items.

    Blocks of m * 2^local neighbours are sorted and merged within a task of the first job (the same merge tree as run by run,
    so the same result and the same calls); then each job merges neighbouring blocks. With a limit every run is at most k long.
    """
    scratch = scratch or Scratch(items.sparkSession, "merge")
    none = np.zeros(0, dtype=np.int64)
    at_once = hasattr(backend, "orders") and backend.orders("", none, none, none) is not None
    local = local if local is not None else LOCAL_AT_ONCE if at_once else LOCAL
    size, m = path.m * 2**local, path.m
    d = shown(items, backend).select("task_id", "item_id", "chars", "lat", "fact", "text", "pos", F.floor(F.col("pos") / size).alias("block"))

    def block(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("pos")
        task, at = f["task_id"].iloc[0], int(f["block"].iloc[0])
        if at_once:
            orders = _orders(backend, task, f)
            return _taken(f, task, at, merge_all(len(f), m, k, orders), [orders.calls, orders.in_tok, orders.out_tok])
        keys, spent = keys_of(f), [0, 0, 0]
        by_id = {x.item_id: x for x in keys}
        order = _order(backend, task, path, spent)
        runs = [r[:k] for r in each(backend, order, [keys[i : i + m] for i in range(0, len(keys), m)])]
        while len(runs) > 1:
            g = merge_round(runs, by_id, m, k)
            try:
                wave = next(g)
                while True:
                    wave = g.send(each(backend, order, [list(w[1:]) for w in wave]))
            except StopIteration as end:
                runs = end.value
        return _rows(task, at, runs[0], by_id, spent)

    def pair(f: pd.DataFrame) -> pd.DataFrame:
        task, at = f["task_id"].iloc[0], int(f["block"].iloc[0]) // 2
        if at_once:
            f = f.sort_values(["block", "seq"])
            once, mine = f.drop_duplicates("block"), int((f["block"] == f["block"].iloc[0]).sum())
            orders = _orders(backend, task, f)
            merged = merge_pair(list(range(mine)), list(range(mine, len(f))), len(f) if k is None else min(k, len(f)), max(m // 2, 1), orders)
            more = (orders.calls, orders.in_tok, orders.out_tok)
            return _taken(f, task, at, np.array(merged, dtype=np.int64), [int(once[c].sum()) + x for c, x in zip(SPENT, more, strict=True)])
        by_id = {x.item_id: x for x in keys_of(f.assign(fact=None))}
        runs = [[int(i) for i in g.sort_values("seq")["item_id"]] for _, g in f.groupby("block")]
        once = f.drop_duplicates("block")
        spent = [int(once[c].sum()) for c in SPENT]
        if len(runs) == 2:
            order, g = _order(backend, task, path, spent), merge_two(runs[0], runs[1], m, k)
            try:
                ask = next(g)
                while True:
                    ask = g.send(order([by_id[x] for x in ask]))
            except StopIteration as end:
                runs = [end.value]
        return _rows(task, at, runs[0], by_id, spent)

    if at_once:
        # a block costs calls, which its bytes do not show
        d = d.repartition(spread(items.sparkSession), "task_id", "block")
    now = scratch.write("block0", d.groupBy("task_id", "block").applyInPandas(block, RUN))
    step, blocks = 0, (now.agg(F.max("block")).first()[0] or 0) + 1
    while blocks > 1:
        step, blocks = step + 1, -(-blocks // 2)
        pairs = now.withColumn("half", F.floor(F.col("block") / 2)).groupBy("task_id", "half").applyInPandas(pair, RUN)
        now = scratch.write(f"block{step}", pairs)
        scratch.drop(f"block{step - 1}")
    ranks = now.select("task_id", F.lit(path.path_id).alias("path_id"), "item_id", (F.col("seq") + 1).alias("rnk"))
    # a task's one run carries what all its calls have spent
    return ranks, now.groupBy("task_id").agg(*[F.max(c).alias(c) for c in SPENT]).select("task_id", F.lit(path.path_id).alias("path_id"), *SPENT, F.lit(0).cast("bigint").alias("lookups"))


def _orders(backend: ModelBackend, task: str, f: pd.DataFrame) -> Orders:
    return backend.orders(task, *[f[c].to_numpy(dtype=np.int64) for c in ("item_id", "lat", "chars")])


def _taken(f: pd.DataFrame, task: str, at: int, places: np.ndarray, spent: list[int]) -> pd.DataFrame:
    """``f``'s rows at ``places`` as a run."""
    return pd.DataFrame({"task_id": task, "block": at, "seq": np.arange(len(places)), **{c: f[c].to_numpy()[places] for c in ("item_id", "chars", "lat", "text")}, **dict(zip(SPENT, spent, strict=True))})


def _rows(task: str, at: int, ids: list[int], by_id: dict[int, Key], spent: list[int]) -> pd.DataFrame:
    keys = [by_id[i] for i in ids]
    return pd.DataFrame({"task_id": task, "block": at, "seq": range(len(ids)), "item_id": ids, "chars": [x.chars for x in keys], "lat": [x.latent for x in keys], "text": [x.text for x in keys], **dict(zip(SPENT, spent, strict=True))})


LIVE = "task_id string, seg string, at bigint, item_id bigint, pos bigint, chars int, lat bigint, text string, need bigint"
KEY = ("chars", "lat", "text")
SEG = ["task_id", "seg"]
#: A segment with up to so many unsettled items is settled within one worker (ids and verdicts only).
SETTLE = 100_000
#: A segment of up to so many items is sorted to its end within one worker.
FINISH = 5000
#: The same for backends that answer a wave at once: equal items in id order take a level each, so their levels must not be jobs.
FINISH_AT_ONCE = 50_000
#: What holds more than one in so many live items is hot: fewer than so many can.
HOT = 500


def _key(i, c, x, t) -> Key:
    return Key(int(i), int(c), int(x), None, t)


def by_segment(rows: DataFrame, stats: DataFrame, total: int) -> DataFrame:
    """``rows`` with the ``stats`` (a row per segment, with its size ``n``) of theirs; hot segments are broadcast, so no task gets all of one."""
    hot = F.col("n") * HOT > total
    few, rest = stats.where(hot), stats.where(~hot)
    cool = rows.join(F.broadcast(few.select(*SEG)), SEG, "left_anti").join(rest, SEG)
    return rows.join(F.broadcast(few), SEG).unionByName(cool)


def quick_waves(
    items: DataFrame, path: PathConfig, backend: ModelBackend, k: int | Column | None = None, *, max_levels: int = 200, settle_packed: int = SETTLE, finish: int | None = None, seed: int = 7, scratch: Scratch | None = None
) -> tuple[DataFrame, DataFrame]:
    """Quick sort with v votes, a few jobs per level over all segments of all tasks; a segment of ``finish`` items or fewer is sorted to its end in one worker.

    A segment's pivot is its first item; verdicts against pivots are one wave, those against peers another. Peers are drawn by hashed
    places in the other side, so they meet by an equi-join. Segment sizes decide what a limit still needs: dropped segments cost nothing further.
    """
    if path.pivot != "first":
        raise ValueError("waves take the first item as pivot; other rules run packed")
    scratch = scratch or Scratch(items.sparkSession, "quick")
    finish = finish or (FINISH_AT_ONCE if hasattr(backend, "compare_many") else FINISH)
    apart = spread(items.sparkSession)
    n = scratch.write("shown", shown(items, backend))
    sizes = n.groupBy("task_id").agg(F.count("*").alias("size"))
    live = n.join(sizes, "task_id").select("task_id", F.lit("").alias("seg"), F.lit(0).cast("bigint").alias("at"), "item_id", F.col("pos").cast("bigint").alias("pos"), *KEY, F.least("size", F.lit(k if k is not None else 2**62)).alias("need"))
    live = scratch.write("live0", live.where("need > 0"))
    done, spent, level = None, None, 0

    def end(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("pos")
        task, at, need = f["task_id"].iloc[0], int(f["at"].iloc[0]), int(f["need"].iloc[0])
        ids, usage = run_path(keys_of(f.assign(fact=None)), path, need, backend, task, by_wave=False)
        out = pd.DataFrame({"task_id": task, "item_id": ids, "rnk": range(at + 1, at + len(ids) + 1)})
        # the first row carries what all calls have spent
        return out.assign(**{c: [sum(u[i] for u in usage.values())] + [0] * (len(ids) - 1) for i, c in enumerate(SPENT)})

    while total := live.count():
        if level >= max_levels:
            raise ValueError(f"still unsorted after {max_levels} levels: use another pivot rule packed")
        # one pass per segment: its pivot; a hot segment is summed partially
        pivots = scratch.write(f"pivots{level}", live.groupBy(*SEG).agg(F.count("*").alias("n"), F.min_by(F.struct("item_id", *KEY), "pos").alias("p")))
        met = by_segment(live, pivots, total)
        ends = scratch.write(f"ends{level}", met.where(F.col("n") <= finish).repartition(apart, *SEG).groupBy(*SEG).applyInPandas(end, "task_id string, item_id bigint, rnk bigint, calls bigint, in_tok bigint, out_tok bigint"))
        paid = ends.groupBy("task_id").agg(*[F.sum(c).alias(c) for c in SPENT])
        placed = ends.select("task_id", "item_id", "rnk")
        done, spent = (placed, paid) if done is None else (done.unionByName(placed), spent.unionByName(paid))
        if not pivots.where(F.col("n") > finish).limit(1).count():
            break
        met = met.where(F.col("n") > finish)

        def ask(frames):
            for f in frames:
                pairs = [(t, _key(i, c, x, s), _key(p["item_id"], p["chars"], p["lat"], p["text"])) for t, i, c, x, s, p in zip(f["task_id"], f["item_id"], f["chars"], f["lat"], f["text"], f["p"], strict=True)]
                yield _compared(f.drop(columns=["p", "n"]).assign(pivot=[b.item_id for _, _, b in pairs]), backend, pairs, "side")

        judged = scratch.write(f"judged{level}", met.select(*live.columns, "n", "p").mapInPandas(ask, LIVE + ", side int, pivot bigint, calls bigint, in_tok bigint, out_tok bigint"))
        paid = judged.groupBy("task_id").agg(*[F.sum(c).alias(c) for c in SPENT])
        judged = judged.drop(*SPENT)
        if path.v > 1:
            judged, peers_paid = _peer_votes(judged, path, backend, scratch, level, settle_packed, seed)
            paid = paid.unionByName(peers_paid)
        spent = spent.unionByName(scratch.write(f"paid{level}", paid))
        more = scratch.write(f"greater{level}", judged.groupBy(*SEG).agg(F.count("*").alias("n"), F.count_if(F.col("side") > 0).alias("g")))
        d = scratch.write(f"divided{level}", by_segment(judged, more, total))
        placed = d.where("side = 0 and need > g").select("task_id", "item_id", (F.col("at") + F.col("g") + 1).alias("rnk"))
        rest = lambda seg, at, need: ("task_id", F.concat("seg", F.lit(seg)).alias("seg"), at.alias("at"), "item_id", "pos", *KEY, need.alias("need"))
        up = d.where("side > 0").select(*rest("g", F.col("at"), F.least("need", "g")))
        down = d.where("side < 0 and need > g + 1").select(*rest("l", F.col("at") + F.col("g") + 1, F.col("need") - F.col("g") - 1))
        done = done.unionByName(scratch.write(f"placed{level}", placed))
        level += 1
        live = scratch.write(f"live{level}", up.unionByName(down))
        scratch.drop(f"live{level - 1}", f"judged{level - 1}", f"divided{level - 1}", f"pivots{level - 1}", f"greater{level - 1}")
    if done is None:
        done = items.sparkSession.createDataFrame([], "task_id string, item_id bigint, rnk bigint")
        spent = items.sparkSession.createDataFrame([], "task_id string, calls bigint, in_tok bigint, out_tok bigint")
    usage = spent.groupBy("task_id").agg(*[F.sum(c).alias(c) for c in SPENT]).select("task_id", F.lit(path.path_id).alias("path_id"), *SPENT, F.lit(0).cast("bigint").alias("lookups"))
    return done.select("task_id", F.lit(path.path_id).alias("path_id"), "item_id", "rnk"), usage


def _compared(f: pd.DataFrame, backend: ModelBackend, pairs: list[tuple[str, Key, Key]], to: str) -> pd.DataFrame:
    """``f`` with the verdicts on ``pairs`` (0 and no call for an item against itself) and what each cost."""
    got = each(backend, lambda q: (0, None) if q[1].item_id == q[2].item_id else backend.compare(*q), pairs)
    cost = {"calls": [int(u is not None) for _, u in got], "in_tok": [u.in_tok if u else 0 for _, u in got], "out_tok": [u.out_tok if u else 0 for _, u in got]}
    return f.assign(**{to: [v for v, _ in got]}, **cost)


def _peer_votes(judged: DataFrame, path: PathConfig, backend: ModelBackend, scratch: Scratch, level: int, settle_packed: int, seed: int) -> tuple[DataFrame, DataFrame]:
    """``judged`` with the sides that remain after peers were asked and conflicts settled, and what the peers cost."""
    rows = judged.where("side <> 0")
    side_key = [*SEG, "side"]
    ranked = indexed(rows, [*side_key, "pos", "item_id"], scratch, name=f"idx{level}").withColumnRenamed(f"idx{level}", "idx")
    groups = ranked.groupBy(*side_key).agg(F.min("idx").alias("from"), F.count("*").alias("n"))
    placed = ranked.join(groups, side_key).withColumn("slot", F.col("idx") - F.col("from")).drop("from", "n")
    others = groups.select(*SEG, (-F.col("side")).alias("side"), F.col("n").alias("others"))
    mine = placed.join(others, side_key, "left").withColumn("others", F.coalesce("others", F.lit(0)))
    draws = path.v - 1

    def draw(frames):
        for f in frames:
            f = f.assign(slot=[peer_slots(seed, int(p), int(x), int(o), draws) for p, x, o in zip(f["pivot"], f["item_id"], f["others"], strict=True)])
            f = f.assign(j=[list(range(len(s))) for s in f["slot"]]).explode(["slot", "j"]).dropna(subset=["slot"])
            yield f[["task_id", "seg", "side", "item_id", *KEY, "slot", "j"]].astype({"slot": "int64", "j": "int64"})

    wanted = mine.select("task_id", "seg", "side", "item_id", *KEY, "pivot", "others").mapInPandas(draw, "task_id string, seg string, side int, item_id bigint, chars int, lat bigint, text string, slot bigint, j bigint")
    peer = placed.select(*SEG, (-F.col("side")).alias("side"), "slot", F.col("item_id").alias("y"), F.col("chars").alias("yc"), F.col("lat").alias("yl"), F.col("text").alias("yt"))
    pairs = wanted.join(peer, [*side_key, "slot"])

    def ask(frames):
        for f in frames:
            q = [(t, _key(*a), _key(*b)) for t, *ab in zip(f["task_id"], f["item_id"], f["chars"], f["lat"], f["text"], f["y"], f["yc"], f["yl"], f["yt"], strict=True) for a, b in [(ab[:4], ab[4:])]]
            yield _compared(f[["task_id", "seg", "item_id", "j", "y"]], backend, q, "r")

    asked = scratch.write(f"peers{level}", pairs.mapInPandas(ask, "task_id string, seg string, item_id bigint, j bigint, y bigint, r int, calls bigint, in_tok bigint, out_tok bigint"))
    heard = asked.groupBy(*SEG, "item_id").agg(F.array_sort(F.collect_list(F.struct("j", "y", "r"))).alias("peers"))
    state = rows.select(*SEG, "item_id", "pos", F.col("side").alias("first")).join(heard, [*SEG, "item_id"], "left")
    less, more = F.exists("peers", lambda p: p["r"] < 0), F.exists("peers", lambda p: p["r"] > 0)
    one = F.when(less, F.lit(-1)).otherwise(F.lit(1))
    agreed = F.when(F.col("peers").isNull(), F.col("first")).when(less != more, one if path.peer_override else F.when(one == F.col("first"), one))
    state = scratch.write(f"state{level}-0", state.withColumn("final", agreed.cast("int")))
    step = 0
    while True:
        open_ = state.where("final is null")
        most = open_.groupBy(*SEG).agg(F.count("*").alias("c")).agg(F.max("c")).first()[0] or 0
        if not most:
            break
        side_of = state.where("final is not null").select(*SEG, F.col("item_id").alias("y"), F.col("final").alias("ys"))
        seen = open_.select(*SEG, "item_id", "pos", "first", F.explode("peers").alias("p")).select(*SEG, "item_id", "pos", "first", F.col("p.j").alias("j"), F.col("p.y").alias("y"), F.col("p.r").alias("r"))
        seen = seen.join(side_of, [*SEG, "y"], "left")
        now = seen.groupBy(*SEG, "item_id", "pos", "first").agg(F.array_sort(F.collect_list(F.struct("j", "y", "r", "ys"))).alias("heard"))
        if most <= settle_packed:
            voted = now.groupBy(*SEG).applyInPandas(_settle_segment, "task_id string, seg string, item_id bigint, final int")
        else:
            # one round for all segments: who is ready votes; where nobody is, the first in input order
            votes = lambda s: F.size(F.filter("heard", lambda p: (p["ys"] == s) & (p["r"] == s))) + F.when(F.col("first") == s, 1.5).otherwise(0.0)
            ready = F.forall("heard", lambda p: p["ys"].isNotNull())
            now = now.withColumn("ready", ready).withColumn("vote", F.when(votes(-1) > votes(1), -1).otherwise(1))
            stuck = now.groupBy(*SEG).agg(F.max("ready").alias("any"), F.min_by("item_id", "pos").alias("lead"))
            voted = now.join(stuck, SEG).where(F.col("ready") | (~F.col("any") & (F.col("item_id") == F.col("lead")))).select(*SEG, "item_id", F.col("vote").cast("int").alias("final"))
        step += 1
        voted = scratch.write(f"voted{level}-{step}", voted).withColumnRenamed("final", "new")
        state = scratch.write(f"state{level}-{step}", state.join(voted, [*SEG, "item_id"], "left").withColumn("final", F.coalesce("final", "new")).drop("new"))
    ends = state.select(*SEG, "item_id", F.col("final").alias("end"))
    settled = scratch.write(f"settled{level}", judged.join(ends, [*SEG, "item_id"], "left").withColumn("side", F.coalesce("end", "side")).drop("end"))
    return settled, asked.groupBy("task_id").agg(*[F.sum(c).alias(c) for c in SPENT])


def _settle_segment(f: pd.DataFrame) -> pd.DataFrame:
    f = f.sort_values("pos")
    peers = {int(x): [(int(p["y"]), int(p["r"])) for p in h] for x, h in zip(f["item_id"], f["heard"], strict=True)}
    known = {int(p["y"]): int(p["ys"]) for h in f["heard"] for p in h if p["ys"] is not None and p["ys"] == p["ys"]}
    side = settle([int(x) for x in f["item_id"]], {int(x): int(r) for x, r in zip(f["item_id"], f["first"], strict=True)}, peers, known=known)
    return pd.DataFrame({"task_id": f["task_id"], "seg": f["seg"], "item_id": f["item_id"], "final": [side[int(x)] for x in f["item_id"]]})
