"""Packed execution: each (task, path) runs whole in one worker; tasks run in parallel.

Its result is one written table with a ``part`` column: 'rank' rows (the ranking), 'usage' rows (calls, tokens and
nano-dollars by operation and wave) and, on request, 'reply' rows (what was asked and answered, for reuse). It is written exactly
once, because running it again would pay again. A key's text travels only for backends that read it.
"""

from __future__ import annotations

import hashlib
import json
import math
from collections.abc import Callable, Mapping, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec import generators
from semrank.exec.scratch import Scratch
from semrank.exec.slides import LEAST, slide_all
from semrank.plans.complexity import candidates_frame
from semrank.plans.spec import PathConfig
from semrank.sources.model import Key, ModelBackend, Usage, each, nano_usd, repair_order, repair_scores

RESULT = "part string, task_id string, path_id string, item_id bigint, rnk bigint, op string, wave int, calls bigint, in_tok bigint, out_tok bigint, lookups bigint, nano_usd bigint, repairs bigint, hits bigint, req string, reply string"
NUMBERS = ("item_id", "rnk", "calls", "in_tok", "out_tok", "lookups", "nano_usd", "repairs", "hits")
#: Beyond so many items a task should run in waves (semrank.exec.waves).
PACKED_MAX = 5000
#: Partitions a core at least: a task costs calls, which its bytes do not show, so partitions must not be joined by bytes.
SPREAD = 16


def answer(backend: ModelBackend, task: str, request: tuple, path: PathConfig) -> tuple[object, Usage, int]:
    """One call: reply, usage, repairs."""
    op, args = request[0], request[1:]
    if op == "order":
        reply, used = backend.order(task, args)
        order, repairs = repair_order(reply, args)
        return order, used, repairs
    if op == "compare":
        reply, used = backend.compare(task, args[0], args[1])
        return reply, used, 0
    more = {"lookup": True} if path.lookup else {}
    if op == "score":
        reply, used = backend.score(task, args[0], path.max_point, **more)
        return reply, used, 0
    return repair_scores(lambda: backend.score_many(task, args[0], args[1:], path.max_point, **more), args[1:])


def request_key(backend: ModelBackend, task: str, request: tuple, path: PathConfig) -> str:
    """A hash of everything that decides the reply: the model and criterion, the operation, its settings and the keys shown."""
    op, *args = request
    settings = [path.max_point, path.lookup] if op.startswith("score") else []
    keys = [[k.item_id, k.text, k.chars, k.latent, k.fact] if isinstance(k, Key) else k for k in args]
    return hashlib.sha256(json.dumps([backend.identity(), task, op, settings, keys]).encode()).hexdigest()


def run_path(
    keys: Sequence[Key], path: PathConfig, k: int | None, backend: ModelBackend, task: str, *, known: Mapping[str, str] | None = None, kept: dict[str, str] | None = None, by_wave: bool = True
) -> tuple[list[int], dict[tuple[str, int | None], list[int]]]:
    """A ranking, and per (op, wave): calls, tokens in, tokens out, lookups, repairs, hits.

    ``known``: replies by request that are not paid again. ``kept`` receives the replies of this run. Without ``by_wave`` the usage
    is summed by operation, with None as the wave: a sliding window has as many waves as calls.
    """
    if path.kind == "slide_window" and not by_wave and not known and kept is None and (slid := _slid(keys, path, k, backend, task)):
        return slid
    steps, usage, wave = generators.PATHS[path.kind](keys, path, k), {}, 0
    try:
        request = next(steps)
        plain = not known and kept is None and backend.threads <= 1
        order, at_once = backend.order, getattr(backend, "compare_many", None)
        while plain:
            if at_once and isinstance(request, generators.Pairs):
                # every pair is asked, in one go
                got, in_tok, out_tok = at_once(task, request)
                u = usage.setdefault(("compare", wave if by_wave else None), [0, 0, 0, 0, 0, 0])
                u[0] += len(request)
                u[1] += in_tok
                u[2] += out_tok
                wave += bool(request)
                request = steps.send(got)
                continue
            if len(request) == 1 and request[0][0] == "order":
                # a chain of single calls: the shortest way round
                shown = request[0][1:]
                got, used = order(task, shown)
                got, repairs = repair_order(got, shown)
                at = ("order", wave if by_wave else None)
                u = usage.get(at)
                if u is None:
                    u = usage[at] = [0, 0, 0, 0, 0, 0]
                u[0] += 1
                u[1] += used[0]
                u[2] += used[1]
                u[4] += repairs
                wave += 1
                request = steps.send([got])
                continue
            replies = []
            for r in request:
                got, used, repairs = answer(backend, task, r, path)
                replies.append(got)
                at = (r[0], wave if by_wave else None)
                u = usage.get(at)
                if u is None:
                    u = usage[at] = [0, 0, 0, 0, 0, 0]
                u[0] += 1
                u[1] += used[0]
                u[2] += used[1]
                u[3] += used[2]
                u[4] += repairs
            wave += bool(request)
            request = steps.send(replies)
        while True:
            names = [request_key(backend, task, r, path) for r in request] if known or kept is not None else [""] * len(request)
            had = [json.loads(known[n]) if known and n in known else None for n in names]
            asked = iter(each(backend, lambda r: answer(backend, task, r, path), [r for r, h in zip(request, had, strict=True) if h is None]))
            replies = []
            for r, name, h in zip(request, names, had, strict=True):
                u = usage.setdefault((r[0], wave if by_wave else None), [0, 0, 0, 0, 0, 0])
                if h is not None:
                    u[5] += 1
                    replies.append(h)
                    continue
                got, used, repairs = next(asked)
                for i, x in enumerate((1, used.in_tok, used.out_tok, used.lookups, repairs)):
                    u[i] += x
                replies.append(got)
                if kept is not None:
                    kept[name] = json.dumps(got)
            wave += bool(request)
            request = steps.send(replies)
    except StopIteration as end:
        return end.value, usage


def _slid(keys: Sequence[Key], path: PathConfig, k: int | None, backend: ModelBackend, task: str) -> tuple[list[int], dict] | None:
    """A sliding window's ranking and usage, if the backend answers many lists at once and the task is worth it."""
    if len(keys) < LEAST or not hasattr(backend, "lists"):
        return None
    ids, latent, chars = generators.Columns(keys).numbers
    lists = backend.lists(task, ids, latent, chars, path.m) if len(np.unique(ids)) == len(ids) else None
    if lists is None or path.stop_when_stable and not lists.steady:
        return None
    places, calls, items, in_tok = slide_all(path, k, lists)
    return ids[places].tolist(), {("order", None): [calls, in_tok, lists.out_tok(calls, items), 0, 0, 0]} if calls else {}


def keys_of(f: pd.DataFrame) -> list[Key]:
    return [Key(int(i), int(c), int(x), None if pd.isna(y) else int(y), t) for i, c, x, y, t in zip(f["item_id"], f["chars"], f["lat"], f["fact"], f["text"], strict=True)]


def _table(task: str, path_id: str, ranked: Sequence[int], usage: Mapping, kept: Mapping[str, str] | None, tier: str) -> pd.DataFrame:
    """One run's rows, made by column: a long chain has many."""
    kept, names = kept or {}, [c.split()[0] for c in RESULT.split(", ")]
    n, spent = (len(ranked), len(usage), len(kept)), list(usage.values())
    numbers = dict(zip(("calls", "in_tok", "out_tok", "lookups", "repairs", "hits"), zip(*spent, strict=True), strict=True)) if spent else {}
    middle = {"op": [op for op, _ in usage], "wave": [w for _, w in usage], "nano_usd": [nano_usd(u[1], u[2], u[3], tier) for u in spent], **numbers}
    head, tail = {"item_id": list(ranked), "rnk": range(1, n[0] + 1)}, {"req": kept.keys(), "reply": kept.values()}
    part = ["rank"] * n[0] + ["usage"] * n[1] + ["reply"] * n[2]
    made = {c: [*x.get(c, [None] * size)] for x, size in ((head, n[0]),) for c in names}
    for x, size in ((middle, n[1]), (tail, n[2])):
        for c in names:
            made[c] += [*x.get(c, [None] * size)]
    types = dict.fromkeys(NUMBERS, "Int64") | {"wave": "Int32"}
    return pd.DataFrame({c: pd.array(v, dtype=types[c]) if c in types else pd.Series(v, dtype=object) for c, v in (made | {"part": part, "task_id": [task] * sum(n), "path_id": [path_id] * sum(n)}).items()})[names]


def _runner(backend: ModelBackend, keep: bool, by_wave: bool = True, paths: Sequence[PathConfig] | None = None) -> Callable[..., pd.DataFrame]:
    """A task's run of the path that its rows name, or of all ``paths`` in turn."""

    def run(f: pd.DataFrame, cached: pd.DataFrame | None = None) -> pd.DataFrame:
        if f.empty:
            return pd.DataFrame(columns=[c.split()[0] for c in RESULT.split(", ")])
        f = f.sort_values(["pos", "item_id"])
        p = f.iloc[0]
        task, k = p["task_id"], (None if pd.isna(p["k"]) else int(p["k"]))
        if paths is None:
            todo = [(p["path_id"], PathConfig(p["kind"], int(p["m"]), int(p["v"]), bool(p["lookup"]), int(p["max_point"]), p["pivot"], bool(p["rescan"]), bool(p["stop_when_stable"]), bool(p["peer_override"])))]
        else:
            todo = [(x.path_id, x) for x in paths]
        model = backend.about(p["criterion"], backend.descending) if p["criterion"] else backend
        known = None if cached is None or cached.empty else dict(zip(cached["req"], cached["reply"], strict=True))
        keys, out = keys_of(f), []
        del f
        for path_id, path in todo:
            kept = {} if keep else None
            ranked, usage = run_path(keys, path, k, model, task, known=known, kept=kept, by_wave=by_wave)
            out.append(_table(task, path_id, ranked, usage, kept, backend.tier))
        return out[0] if len(out) == 1 else pd.concat(out, ignore_index=True)

    return run


def measured(items: DataFrame) -> Column:
    """The length of a key: that of the column ``chars``, if it is there (see ``slim``)."""
    return F.col("chars") if "chars" in items.columns else F.length("key")


def slim(items: DataFrame, backend: ModelBackend) -> DataFrame:
    """``items`` without the texts of their keys, which have their lengths in ``chars``, where the backend reads none; keys that are null or empty stay so."""
    if backend.reads_text or "chars" in items.columns:
        return items
    return items.withColumn("chars", F.length("key")).withColumn("key", F.when(F.col("key") != "", F.lit("x")).otherwise(F.col("key")))


def shown(items: DataFrame, backend: ModelBackend) -> DataFrame:
    """task_id, item_id, pos, chars, lat, k, fact, text, criterion of items with a key; text is empty where the backend reads none."""
    optional = {"k": "bigint", "fact": "bigint", "criterion": "string"}
    more = [(F.col(c) if c in items.columns else F.lit(None)).cast(t).alias(c) for c, t in optional.items()]
    text = F.col("key") if backend.reads_text else F.lit("")
    return items.where("key is not null and key <> ''").select("task_id", "item_id", "pos", measured(items).alias("chars"), F.col("lat").cast("bigint").alias("lat"), text.alias("text"), *more)


def spread(spark: SparkSession) -> int:
    """Partitions for rows that are tasks."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), SPREAD * spark.sparkContext.defaultParallelism)


def run_paths(
    items: DataFrame, paths: list[PathConfig] | DataFrame, backend: ModelBackend, *, scratch: Scratch | None = None, name: str = "run", keep: bool = False, cached: DataFrame | None = None, max_in_flight: int | None = None,
    by_wave: bool = True, together: bool = False,
) -> DataFrame:
    """Run each path on each task. ``items``: task_id, item_id, pos, key, lat, and optional k, fact and criterion (of the task).

    ``paths`` is a list (every path on every task) or a table (task_id, path_id) joined with its configuration. ``keep`` adds the replies;
    ``cached`` (task_id, path_id, req, reply) holds replies that are not paid again. ``max_in_flight`` bounds the calls of all workers at once.
    ``by_wave``: whether usage is kept apart by wave. ``together`` runs a list of paths on a task in one worker, so that its items travel once: for many tasks.
    Keys that are null or empty are not sent to a model: see ``operators.frame`` for where they are put.
    """
    spark = items.sparkSession
    scratch = scratch or Scratch(spark, "paths")
    d = shown(items, backend)
    apart = spread(spark)
    if together and not isinstance(paths, DataFrame) and cached is None and max_in_flight is None:
        run = _runner(backend, keep, by_wave, paths)
        return scratch.write(name, d.repartition(apart, "task_id").groupBy("task_id").applyInPandas(lambda f: run(f), RESULT))
    if isinstance(paths, DataFrame):
        d = d.join(paths, "task_id")
    else:
        d = d.crossJoin(F.broadcast(candidates_frame(spark, paths)))  # a few rows by construction
    if max_in_flight is not None:
        # a partition is one task, which has as many calls in flight as the backend has threads
        apart = max(1, math.floor(max_in_flight / backend.threads))
    d = d.repartition(apart, "task_id", "path_id")
    run, groups = _runner(backend, keep, by_wave), d.groupBy("task_id", "path_id")
    if cached is None:
        return scratch.write(name, groups.applyInPandas(lambda f: run(f), RESULT))
    return scratch.write(name, groups.cogroup(cached.groupBy("task_id", "path_id")).applyInPandas(lambda f, c: run(f, c), RESULT))


def rankings_of(result: DataFrame) -> DataFrame:
    return result.where("part = 'rank'").select("task_id", "path_id", "item_id", "rnk")


def usage_of(result: DataFrame) -> DataFrame:
    return result.where("part = 'usage'").select("task_id", "path_id", "op", "wave", "calls", "in_tok", "out_tok", "lookups", "nano_usd", "repairs", "hits")


def replies_of(result: DataFrame) -> DataFrame:
    """(task_id, req, reply): each request of a task once, whichever path asked it."""
    return result.where("part = 'reply'").select("task_id", "req", "reply").dropDuplicates(["task_id", "req"])
