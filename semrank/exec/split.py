"""A full sort of very large tasks without one long chain of merges: split by sampled items, sort the parts apart.

Not one of the studied paths, an extra one for full orders: with p parts it costs N log2(p) parallel comparisons and p merges of N/p
items, where the last merge of an external merge is one sequential chain of some N calls in one worker.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.generators import Columns, Pairs
from semrank.exec.index import placed_by
from semrank.exec.packed import keys_of, run_path, shown
from semrank.exec.scratch import Scratch
from semrank.exec.waves import SPENT, _key, merge_waves
from semrank.plans.spec import EXT_MERGE, PathConfig
from semrank.sources.model import Key, ModelBackend

#: Splitters travel with the items of their task: so many at most.
MOST_PARTS = 256
#: Splitters of all tasks together that a worker holds; more travel with their items.
MOST_CUTS = 100_000
CUTS = "task_id string, cuts array<struct<item_id:bigint,chars:int,lat:bigint,text:string>>, calls bigint, in_tok bigint, out_tok bigint"


def split_merge(items: DataFrame, backend: ModelBackend, parts: int = 8, path: PathConfig = EXT_MERGE, oversample: int = 4, scratch: Scratch | None = None) -> tuple[DataFrame, DataFrame]:
    """((task_id, path_id, item_id, rnk), usage) of full orders of any number of tasks."""
    if not 2 <= parts <= MOST_PARTS:
        raise ValueError(f"parts is 2 to {MOST_PARTS}")
    from semrank.plans.optimizer import sample_items

    scratch = scratch or Scratch(items.sparkSession, "split")
    drawn = shown(sample_items(items.where("key is not null and key <> ''"), parts * oversample), backend)

    def choose(f: pd.DataFrame) -> pd.DataFrame:
        task, keys = f["task_id"].iloc[0], keys_of(f.sort_values("item_id"))
        by_id = {x.item_id: x for x in keys}
        ordered, usage = run_path(keys, path, None, backend, task)
        cuts = [by_id[i] for i in ordered[oversample - 1 :: oversample]][: parts - 1]
        spent = [sum(u[i] for u in usage.values()) for i in range(3)]
        return pd.DataFrame([(task, [{"item_id": x.item_id, "chars": x.chars, "lat": x.latent, "text": x.text} for x in cuts], *spent)], columns=["task_id", "cuts", *SPENT])

    cuts = scratch.write("cuts", drawn.groupBy("task_id").applyInPandas(choose, CUTS))

    def placed_in(f: pd.DataFrame, cuts_of) -> pd.DataFrame:
        """``f`` with the part of each row; what a task's rows have cost is on its first."""
        found, spent = np.zeros(len(f), dtype=np.int64), np.zeros((len(f), 3), dtype=np.int64)
        for task, at in f.groupby("task_id", sort=False).indices.items():
            own = cuts_of(task, int(at[0]))
            if hasattr(backend, "compare_many"):
                found[at], spent[at[0]] = _place_all(backend, task, f.iloc[at], own)
                continue
            for i, x in zip(at, zip(*[f[c].iloc[at] for c in ("item_id", "chars", "lat", "text")], strict=True), strict=True):
                found[i], spent[i] = _place(backend, task, _key(*x), own)
        return f.assign(part=found, **{c: spent[:, i] for i, c in enumerate(SPENT)})

    read = lambda own: [_key(c["item_id"], c["chars"], c["lat"], c["text"]) for c in own]
    full = shown(items, backend).select("task_id", "item_id", F.col("pos").cast("bigint").alias("pos"), "chars", "lat", "text")
    schema = "task_id string, item_id bigint, pos bigint, chars int, lat bigint, text string, part int, calls bigint, in_tok bigint, out_tok bigint"
    if cuts.count() * parts <= MOST_CUTS:
        # few splitters, just counted: they wait where the items are
        known = {r["task_id"]: read(r["cuts"]) for r in cuts.select("task_id", "cuts").collect()}
        placed = full.mapInPandas(lambda frames: (placed_in(f, lambda task, _: known[task]) for f in frames), schema)
    else:
        placed = full.join(cuts.select("task_id", "cuts"), "task_id").mapInPandas(lambda frames: (placed_in(f, lambda _, at, f=f: read(f["cuts"].iloc[at])).drop(columns=["cuts"]) for f in frames), schema)
    placed = scratch.write("placed", placed)
    sizes = placed.groupBy("task_id", "part").agg(F.count("*").alias("n"))
    sub_id = F.concat_ws("#", "task_id", "part")
    before = scratch.write("before", sizes.select("task_id", sub_id.alias("sub"), (F.sum("n").over(W.partitionBy("task_id").orderBy("part")) - F.col("n")).alias("before")))
    # the text that a backend reads is the key itself; for the others any key that is not empty will do
    key = F.col("text") if backend.reads_text else F.lit("x")
    sub = placed.select(sub_id.alias("task_id"), "item_id", "pos", key.alias("key"), "chars", "lat")
    sub = placed_by(sub, ["pos"], scratch, "at").withColumn("pos", F.col("at") - 1).drop("at")
    ranks, merged = merge_waves(sub, path, backend, scratch=Scratch(items.sparkSession, "split-parts"))
    out = ranks.withColumnRenamed("task_id", "sub").join(before, "sub")
    out = out.select("task_id", "path_id", "item_id", (F.col("rnk") + F.col("before")).alias("rnk"))
    spent = [cuts.select("task_id", *SPENT), placed.select("task_id", *SPENT), merged.withColumnRenamed("task_id", "sub").join(before, "sub").select("task_id", *SPENT)]
    usage = spent[0].unionByName(spent[1]).unionByName(spent[2]).groupBy("task_id").agg(*[F.sum(c).alias(c) for c in SPENT])
    return out, usage.select("task_id", F.lit(path.path_id).alias("path_id"), *SPENT, F.lit(0).cast("bigint").alias("lookups"))


def _place(backend: ModelBackend, task: str, key: Key, cuts: list[Key]) -> tuple[int, list[int]]:
    """The part of a key by a binary search, and what it cost."""
    lo, hi, spent = 0, len(cuts), [0, 0, 0]
    while lo < hi:
        mid = (lo + hi) // 2
        ahead = cuts[mid].item_id == key.item_id
        if not ahead:
            verdict, used = backend.compare(task, key, cuts[mid])
            spent = [spent[0] + 1, spent[1] + used.in_tok, spent[2] + used.out_tok]
            ahead = verdict > 0
        lo, hi = (lo, mid) if ahead else (mid + 1, hi)
    return lo, spent


def _place_all(backend: ModelBackend, task: str, f: pd.DataFrame, cuts: list[Key]) -> tuple[np.ndarray, list[int]]:
    """``_place`` of a task's rows, which search in step, and what all have cost."""
    n, of_cuts = len(f), Columns(cuts).numbers
    shown = Columns.of(*[np.concatenate([f[c].to_numpy(dtype=np.int64), x]) for c, x in zip(("item_id", "lat", "chars"), of_cuts, strict=True)])
    ids = shown.numbers[0]
    lo, hi, spent = np.zeros(n, dtype=np.int64), np.full(n, len(cuts), dtype=np.int64), [0, 0, 0]
    while len(at := np.flatnonzero(lo < hi)):
        mid = (lo[at] + hi[at]) // 2
        ahead = ids[n + mid] == ids[at]
        ask = np.flatnonzero(~ahead)
        if len(ask):
            verdicts, in_tok, out_tok = backend.compare_many(task, Pairs(shown, at[ask], n + mid[ask]))
            ahead[ask] = verdicts > 0
            spent = [spent[0] + len(ask), spent[1] + in_tok, spent[2] + out_tok]
        hi[at[ahead]], lo[at[~ahead]] = mid[ahead], mid[~ahead] + 1
    return lo, spent
