"""The ordering as a DataFrame operator."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.index import placed_by
from semrank.exec.packed import PACKED_MAX, rankings_of, run_paths, slim
from semrank.exec.scratch import Scratch
from semrank.exec.waves import FINISH_AT_ONCE
from semrank.plans.optimizer import SAMPLE, optimize, run_in_waves
from semrank.plans.spec import EXT_MERGE, PathConfig, RankSpec
from semrank.sources.lookup import with_facts
from semrank.sources.model import ModelBackend, SimBackend


def llm_order_by(
    df: DataFrame,
    key: str | list[str],
    criterion: str,
    *,
    desc: bool = True,
    limit: int | None = None,
    partition_by: str | list[str] | None = None,
    id_col: str,
    latent: str | Column | dict[str, str] | None = None,
    facts: DataFrame | None = None,
    path: PathConfig | None = None,
    budget_nano: int | None = None,
    policy: str = "consensus",
    sample: int = SAMPLE,
    nulls: str = "last",
    dedup_keys: bool = False,
    backend: ModelBackend | None = None,
    packed_max: int | None = None,
    max_in_flight: int | None = None,
) -> DataFrame:
    """``df`` with ``rnk`` (1-based, per partition) by a criterion in words, cut to ``limit``.

    ``key``: the column shown to the model, or several (as JSON). ``id_col``: a unique bigint; a null id is an error. The criterion and the direction
    go into every request, and with a backend that reads text the key's text does too. ``latent``: what the simulator knows, 0 to 10000 (0 without it); a
    dictionary has a column for each criterion it knows. ``facts`` (key, value, and origin for conflicts): what lookup paths are grounded in.
    Without a path a budget makes the optimizer choose; without either it is an external merge. Null and empty keys are not
    sent; they come last, first, or are an error. ``dedup_keys`` ranks distinct keys and gives equal keys neighbouring ranks.
    If a partition has more than ``packed_max`` rows the partitions run in waves and are numbered without a window over all their rows; without it that is ``PACKED_MAX``, or for a
    quick sort by a backend that answers a wave of comparisons at once ``FINISH_AT_ONCE``, as waves too sort so many in one worker. A sliding window is one sequential
    chain, which runs in a worker however large the partition is, unless ``packed_max`` forbids it.
    """
    by = [partition_by] if isinstance(partition_by, str) else list(partition_by or [])
    spec = RankSpec(criterion, desc, limit, nulls, partition_by=tuple(by))
    missing = [c for c in [id_col, *by, *([key] if isinstance(key, str) else key)] if c not in df.columns]
    if missing:
        raise ValueError(f"no column {', '.join(missing)}")
    backend = (backend or SimBackend()).about(criterion, desc)
    scratch = Scratch(df.sparkSession, "order")
    shown = F.col(key).cast("string") if isinstance(key, str) else F.to_json(F.struct(*key))
    known = latent.get(criterion) if isinstance(latent, dict) else latent
    lat = F.lit(0) if known is None else (F.col(known) if isinstance(known, str) else known)
    # JSON keeps apart what a plain join of the values would not, and nulls from empty strings
    task = F.to_json(F.struct(*by)) if by else F.lit("all")
    base = df.select(task.alias("task_id"), F.col(id_col).cast("bigint").alias("item_id"), shown.alias("key"), lat.cast("bigint").alias("lat"))
    chain = packed_max is None and path is not None and path.kind == "slide_window"
    if packed_max is None:
        packed_max = FINISH_AT_ONCE if path is not None and path.kind == "pivot_split" and getattr(backend, "compare_many", None) else PACKED_MAX
    # read by all that follows, so worked out once; texts stay out where neither the backend nor a join needs them
    base = scratch.write("items", base if dedup_keys or facts is not None else slim(base, backend))
    stats = base.groupBy("task_id").agg(F.count("*").alias("n"), F.count_if(F.col("item_id").isNull()).alias("lost")).agg(F.max("n").alias("n"), F.sum("lost").alias("lost")).first()
    if stats["lost"]:
        raise ValueError(f"{stats['lost']} rows have no {id_col}")
    large = (stats["n"] or 0) > packed_max

    def numbered(d: DataFrame, name: str) -> DataFrame:
        """Places from 1 by id within each partition."""
        if not large:
            return d.withColumn(name, F.row_number().over(W.partitionBy("task_id").orderBy("item_id")).cast("bigint"))
        return placed_by(d, ["item_id"], scratch, name)

    def positioned(d: DataFrame) -> DataFrame:
        return numbered(d, "pos").withColumn("pos", (F.col("pos") - 1).cast("int"))

    bad = F.col("key").isNull() | (F.col("key") == "")
    if spec.nulls == "error" and base.where(bad).limit(1).count():
        raise ValueError("null or empty keys")
    items = base.where(~bad)
    if dedup_keys:
        items = items.groupBy("task_id", "key").agg(F.min("item_id").alias("item_id"), F.max("lat").alias("lat"))
    if facts is not None:
        items = with_facts(items, facts, "first" if "origin" in facts.columns else "max")
    items = scratch.write("shown", positioned(items))
    # nulls that come first take places from the limit, so the order is cut once all have their rank
    if path is None and budget_nano is not None:
        tasks = items.select("task_id").distinct().select("task_id", F.lit(spec.kind).alias("kind"), F.lit(limit).cast("bigint").alias("k"))
        ranked = optimize(items, tasks, budget_nano, backend, policy=policy, sample=sample, packed_max=packed_max, max_in_flight=max_in_flight, scratch=scratch).ranking
    elif large and not chain:
        ranked = run_in_waves(items, path or EXT_MERGE, backend, limit, scratch)[0]
    else:
        run = items.withColumn("k", F.lit(limit).cast("bigint"))
        ranked = rankings_of(run_paths(run, [path or EXT_MERGE], backend, scratch=scratch, max_in_flight=max_in_flight, by_wave=False))
    ranked = ranked.select("task_id", "item_id", "rnk")
    if dedup_keys:
        keyed = ranked.join(items.select("task_id", "item_id", "key"), ["task_id", "item_id"]).select("task_id", "key", F.col("rnk").alias("r"))
        same = base.where(~bad).join(keyed, ["task_id", "key"]).select("task_id", "item_id", "r")
        if large:
            ranked = placed_by(same, ["r", "item_id"], scratch, "rnk").drop("r")
        else:
            ranked = same.select("task_id", "item_id", F.row_number().over(W.partitionBy("task_id").orderBy("r", "item_id")).cast("bigint").alias("rnk"))
    empties = numbered(base.where(bad).select("task_id", "item_id"), "e")
    counts = base.groupBy("task_id").agg(F.count_if(bad).alias("nulls"), F.count_if(~bad).alias("full"))
    if spec.nulls == "first":
        ranked = ranked.join(counts, "task_id").select("task_id", "item_id", (F.col("rnk") + F.col("nulls")).alias("rnk"))
        empties = empties.select("task_id", "item_id", F.col("e").alias("rnk"))
    else:
        empties = empties.join(counts, "task_id").select("task_id", "item_id", (F.col("e") + F.col("full")).alias("rnk"))
    ranked = ranked.unionByName(empties)
    if limit is not None:
        ranked = ranked.where(F.col("rnk") <= limit)
    ranked = ranked.select(F.col("item_id").alias("_item"), "rnk")
    return df.drop("rnk").join(ranked, F.col(id_col) == F.col("_item")).drop("_item")
