"""Mixing sources to target weights by hash-threshold histograms.

Every document has a position: 60 bits of the MD5 of its id. A source whose target
is ``q`` times its size takes each document floor(q) times and, of those below a
threshold position, one copy more. The threshold comes from nested histograms:
sizes are summed by source and the position's leading bits, the bucket in which
the running sum meets the need is found, and only that bucket is split by its next
bits. Documents are then filtered by comparing positions; nothing sorts them.

Raising a source's target moves its threshold up, so smaller mixes are nested in larger ones.

At scale: one pass over the texts writes (source, position, size); all later passes
read that narrow table. Histograms are partial sums (a hot source adds bins, not
rows). Per-source figures are written and reread, so that the planner knows their size:
it broadcasts them below its threshold and otherwise joins by source, where
adaptive execution splits a hot source.

Defined cases: null text has size 0 and is taken floor(q) times like any other; a null
source is a source of its own, last in order; documents that share an id share a
position and are taken alike; an empty table gives an empty mix; extra columns are
carried (``mix``) or left unread (``mix_counts``).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semrank.exec.scratch import Scratch
from semrank.llm.text import fresh, n_words

#: A document is taken at most so many times.
MOST = 3
BITS, STEP = 60, 12
HEX = BITS // 4


def position(doc_id: str | Column) -> Column:
    """60 bits of the MD5 of the id; a null id counts as empty."""
    text = F.coalesce(F.col(doc_id).cast("string") if isinstance(doc_id, str) else doc_id.cast("string"), F.lit(""))
    return F.conv(F.substring(F.md5(text), 1, HEX), 16, 10).cast("bigint")


def targets(sizes: DataFrame) -> DataFrame:
    """(source, source_size) -> weights and targets, one row per source.

    Capped proportional sharing in closed form: with sources by rising cap per weight, those
    before some point are at their caps and the rest share what is left by weight. ``level``
    is the share of one unit of weight if exactly the sources before this one are capped; the
    right point is the first source whose cap is not below its level's share.
    """
    ordered = W.orderBy(F.col("source").asc_nulls_last())
    s = sizes.select("source", "source_size", ((F.row_number().over(ordered) - 1) % 3 + 1).cast("bigint").alias("weight"))
    up = W.orderBy(F.col("source_size") * 6 / F.col("weight"), F.col("source").asc_nulls_last())
    before, everything = up.rowsBetween(W.unboundedPreceding, -1), W.partitionBy()
    s = s.select(
        "*",
        (MOST * F.col("source_size")).alias("cap"),
        (F.sum("source_size").over(everything) - MOST * F.coalesce(F.sum("source_size").over(before), F.lit(0))).alias("left_size"),
        (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))).alias("left_weight"),
    )
    s = s.withColumn("level", F.col("left_size").cast("double") / F.col("left_weight").cast("double"))
    fits = F.col("cap").cast("double") >= F.col("level") * F.col("weight")
    s = s.withColumn("final", F.min(F.when(fits, F.struct((F.col("source_size") * 6 / F.col("weight")).alias("r"), F.col("source").isNull().alias("z"), F.col("source"), F.col("level")))).over(everything)["level"])
    target = F.least(F.col("cap").cast("double"), F.col("final") * F.col("weight"))
    return s.select("source", "source_size", "weight", target.alias("target"))


def thresholds(sized: DataFrame, scratch: Scratch) -> DataFrame:
    """source -> source_size, target, base (copies for all) and cut: one copy more for positions <= cut."""
    per_source = scratch.write("sizes", sized.groupBy("source").agg(F.sum("size").alias("source_size")))
    t = targets(per_source)
    t = t.withColumn("base", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("bigint"))
    t = t.withColumn("need", F.col("target") - F.col("base") * F.col("source_size"))
    # below: size at positions under the bucket; prefix: the bucket's leading bits
    state = scratch.write("state0", t.select("*", F.lit(0).cast("bigint").alias("prefix"), F.lit(0).cast("bigint").alias("below")))
    for level in range(1, BITS // STEP + 1):
        shift = BITS - STEP * level
        bin_of = F.shiftright("pos", shift)
        inside = sized if level == 1 else sized.join(
            state.select(F.col("source").alias("_s"), F.col("prefix").alias("_p")), F.col("source").eqNullSafe(F.col("_s")) & (F.shiftright("pos", shift + STEP) == F.col("_p"))
        )
        bins = inside.groupBy("source", bin_of.alias("bin")).agg(F.sum("size").alias("in_bin"))
        run = W.partitionBy("source").orderBy("bin")
        bins = bins.select("source", "bin", "in_bin", (F.sum("in_bin").over(run) - F.col("in_bin")).alias("run"))
        b = bins.alias("b").join(state.alias("s"), F.col("b.source").eqNullSafe(F.col("s.source")))
        start = F.col("s.below") + F.col("b.run")
        # the first bucket whose end reaches the need; if rounding leaves none, the last one
        reached = (start + F.col("b.in_bin")).cast("double") >= F.col("s.need")
        found = b.groupBy(F.col("s.source").alias("source")).agg(
            F.min(F.when(reached, F.struct(F.col("b.bin").alias("bin"), start.alias("start"), F.col("b.in_bin").alias("in_bin")))).alias("first"),
            F.max(F.struct(F.col("b.bin").alias("bin"), start.alias("start"), F.col("b.in_bin").alias("in_bin"))).alias("last"),
            *[F.first(f"s.{c}").alias(c) for c in ("source_size", "target", "base", "need")],
        )
        hit = F.coalesce("first", "last")
        found = found.select("source", "source_size", "target", "base", "need", hit["bin"].alias("prefix"), hit["start"].alias("below"), hit["in_bin"].alias("in_bin"))
        if shift == 0:
            # the document at the boundary comes in if that ends nearer to the need
            near = (F.col("below") + F.col("in_bin")).cast("double") - F.col("need") <= F.col("need") - F.col("below").cast("double")
            found = found.withColumn("cut", F.when(near, F.col("prefix")).otherwise(F.col("prefix") - 1))
        state = scratch.write(f"state{level}", found)
        scratch.drop(f"state{level - 1}")
    scratch.drop("sizes")
    return state.select("source", "source_size", "target", "base", "cut")


def mix_counts(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """doc_id, size, source_size, target, copies and taken of every document."""
    scratch = Scratch(docs.sparkSession, "mix")
    sized = docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), n_words(text).alias("size"), position(doc_id).alias("pos"))
    sized = scratch.write("sized", sized)
    cuts = thresholds(sized, scratch).withColumnRenamed("source", "_s")
    out = sized.join(cuts, F.col("source").eqNullSafe(F.col("_s")))
    copies = F.least(F.col("base") + (F.col("pos") <= F.col("cut")).cast("bigint"), F.lit(MOST))
    return out.select("doc_id", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))


def mix(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """The mix itself: each row as often as it is taken, with the columns of ``docs``."""
    scratch = Scratch(docs.sparkSession, "mix")
    sized = scratch.write("sized", docs.select(F.col(source).alias("source"), n_words(text).alias("size"), position(doc_id).alias("pos")))
    s, p, b, c, n = fresh(docs, "_source", "_pos", "_base", "_cut", "_copy")
    cuts = thresholds(sized, scratch).select(F.col("source").alias(s), F.col("base").alias(b), F.col("cut").alias(c))
    scratch.drop("sized")
    out = docs.withColumn(p, position(doc_id)).join(cuts, F.col(source).eqNullSafe(F.col(s)))
    copies = F.least(F.col(b) + (F.col(p) <= F.col(c)).cast("bigint"), F.lit(MOST)).cast("int")
    # explode drops rows that are taken no time
    return out.withColumn(n, F.explode(F.array_repeat(F.lit(1), copies))).select(*docs.columns)
