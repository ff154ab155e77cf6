"""Document fingerprints: a Merkle tree over phrases, paragraphs and sections.

A paragraph is a line; its leaves are phrases, cut at a space that follows ASCII punctuation.
A paragraph's node is the hash of its leaves. A section ends after a paragraph whose node
starts with one of four hex digits, so sections too are cut by content and an edit moves
no boundary but its own. The root is the hash of the section nodes.

``fingerprint`` is the root, the section nodes and the leaves as one string: equal roots mean equal
texts; where roots differ, ``differing_branches`` walks sections and then paragraphs to the places that do. ``likeness``
is the share of leaves that two trees have in common (Dice), each as often as it occurs, 1 for equal roots: what a walk that
takes common sections first, then common paragraphs of the rest, then common leaves would count, as branches taken
out of both sides take as many leaves from each.

At scale: a document's tree is a projection. The next document is found without one global
sort: ids are cut into ranges by bounded quantiles, rows move once to their range, and the first
row of each range is sent to the range before it (one row per range).

Defined cases: null is empty; an empty text is one empty leaf; repeated rows follow one another like
other rows of the same id; null ids come first; the last document is followed by the first
(a single one by itself); an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semrank.llm.text import whole

#: A phrase ends at a space behind ASCII punctuation.
PHRASE_END = r"""(?<=[!-/:-@\[-`{-~]) """
#: A paragraph whose node starts with one of these closes a section.
CLOSING = "0123"
#: Ranges of ids: four for each shuffle partition, within these bounds.
RANGES = (64, 2048)
FIRST_ID = -(2**63)


def leaf(x: Column) -> Column:
    """48 bits are enough to tell branches apart; nodes, sections and root keep all 128."""
    return F.substring(F.md5(x), 1, 12)


def tree(d: DataFrame, text: str, name: str) -> DataFrame:
    """Adds {name}_leaves (per paragraph), {name}_nodes and {name}_sections."""
    leaves, nodes, ends = f"{name}_leaves", f"{name}_nodes", f"{name}_ends"
    d = d.withColumn(leaves, F.transform(F.split(text, "\n"), lambda p: F.transform(F.split(p, PHRASE_END), leaf)))
    d = d.withColumn(nodes, F.transform(leaves, lambda x: F.md5(F.array_join(x, ""))))
    close = F.transform(nodes, lambda x, i: F.when((i + 1 == F.size(nodes)) | F.substring(x, 1, 1).isin(*CLOSING), i))
    d = d.withColumn(ends, F.filter(close, lambda i: i.isNotNull()))
    start = lambda k: F.coalesce(F.get(ends, k - 1) + 1, F.lit(0))
    return d.withColumn(f"{name}_sections", F.transform(ends, lambda e, k: F.md5(F.array_join(F.slice(nodes, start(k) + 1, e - start(k) + 1), "")))).drop(ends)


def fingerprint(name: str) -> Column:
    """root : section nodes, 16 digits each : leaves by paragraph."""
    root = F.md5(F.array_join(f"{name}_sections", ""))
    return F.concat_ws(":", root, F.array_join(F.transform(f"{name}_sections", lambda x: F.substring(x, 1, 16)), "."), F.array_join(F.transform(f"{name}_leaves", lambda x: F.array_join(x, ".")), "/"))


def root_of(fp: str | Column) -> Column:
    return F.substring(fp, 1, 32)


def counted(d: DataFrame, fp: str, name: str) -> DataFrame:
    """Adds {name}, the leaves that a fingerprint lists in order of hash, and {name}_each, where the repeats of a leaf are told apart by a number."""
    d = d.withColumn(name, F.array_sort(F.split(F.substring_index(fp, ":", -1), "[./]")))
    new = F.transform(name, lambda x, i: F.when((i == 0) | (F.get(name, i - 1) != x), i))
    d = d.withColumn(f"{name}_at", F.filter(new, lambda i: i.isNotNull()))
    until = lambda k: F.coalesce(F.get(f"{name}_at", k + 1), F.size(name))
    each = F.transform(f"{name}_at", lambda i, k: F.transform(F.sequence(F.lit(1), until(k) - i), lambda c: F.concat(F.get(name, i), F.lit("."), c.cast("string"))))
    return d.withColumn(f"{name}_each", F.flatten(each)).drop(f"{name}_at")


def likeness(a: str, b: str) -> Column:
    """Of two fingerprints whose leaves were counted under these names."""
    return 2.0 * F.size(F.array_intersect(f"{a}_each", f"{b}_each")) / (F.size(a) + F.size(b))


def differing(a: list[str], b: list[str]) -> tuple[range, range]:
    """What is left of two lists of nodes without the items in common at their start and, then, at their end."""
    least = min(len(a), len(b))
    i = next((k for k in range(least) if a[k] != b[k]), least)
    j = next((k for k in range(least - i) if a[-1 - k] != b[-1 - k]), least - i)
    return range(i, len(a) - j), range(i, len(b) - j)


def walk(a: str, b: str) -> tuple[list[int], list[int]]:
    """The paragraphs that differ, of two fingerprints: by roots, then sections, then paragraphs of the sections left."""
    (root, tops, leaves), (other_root, other_tops, other_leaves) = a.split(":"), b.split(":")
    if root == other_root:
        return [], []
    sides = []
    for sections, paragraphs in zip(differing(tops.split("."), other_tops.split(".")), (leaves.split("/"), other_leaves.split("/")), strict=True):
        nodes = [hashlib.md5(p.replace(".", "").encode()).hexdigest() for p in paragraphs]
        ends = [0, *(i + 1 for i, x in enumerate(nodes) if i + 1 == len(nodes) or x[0] in CLOSING)]
        sides.append((ends[sections.start], nodes[ends[sections.start] : ends[sections.stop]]))
    (at, x), (other_at, y) = sides
    p, q = differing(x, y)
    mine, others = {x[i] for i in p}, {y[i] for i in q}
    moved = mine == others
    return [at + i for i in p if moved or x[i] not in others], [other_at + i for i in q if moved or y[i] not in mine]


@F.pandas_udf(T.StructType([T.StructField(c, T.ArrayType(T.IntegerType())) for c in ("a", "b")]))
def walked(a: pd.Series, b: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([walk(x, y) for x, y in zip(a, b, strict=True)], columns=["a", "b"])


def differing_branches(a: str | Column, b: str | Column) -> Column:
    """Of two fingerprints: a and b, the 0-based paragraphs of each text that differ; empty lists for equal roots.

    Of the paragraphs left by the walk those are given that the other side lacks, or all where neither side lacks any
    (a move or a repeat), so that unequal texts have a place at least.
    """
    return walked(a, b)


def with_next(d: DataFrame, order: str, tie: str, prepare, payload: tuple[str, ...]) -> DataFrame:
    """``prepare(d)`` and _next: the ``payload`` columns of the row that follows by ``order`` then ``tie``; the first follows the last.

    Ids are cut into ranges by quantiles (a bounded list), rows move once to their range, and each range is lent the
    first row of the next one.
    """
    spark = d.sparkSession
    n = min(max(RANGES[0], 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))), RANGES[1])
    # the bounds: at most n longs, whatever the input; exact balance does not matter
    found = d.select(F.percentile_approx(order, [i / n for i in range(1, n)], 10 * n).alias("b")).first()["b"]
    bounds = sorted(set(found or []))
    cut = F.array(*[F.lit(x) for x in bounds]).cast("array<bigint>")
    at = F.size(F.filter(cut, lambda x: x <= F.col(order))) if bounds else F.lit(0)
    d = d.withColumn("_range", at.cast("int"))
    heads = d.groupBy("_range").agg(F.min(F.struct(order, tie)).alias("_head")).collect()  # one row per range
    heads = sorted((h["_range"], h["_head"][order], h["_head"][tie]) for h in heads)
    # each range is shown the head of the range after it, the last one that of the first
    lent = [(h[1], h[2], heads[i - 1][0]) for i, h in enumerate(heads)]
    guests = spark.createDataFrame(lent, "_o bigint, _t bigint, _host int")
    shown = d.join(F.broadcast(guests), (F.col(order) == F.col("_o")) & (F.col(tie) == F.col("_t")))
    shown = shown.dropDuplicates(["_host", order, tie])  # rows alike are one guest
    shown = shown.withColumn("_range", F.col("_host")).withColumn("_guest", F.lit(True)).drop("_o", "_t", "_host")
    # texts alone are moved; trees are built where they arrive
    rows = prepare(d.withColumn("_guest", F.lit(False)).unionByName(shown).repartition("_range"))
    w = W.partitionBy("_range").orderBy("_guest", order, tie)
    return rows.withColumn("_next", F.lead(F.struct(*payload)).over(w)).where(~F.col("_guest")).drop("_range", "_guest")


def fingerprints(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: doc_id, n_chars, the edited text's SHA-256, both fingerprints and likenesses."""
    d = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), whole(text).alias("_text"))
    d = d.select("*", F.coalesce("doc_id", F.lit(FIRST_ID)).alias("_order"), F.xxhash64("_text").alias("_tie"))
    own = lambda x: tree(x, "_text", "own").withColumn("fingerprint", fingerprint("own")).drop("own_leaves", "own_nodes", "own_sections")
    d = with_next(d, "_order", "_tie", own, ("_text", "fingerprint"))
    n = F.length("_text")
    k = F.floor(n / 4).cast("int")
    edited = F.concat(F.substring(F.col("_text"), F.lit(1), n - k), F.substring(F.col("_next._text"), F.lit(1), k))
    d = d.select("doc_id", n.cast("bigint").alias("n_chars"), edited.alias("_edited"), "fingerprint", F.col("_next.fingerprint").alias("_next"))
    d = tree(d, "_edited", "edit")
    d = d.select("doc_id", "n_chars", F.sha2("_edited", 256).alias("edited_sha256"), "fingerprint", fingerprint("edit").alias("edited_fingerprint"), "_next")
    for fp, name in (("fingerprint", "_own"), ("edited_fingerprint", "_edit"), ("_next", "_after")):
        d = counted(d, fp, name)
    near = lambda fp, leaves: F.when(root_of("fingerprint") == root_of(fp), F.lit(1.0)).otherwise(likeness("_own", leaves))
    return d.select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", near("edited_fingerprint", "_edit").alias("near_edited"), near("_next", "_after").alias("near_next"))
