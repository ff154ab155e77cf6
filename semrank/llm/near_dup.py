"""Near-duplicate groups by a chosen-path set similarity join.

A document is the set of its five-word shingles. In each of several independent trees it
walks down a path of its own minwise shingles: every step takes the shingle of least hash under a
hash function that this step of this tree has for itself. Documents that have walked the same path
share a node. With a Jaccard similarity of J two documents take the same step with probability J,
whatever their sizes and whatever came before, so they share the node at depth d with probability J^d, and
the number of trees is set for a missed pair of similarity 0.75 to have a probability under ``miss``
at each depth. Sets of fewer than three shingles can't be linked with an unequal one and walk no tree.

The join goes deeper only where it has to:

1. Documents with equal sets are one class, and each class sends one representative.
2. At the first depth each node compares its least document with the others; components are found from the
   links that hold, which settles most groups of copies.
3. At every depth of ``DEPTHS``, nodes whose documents are in one component are done. Small open nodes compare
   the pairs between components exhaustively, middling ones all their documents within one task. Documents of nodes
   that are larger still (a line or passage that many share) walk on to the next depth, where unlike ones part.
4. Nodes that are large and open at the last depth compare all their documents too, in cells of bounded size.

So the size of a node decides how its pairs are found, never whether.

Every link is confirmed on the full sets, by 64-bit hashes of shingles.

At scale: one pass over the texts writes a sketch per document; nodes are counted with partial
sums; a group of n copies costs n comparisons, not n^2; texts move only for candidate pairs. A cell is bounded in
documents and in shingles. Nodes and groups of copies that hold more than one in ``HOT`` of all rows, fewer than
``HOT`` by arithmetic, are broadcast as narrow rows, so no task gets all rows of one; empty texts are in no join.
Components are found with label propagation and pointer jumping on written tables, narrow equi-joins that
adaptive execution can split. Nothing is collected but row counts.

Defined cases: null and empty texts have no shingles and link with nothing; fewer than five words are one
shingle; rows with a null id are never linked (component_id null, kept true); rows alike in
id and text are in one group, and ``drop_near_duplicates`` keeps one of them; rows that share an id but not a text are one node; an
empty table gives an empty table; extra columns are carried or left unread.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semrank.exec.scratch import Scratch
from semrank.llm.text import fresh, row_key

WIDTH = 5
#: A link: MATCH[0] * intersection >= MATCH[1] * union.
MATCH = (100, 75)
DEPTHS = (1, 4, 8)
MISS = 1e-6
#: A node of up to so many documents is small.
SMALL = 24
#: A node of up to so many documents is compared whole in one task; larger ones at the last depth in cells of that size.
CELL = 1536
#: A node of more shingles than this counts as large too, and is cut into cells of about so many.
MASS = 1 << 22
#: What holds more than one in so many rows is hot: fewer than so many can.
HOT = 2000
#: Shingles per matrix product in a cell; elements per block of minwise hashes.
SLICE, BLOCK = 4096, 1 << 18
CACHE, LONGEST = 100_000, 256
#: Texts that are Python objects at once.
AT_ONCE = 512
#: Odd multipliers of the shingle hash and of its last mixing steps.
ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD], dtype=np.uint64)
MIX = np.uint64(0xC4CEB9FE1A85EC53)


def trees_for(depth: int, miss: float = MISS) -> int:
    """Trees so that a pair at the similarity bound shares no node with probability ``miss`` at most."""
    return math.ceil(math.log(miss) / math.log(1 - (MATCH[1] / MATCH[0]) ** depth))


class WordHashes(dict):
    """Word -> 64 bits, kept for the words seen of late."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > CACHE:
            self.clear()
        out = xxhash.xxh64_intdigest(word)
        if len(word) <= LONGEST:
            self[word] = out
        return out


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * MIX
    return x ^ (x >> np.uint64(29))


def shingles(text: bytes | None, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles. bytes.lower and bytes.split know ASCII alone."""
    words = (text or b"").lower().split()
    n = len(words)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, n)
    with np.errstate(over="ignore"):
        if n >= WIDTH:
            s = h[: n - WIDTH + 1] * ODD[0]
            for k in range(1, WIDTH):
                s = s + h[k : n - WIDTH + 1 + k] * ODD[k]
        elif n:
            s = np.array([(h * ODD[:n]).sum(dtype=np.uint64) + np.uint64(n)])
        else:
            return np.empty(0, np.uint64)
        return np.unique(mixed(s))


#: Smaller sets are like no set but their equals.
LEAST = next(n for n in range(1, 1000) if MATCH[0] * n >= MATCH[1] * (n + 1))


def minwise(s: np.ndarray, functions: int) -> np.ndarray:
    """The shingle of least hash under each of so many hash functions."""
    k = np.arange(functions, dtype=np.uint64)
    out = np.empty(functions, np.uint64)
    with np.errstate(over="ignore"):
        m = ODD[np.arange(functions) % WIDTH] + k * np.uint64(2 * 0x2545F4914F6CDD1D)
        size = max(1, BLOCK // len(s))
        for at in range(0, functions, size):
            h = m[at : at + size, None] * s[None, :]
            h ^= h >> np.uint64(32)
            h *= MIX
            out[at : at + size] = s[h.argmin(axis=1)]
    return out


def paths(s: np.ndarray, trees: int, depth: int) -> np.ndarray:
    """One hash per tree: of a path of ``depth`` minwise shingles, each under a hash function of its own."""
    steps = minwise(s, trees * depth).reshape(trees, depth)
    out = np.arange(trees, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(depth):
            out = (out ^ steps[:, k]) * ODD[0]
            out ^= out >> np.uint64(32)
    return out


def jaccard_holds(a: np.ndarray, b: np.ndarray) -> bool:
    if not len(a) or not len(b):
        return False
    union = len(np.union1d(a, b))
    return MATCH[0] * (len(a) + len(b) - union) >= MATCH[1] * union


def sliced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, AT_ONCE):
            yield batch.slice(at, AT_ONCE)


def hand_back(hashes: WordHashes) -> None:
    """Workers outlive tasks: what this one no longer needs goes back to the system."""
    hashes.clear()
    pa.default_memory_pool().release_unused()


def sketches(trees: int, depth: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in sliced(batches):
            ns, fa, fb, steps = [], [], [], []
            for text in batch.column("text").cast(pa.binary()).to_pylist():
                s = shingles(text, hashes)
                ns.append(len(s))
                with np.errstate(over="ignore"):
                    fa.append(s.sum(dtype=np.uint64).astype(np.int64) if len(s) else 0)
                    fb.append((mixed(s * ODD[1])).sum(dtype=np.uint64).astype(np.int64) if len(s) else 0)
                steps.append(paths(s, trees, depth).astype(np.int64) if len(s) >= LEAST else [])
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), batch.column("row"), pa.array(ns, pa.int64()), pa.array(fa, pa.int64()), pa.array(fb, pa.int64()), pa.array(steps, pa.list_(pa.int64()))],
                ["id", "row", "n", "fa", "fb", "steps"],
            )
        hand_back(hashes)

    return run


def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hashes, last, own = WordHashes(), None, None
    for batch in batches:
        a, b = batch.column("a").to_pylist(), batch.column("b").to_pylist()
        at, bt = batch.column("at").cast(pa.binary()), batch.column("bt").cast(pa.binary())
        hold = []
        for i in range(len(a)):
            text = at[i].as_py()
            if own is None or text != last:
                last, own = text, shingles(text, hashes)
            hold.append(jaccard_holds(own, shingles(bt[i].as_py(), hashes)))
        keep = [i for i, x in enumerate(hold) if x]
        yield pa.RecordBatch.from_arrays([pa.array([a[i] for i in keep], pa.int64()), pa.array([b[i] for i in keep], pa.int64())], ["a", "b"])
    hand_back(hashes)


def components(links: DataFrame, scratch: Scratch, label: str) -> DataFrame:
    """(id, comp) of every document with a link: the least id it can reach."""
    both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = scratch.write(f"{label}-both", both)
    now = scratch.write(f"{label}-0", both.groupBy(F.col("a").alias("id")).agg(F.least(F.first("a"), F.min("b")).alias("comp")))
    step = 0
    while True:
        near = both.join(now.select(F.col("id").alias("b"), "comp"), "b").groupBy(F.col("a").alias("id")).agg(F.min("comp").alias("near"))
        new = now.join(near, "id").select("id", F.least("comp", "near").alias("comp"), F.col("comp").alias("was"))
        up = now.select(F.col("id").alias("comp"), F.col("comp").alias("up"))
        new = new.join(up, "comp", "left").select("id", F.least("comp", F.coalesce("up", "comp")).alias("comp"), "was")
        step += 1
        new = scratch.write(f"{label}-{step}", new)
        changed = new.where("comp <> was").limit(1).count()
        scratch.drop(f"{label}-{step - 1}")
        now = new.select("id", "comp")
        if not changed:
            scratch.drop(f"{label}-both")
            return now


def cell_links(f: pd.DataFrame) -> pd.DataFrame:
    """Exact links between components among the documents of one cell, as a spanning forest: intersections of all
    pairs at once, as products of 0/1 matrices over so many shingles at a time."""
    hashes = WordHashes()
    f = f.drop_duplicates(["id", "row"]).sort_values(["id", "row"])
    sets = [shingles(t.encode("utf-8", "surrogatepass"), hashes) for t in f["text"]]
    sizes = np.array([len(x) for x in sets])
    every, place = np.unique(np.concatenate(sets), return_inverse=True)
    owner = np.repeat(np.arange(len(sets)), sizes)
    common = np.zeros((len(sets), len(sets)), np.float32)
    # a shingle of one document is in no intersection
    shared = np.bincount(place, minlength=len(every)) > 1
    number = np.cumsum(shared) - 1
    owner, place = owner[shared[place]], number[place[shared[place]]]
    order = np.argsort(place, kind="stable")
    place, owner, n = place[order], owner[order], int(shared.sum())
    for start in range(0, n, SLICE):
        lo, hi = np.searchsorted(place, [start, start + SLICE])
        has = np.zeros((len(sets), min(SLICE, n - start)), np.float32)
        has[owner[lo:hi], place[lo:hi] - start] = 1
        common += has @ has.T
    common = common.astype(np.float64)  # the products below stay exact
    holds = MATCH[0] * common >= MATCH[1] * (sizes[:, None] + sizes[None, :] - common)
    ids, comp = f["id"].to_numpy(), f["comp"].to_numpy().copy()
    out = []
    for i, j in np.argwhere(np.triu(holds, 1)):
        if comp[i] != comp[j]:
            out.append((ids[i], ids[j]) if ids[i] < ids[j] else (ids[j], ids[i]))
            comp[comp == comp[j]] = comp[i]
    return pd.DataFrame(out, columns=["a", "b"], dtype="int64")


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", miss: float = MISS, small: int = SMALL, cell: int = CELL) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row."""
    scratch = Scratch(docs.sparkSession, "near")
    rows = docs.select(F.col(doc_id).cast("bigint").alias("id"), row_key(doc_id, text).alias("row"), F.col(text).alias("text"))
    schema = "id bigint, row bigint, n bigint, fa bigint, fb bigint, steps array<bigint>"
    all_rows = scratch.write("sketch", rows.mapInArrow(sketches(trees_for(DEPTHS[0], miss), DEPTHS[0]), schema))
    classes = all_rows.where("n > 0 and id is not null").groupBy("fa", "fb", "n").agg(F.min(F.struct("id", "row")).alias("rep"), F.count("*").alias("size"))
    classes = scratch.write("classes", classes.select("fa", "fb", "n", "size", F.col("rep.id").alias("rep"), F.col("rep.row").alias("rep_row")))
    reps = classes.where(F.col("n") >= LEAST).select(F.col("rep").alias("id"), F.col("rep_row").alias("row"), "n")
    at = scratch.write("walkers", all_rows.select("id", "row", "steps").join(reps, ["id", "row"]).dropDuplicates(["id", "row"]))
    comps = tried = texts = None
    fit = lambda x, y: F.least(x, y) * MATCH[0] >= F.greatest(x, y) * MATCH[1]

    def labelled(nodes: DataFrame) -> DataFrame:
        if comps is None:
            return nodes.withColumn("comp", F.col("id"))
        return nodes.join(comps, "id", "left").withColumn("comp", F.coalesce("comp", "id"))

    def add_links(new: DataFrame, name: str) -> None:
        """Renew the components: later links join components, of which there are few, not documents."""
        nonlocal comps
        if comps is None:
            comps = components(new, scratch, f"{name}-comps")
            return
        found = labelled(labelled(new.withColumn("id", F.col("a"))).withColumnRenamed("comp", "x").withColumn("id", F.col("b")))
        edges = scratch.write(f"{name}-edges", found.where("x <> comp").select(F.least("x", "comp").alias("a"), F.greatest("x", "comp").alias("b")).distinct())
        if not edges.limit(1).count():
            return
        merged = components(edges, scratch, f"{name}-comps").select(F.col("id").alias("comp"), F.col("comp").alias("new"))
        ends = edges.select(F.explode(F.array("a", "b")).alias("id")).distinct().join(comps, "id", "left_anti").select("id", F.col("id").alias("comp"))
        comps = scratch.write(f"{name}-labels", comps.unionByName(ends).join(merged, "comp", "left").select("id", F.coalesce("new", "comp").alias("comp")))

    def keep_texts(of: DataFrame, name: str) -> None:
        """From now on only the texts of these documents can be asked for."""
        nonlocal texts
        source = rows if texts is None else texts
        texts = scratch.write(name, source.join(of.select("id", "row").distinct(), ["id", "row"]).dropDuplicates(["id", "row"]))

    def linked(pairs: DataFrame, name: str) -> DataFrame:
        """Those of the pairs (a, ar, b, br) that are new and that full sets confirm."""
        nonlocal tried
        pairs = pairs.distinct()
        if tried is not None:
            pairs = pairs.join(tried, ["a", "ar", "b", "br"], "left_anti")
        pairs = scratch.write(f"{name}-pairs", pairs)
        tried = pairs if tried is None else tried.unionByName(pairs)
        with_b = pairs.join(texts.select(F.col("id").alias("b"), F.col("row").alias("br"), F.col("text").alias("bt")), ["b", "br"])
        with_both = with_b.join(texts.select(F.col("id").alias("a"), F.col("row").alias("ar"), F.col("text").alias("at")), ["a", "ar"])
        return scratch.write(f"{name}-links", with_both.select("a", "b", "at", "bt").mapInArrow(confirm, "a bigint, b bigint"))

    # the halves of a cell of two blocks hold half of what a cell may
    halves = F.ceil(F.greatest(F.col("size") / (cell / 2), F.col("mass") / (MASS / 2))).cast("int")
    large = (F.col("size") > cell) | (F.col("mass") > MASS)

    def compared(nodes: DataFrame, name: str) -> DataFrame:
        """Compare all documents of each node, in cells of bounded size that no task has two of at once."""
        one = F.when(large, F.greatest(halves, F.lit(2))).otherwise(F.lit(1))
        d = nodes.select("tree", "step", "id", "row", "comp", one.alias("blocks"), F.pmod(F.xxhash64("id"), one).cast("int").alias("own"))
        # each block meets every other once: the cell (i, j), i <= j, holds blocks i and j
        d = d.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        d = d.where("blocks = 1 or own <> other").select("tree", "step", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "id", "row", "comp")
        d = d.join(texts, ["id", "row"])
        return scratch.write(f"{name}-links", d.groupBy("tree", "step", "i", "j").applyInPandas(cell_links, "a bigint, b bigint"))

    def node_pairs(nodes: DataFrame) -> DataFrame:
        """All pairs between components, for small nodes."""
        nodes = nodes.select("tree", "step", "id", "row", "n", "comp")
        b = nodes.select("tree", "step", F.col("id").alias("b"), F.col("row").alias("br"), F.col("n").alias("bn"), F.col("comp").alias("bc"))
        p = nodes.join(b, ["tree", "step"]).where((F.col("id") < F.col("b")) & (F.col("comp") != F.col("bc")) & fit(F.col("n"), F.col("bn")))
        return p.select(F.col("id").alias("a"), F.col("row").alias("ar"), "b", "br")

    def nodes_of(spread: DataFrame, total: int, name: str) -> DataFrame:
        """Documents of nodes that hold more than one component, with the node's size, shingles and least document.

        Hot nodes are broadcast, so that their documents stay where they are.
        """
        key = ["tree", "step"]
        stats = spread.groupBy(*key).agg(F.count("*").alias("size"), F.sum("n").alias("mass"), F.min(F.struct("id", "row", "n", "comp")).alias("lead"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
        stats = scratch.write(f"{name}-stats", stats.where("lo < hi").drop("lo", "hi"))
        hot = F.col("size") * HOT > total
        few, rest = F.broadcast(stats.where(hot)), stats.where(~hot)
        cool = spread.join(F.broadcast(stats.where(hot).select(*key)), key, "left_anti").join(rest, key)
        return scratch.write(name, spread.join(few, key).unionByName(cool))

    for k, depth in enumerate(DEPTHS):
        last = k == len(DEPTHS) - 1
        if k:
            at = scratch.write(f"walkers{k}", texts.mapInArrow(sketches(trees_for(depth, miss), depth), schema).select("id", "row", "n", "steps"))
        spread = labelled(at.select("id", "row", "n", "steps")).select("id", "row", "n", "comp", F.posexplode("steps").alias("tree", "step"))
        now = nodes_of(spread, at.count() * trees_for(depth, miss), f"now{k}")
        keep_texts(now, f"texts{k}")
        if not k:
            # most copies fall to this, so that few pairs are left for the nodes
            star = now.where((F.col("id") != F.col("lead.id")) & (F.col("comp") != F.col("lead.comp")) & fit(F.col("n"), F.col("lead.n")))
            add_links(linked(star.select(F.col("lead.id").alias("a"), F.col("lead.row").alias("ar"), F.col("id").alias("b"), F.col("row").alias("br")), "star"), "star")
            now = nodes_of(labelled(now.drop("comp", "size", "mass", "lead")), now.count(), "open0")
            keep_texts(now, "open-texts0")
        found = linked(node_pairs(now.where((F.col("size") <= small) & ~large)), f"pairs{k}")
        add_links(found.unionByName(compared(now.where(((F.col("size") > small) | large) & (F.lit(last) | ~large)), f"cells{k}")), f"depth{k}")
        if last:
            break
        deeper = nodes_of(labelled(now.where(large).drop("comp", "size", "mass", "lead")), now.count(), f"large{k}")
        if not deeper.limit(1).count():
            break
        keep_texts(deeper, f"large-texts{k}")

    # labels meet classes first, so that the rows of a large class need one join, of which the hot classes are no part
    component = classes.join(comps.select(F.col("id").alias("rep"), "comp"), "rep", "left").select("fa", "fb", "n", "size", F.coalesce("comp", "rep").alias("component"))
    component = scratch.write("component", component)
    key = ["fa", "fb", "n"]
    full = F.col("id").isNotNull() & (F.col("n") > 0)
    ids = all_rows.select("id", "n", "fa", "fb")
    hot = F.col("size") * HOT > all_rows.count()
    few, rest = component.where(hot).drop("size"), component.where(~hot).drop("size")
    out = ids.where(full).join(F.broadcast(few), key).unionByName(ids.where(full).join(F.broadcast(few.select(*key)), key, "left_anti").join(rest, key))
    out = out.unionByName(ids.where(~full).withColumn("component", F.col("id")))
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.coalesce(F.col("id") == F.col("component"), F.lit(True)).alias("kept"))


def drop_near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one row of each group: the one with the least id."""
    i, r, k = fresh(docs, "_nid", "_nrow", "_nkey")
    gone = near_duplicates(docs, doc_id=doc_id, text=text).where("not kept").select(F.col("doc_id").alias(k)).distinct()
    out = docs.join(gone, F.col(doc_id).cast("bigint") == F.col(k), "left_anti")
    return out.withColumn(r, row_key(doc_id, text)).dropDuplicates([doc_id, r]).drop(r)
