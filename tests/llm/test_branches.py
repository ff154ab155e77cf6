"""Where two fingerprints' texts differ, by their branches."""

import random
from collections import Counter

from semrank.llm import merkle


def plain(a, b):
    """By lines alone: the ends in common go, then lines of one side only, or all that is left."""
    x, y = a.split("\n"), b.split("\n")
    if x == y:
        return [], []
    i = 0
    while i < min(len(x), len(y)) and x[i] == y[i]:
        i += 1
    j = 0
    while j < min(len(x), len(y)) - i and x[-1 - j] == y[-1 - j]:
        j += 1
    p, q = x[i : len(x) - j], y[i : len(y) - j]
    moved = not set(p) - set(q) and not set(q) - set(p)
    return [i + k for k, v in enumerate(p) if moved or v not in q], [i + k for k, v in enumerate(q) if moved or v not in p]


def test_edits_are_located(spark):
    rng = random.Random(4)
    base = [f"Paragraph {k}, of {rng.randrange(10**6)}. It goes on, a little." for k in range(40)]
    edit = lambda *at: "\n".join("edited, " + x if k in at else x for k, x in enumerate(base))
    t = "\n".join(base)
    pairs = [(t, t), (t, edit(7)), (t, edit(0)), (t, edit(39)), (t, edit(3, 21, 35)), (t, "\n".join(base[:9] + ["new"] + base[9:])), ("\n".join(base[:30]), t), ("", t), ("", ""), ("a", "a\na"), ("a\nb", "b\na"), (t, t + "\n")]
    d = spark.createDataFrame([(i, *p) for i, p in enumerate(pairs)], "i int, x string, y string")
    d = merkle.tree(merkle.tree(d, "x", "x"), "y", "y").select("i", merkle.fingerprint("x").alias("own"), merkle.fingerprint("y").alias("other"))
    got = {r.i: (r.d.a, r.d.b) for r in d.select("i", merkle.differing_branches("own", "other").alias("d")).collect()}
    assert got[1] == ([7], [7]) and got[4] == ([3, 21, 35], [3, 21, 35]) and got[5] == ([], [9]) and got[0] == ([], [])
    for i, (a, b) in enumerate(pairs):
        assert bool(got[i][0] or got[i][1]) == (a != b)
    assert got == {i: plain(*p) for i, p in enumerate(pairs)}


def test_branches_beside_likeness(spark):
    rows = merkle.fingerprints(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    rows = rows.select("fingerprint", "edited_fingerprint", "near_edited", merkle.differing_branches("fingerprint", "edited_fingerprint").alias("d")).collect()
    assert len(rows) == 200
    for r in rows:
        same = r.fingerprint[:32] == r.edited_fingerprint[:32]
        assert same == (not r.d.a and not r.d.b) and (r.near_edited == 1 or not same)


def leaves(fp):
    return Counter(x for p in fp.rsplit(":", 1)[1].split("/") for x in p.split("."))


def test_likeness_counts_repeats(spark):
    texts = ["again and again, " * 400, "one. two. three. " * 50 + "end", "", "a. b. a. b. c", "a. a. a. a", "x\ny\nx\nx"]
    rows = merkle.fingerprints(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")).orderBy("doc_id").collect()
    for r, after in zip(rows, [*rows[1:], rows[0]], strict=True):
        for fp, got in ((r.edited_fingerprint, r.near_edited), (after.fingerprint, r.near_next)):
            a, b = leaves(r.fingerprint), leaves(fp)
            assert got == (1 if r.fingerprint[:32] == fp[:32] else 2 * (a & b).total() / (a.total() + b.total()))
    assert rows[0].near_edited > 0.7


def test_no_text_holds_a_mark(spark):
    pairs = ["a. b", "a.\u0001b", "a.\u0002b", "a.  b", "a.\nb", "a. \nb"]
    rows = merkle.fingerprints(spark.createDataFrame(list(enumerate(pairs)), "doc_id bigint, text string")).collect()
    assert len({r.fingerprint[:32] for r in rows}) == len(pairs)
