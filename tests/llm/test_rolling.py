"""The rolling hash of lines, against one rolled by hand."""

import hashlib

from semrank.llm import line_dedup

FULL = (1 << 64) - 1


def turn(x, by):
    return (x << by | x >> (64 - by)) & FULL


def by_hand(lines):
    """Rolled over all lines in one go, lane by lane."""
    lanes = []
    for at in (0, 8):
        h, now, out = [int.from_bytes(hashlib.sha256(x.encode()).digest()[at : at + 8], "big") for x in lines], 0, []
        for k, x in enumerate(h):
            now = turn(now, 1) ^ x ^ (turn(h[k - 2], 2) if k > 1 else 0)
            out.append(now - (now >> 63 << 64))
        lanes.append(out[1:])
    return list(zip(*lanes, strict=True))


def test_hashes_are_rolled_on_across_pieces(spark):
    n = line_dedup.PIECE
    texts = {i: [f"line {(7 * k + i) % 50}" for k in range(c)] for i, c in enumerate((0, 1, 2, 3, n, n + 1, n + 2, 2 * n + 1, 2 * n + 2, 3 * n))}
    docs = spark.createDataFrame([(i, "\n \n".join(x)) for i, x in texts.items()] + [(99, None)], "doc_id bigint, text string")
    got = {}
    for r in line_dedup.rolling(docs, "doc_id", "text").collect():
        got.setdefault(r["_id"], {})[r["_k"]] = (r["_p"]["a"], r["_p"]["b"])
    assert {i: [p for _, p in sorted(x.items())] for i, x in got.items()} == {i: by_hand(x) for i, x in texts.items() if len(x) > 1}


def test_a_window_knows_its_two_lines_alone(spark):
    docs = spark.createDataFrame([(1, "a\nb\nc\nd"), (2, "x\ny\nb\nc"), (3, "c\nb"), (4, "b\nb\nb")], "doc_id bigint, text string")
    p = {(r["_id"], r["_k"]): tuple(r["_p"]) for r in line_dedup.rolling(docs, "doc_id", "text").collect()}
    assert p[1, 1] == p[2, 2] and p[4, 0] == p[4, 1] and len(set(p.values())) == len(p) - 2
