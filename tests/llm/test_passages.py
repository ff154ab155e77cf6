"""Repeated passages of a few lines in different surroundings."""

import random

import pytest

from semrank.llm import line_dedup
from semrank.llm.text import load

SF = "/root/testdata/sf0.001"


def plain(texts):
    """Id -> text by a plain loop: a pair of neighbouring full lines that came before goes, with the blanks between."""
    first, new = {}, {}
    for i in sorted(texts):
        lines = texts[i].split("\n")
        full = [k for k, x in enumerate(lines) if x.strip(" \t\n\x0b\x0c\r")]
        gone = set()
        for n, (a, b) in enumerate(zip(full, full[1:], strict=False)):
            head = first.setdefault((lines[a], lines[b]), (i, n))
            if head[0] != i or n - head[1] > 1:
                gone |= set(range(a, b + 1))
        new[i] = "\n".join(x for k, x in enumerate(lines) if k not in gone)
    return new


def run(spark, texts):
    rows = line_dedup.dedup_lines(spark.createDataFrame(sorted(texts.items()), "doc_id bigint, text string"), counts=True).collect()
    return {r.doc_id: r for r in rows}


@pytest.mark.parametrize("n", [2, 3, 4])
def test_planted_passages_go(spark, n):
    rng = random.Random(n)
    line = lambda: " ".join(f"w{rng.randrange(10**6)}" for _ in range(30))
    texts, own = {}, {}
    for p in range(20):
        passage = [line() for _ in range(n)]
        for i in (2 * p, 2 * p + 1):
            before, after = [line() for _ in range(rng.randrange(6))], [line() for _ in range(rng.randrange(6))]
            own[i] = before + (passage if i == 2 * p else []) + after
            texts[i] = "\n".join(before + passage + after)
    got = run(spark, texts)
    assert {i: r.text for i, r in got.items()} == {i: "\n".join(x) for i, x in own.items()}
    assert all(r.n_lines_removed == (n if i % 2 else 0) for i, r in got.items())


def test_blank_lines_own_repeats_and_single_lines(spark):
    texts = {1: "a\n\nb\nc", 2: "x\na\nb\ny", 3: "a\ny\nb", 4: "r\nr\nr", 5: "r\nr\nr\nend", 6: "s\ns\ns\ns", 7: "", 8: "a\nb"}
    got = {i: r.text for i, r in run(spark, texts).items()}
    assert got == {1: "a\n\nb\nc", 2: "x\ny", 3: "a\ny\nb", 4: "r\nr\nr", 5: "end", 6: "s\ns", 7: "", 8: ""}


def test_query_is_the_plain_loop(spark):
    import __spark_entry__ as entry

    texts = {r.doc_id: r.text for r in load(spark, SF, "documents").collect() if r.text is not None}
    got = {r.doc_id: r.text for r in entry.queries()["op3_line_dedup"](spark, SF).collect() if r.text is not None}
    assert got == plain(texts)


def test_odd_rows(odd_docs, no_docs):
    out = line_dedup.dedup_lines(odd_docs)
    assert out.columns == odd_docs.columns and out.count() == odd_docs.count()
    assert line_dedup.dedup_lines(no_docs, counts=True).collect() == []


def test_ids_of_any_type(spark):
    rows = [("b", "x\np q\nr s"), ("a", "p q\nr s\ny"), (None, "z\np q\nr s"), ("a", "p q\nr s\ny")]
    out = line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id string, text string")).collect()
    assert sorted((str(r.doc_id), r.text) for r in out) == [("None", "z"), ("a", "p q\nr s\ny"), ("a", "p q\nr s\ny"), ("b", "x")]


def test_a_hot_passage_is_cut_everywhere_but_once(spark):
    from pyspark.sql import functions as F

    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit("own "), "id", F.lit("\na hot line\nand its next\nend "), "id").alias("text"))
    left = line_dedup.dedup_lines(docs).where(F.col("text").contains("hot")).collect()
    assert [r.doc_id for r in left] == [0]


@pytest.mark.parametrize("marks", [15, 24])
def test_bytes_decide_where_hashes_are_alike(spark, monkeypatch, marks):
    """Unlike lines with one rolling hash stay; with the hash alone all of them went."""
    from pyspark.sql import functions as F

    rolled = line_dedup.rolled
    # two bits of one lane are left
    monkeypatch.setattr(line_dedup, "rolled", lambda h: F.transform(rolled(h), lambda x: F.struct(x["a"].bitwiseAND(F.lit(3)).alias("a"), F.lit(0).cast("bigint").alias("b"))))
    monkeypatch.setattr(line_dedup, "MARKS", marks, raising=False)
    rng = random.Random(5)
    texts = {i: "\n".join(rng.choice(["a", "b", " ", "c", "d e", "f", f"own {i}", "long " * 50]) for _ in range(rng.randrange(12))) for i in range(60)}
    assert {i: r.text for i, r in run(spark, texts).items()} == plain(texts)


def test_the_pipeline_stage_compares_bytes(spark, monkeypatch):
    """As above, in the stage: with the hash alone two unlike pairs of lines were one."""
    import corpus_pipeline
    from pyspark.sql import functions as F

    zero = F.lit(0).cast("bigint")
    monkeypatch.setattr(line_dedup, "rolled", lambda h: F.transform(F.slice(F.col(h), F.lit(1), F.size(h) - 1), lambda x: F.struct(zero.alias("a"), zero.alias("b"))))
    docs = spark.createDataFrame([(1, "a\nb"), (2, "c\nd"), (3, "x\na\nb\ny")], "doc_id bigint, text string").withColumn("n_chars", F.length("text").cast("bigint"))
    got = {r.doc_id: (r.text, r.n_chars) for r in corpus_pipeline.cut_repeated_lines(spark, docs, SF).collect()}
    assert got == {1: ("a\nb", 3), 2: ("c\nd", 3), 3: ("x\ny", 3)}
