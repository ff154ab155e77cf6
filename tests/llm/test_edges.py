"""Every operator and stage on odd rows and on an empty table."""

import os

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from semrank.exec.scratch import Scratch
from semrank.llm import bpe, license_scan, line_dedup, merkle, mixing, near_dup, quality_classifier, quality_rules, secret_scan, token_counts

LABELS = "doc_id bigint, quality int, toxic int"


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (5, 1, 0), (11, 0, 0), (11, 1, None), (10, None, 0), (None, 1, 0), (9, 1, 0), (99, 1, 1)], LABELS)


OPERATORS = {
    "counts": lambda d, lab: token_counts.maintain(d, Scratch(d.sparkSession, "t").root),
    "secrets": lambda d, lab: secret_scan.secret_scan(d),
    "lines": lambda d, lab: line_dedup.dedup_lines(d, counts=True),
    "rules": lambda d, lab: quality_rules.quality_rules(d),
    "near": lambda d, lab: near_dup.near_duplicates(d),
    "mix": lambda d, lab: mixing.mix_counts(d),
    "bpe": lambda d, lab: bpe.encode_digests(d),
    "licenses": lambda d, lab: license_scan.license_scan(d),
    "classifier": lambda d, lab: quality_classifier.classify(d, lab),
    "merkle": lambda d, lab: merkle.fingerprints(d),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_odd_rows(odd_docs, labels, name):
    got = OPERATORS[name](odd_docs, labels).collect()
    if name != "counts":
        assert len(got) == odd_docs.count()
        ids = sorted(str(r["doc_id"]) for r in got)
        assert ids == sorted(str(r["doc_id"]) for r in odd_docs.collect())


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_table(no_docs, labels, name):
    assert OPERATORS[name](no_docs, labels).collect() == []
    if name == "classifier":
        assert OPERATORS[name](no_docs, labels.limit(0)).collect() == []


def test_no_labels(odd_docs, labels):
    got = quality_classifier.classify(odd_docs, labels.limit(0)).collect()
    assert {r.score for r in got} == {0.5}


@pytest.fixture(scope="module")
def folder(labels, tmp_path_factory):
    root = str(tmp_path_factory.mktemp("sf"))
    labels.write.parquet(f"{root}/labels.parquet")
    return root


@pytest.mark.parametrize("k", range(len(corpus_pipeline.STAGES)))
def test_stages(spark, odd_docs, no_docs, folder, k):
    name, stage = corpus_pipeline.STAGES[k]
    out = stage(spark, odd_docs, folder)
    if k < len(corpus_pipeline.STAGES) - 1:
        assert out.columns == odd_docs.columns
        assert [f.dataType for f in out.schema] == [f.dataType for f in odd_docs.schema]
    assert out.count() > 0
    assert stage(spark, no_docs, folder).count() == 0


def test_pipeline_runs(spark, odd_docs, folder):
    odd_docs.write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    got = corpus_pipeline.run(spark, folder)
    assert {"doc_id", "n_tokens", "ids"} == set(got.columns) and got.count() > 0


def test_near_duplicates_of_odd_rows(odd_docs):
    got = {}
    for r in near_dup.near_duplicates(odd_docs).collect():
        got.setdefault(r.doc_id, set()).add((r.n_shingles, r.component_id, r.kept))
    assert got[7] == {(9, 1, False)} and got[1] == {(9, 1, True)}
    assert got[2] == {(0, 2, True)} and got[4] == {(0, 4, True)} and got[6] == {(1, 6, True)}
    assert got[None] == {(11, None, True)}
    kept = near_dup.drop_near_duplicates(odd_docs)
    assert sorted(str(r.doc_id) for r in kept.select("doc_id").collect()) == sorted(["1", "2", "3", "4", "5", "6", "None", "8", "10", "11"])


def test_repeated_rows_stay_once(odd_docs):
    twice = odd_docs.unionByName(odd_docs)
    assert near_dup.drop_near_duplicates(twice).count() == near_dup.drop_near_duplicates(odd_docs).count()


def test_imports_do_not_leak():
    """Nothing outside the subpackage and the entry's guard imports it."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    for top, _, files in os.walk(os.path.join(root, "semrank")):
        if os.sep + "llm" in top:
            continue
        for f in files:
            if f.endswith(".py"):
                assert "semrank.llm" not in open(os.path.join(top, f)).read(), f


def test_line_removal_compares_bytes(odd_docs):
    out = {r.doc_id: r for r in line_dedup.dedup_lines(odd_docs, counts=True).where(F.col("doc_id").isin(8, 9)).collect()}
    assert out[8].n_chunks_removed == 0 and out[9].n_chunks_removed > 0
    assert out[9].text.count("\n") + 1 + out[9].n_lines_removed == 13
