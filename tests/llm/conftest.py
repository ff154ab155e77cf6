import pytest
from pyspark.sql import types as T

SCHEMA = T.StructType(
    [T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())]
    # names that operators use or return themselves
    + [T.StructField(c, T.StringType()) for c in ("kept", "size", "score", "n_words", "_t", "id", "row", "component_id", "pos", "comp", "_next", "fingerprint")]
)
EXTRA = ("x",) * 12

LONG = " ".join(f"word{i % 977} other{i * 7 % 1013}" for i in range(20000))
POEM = "\n".join(f"line {i} of a passage that comes again and again in many texts" for i in range(12))


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in any column, empty, blank and very long texts, ties, repeated rows, clashing columns."""
    texts = [
        (1, "the quick brown fox jumps over the lazy dog again and again today", "en", "a"),
        (2, None, "en", "a"),
        (3, "", None, "b"),
        (4, " \t\n ", "en", None),
        (5, LONG, "en", "b"),
        (6, "zwei drei", "de", "b"),
        (7, "the quick brown fox jumps over the lazy dog again and again today", "en", "a"),
        (7, "the quick brown fox jumps over the lazy dog again and again today", "en", "a"),
        (None, "a row without an id but with enough words to be judged by every rule", "en", "a"),
        (8, POEM + "\nthe end of one", "en", "c"),
        (9, "a start\n" + POEM, "en", "c"),
        (10, "token = \"04dbebab91ab85687d33eeaaf9ac699e1188f962\" é 日本 😀", "en", "c"),
        (11, "word " * 300, "en", "a"),
    ]
    return spark.createDataFrame([(i, t, g, s, None if t is None else len(t), *EXTRA) for i, t, g, s in texts], SCHEMA)


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.where("doc_id = -1")
