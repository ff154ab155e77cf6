"""What the operators share: words, lines, free column names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A run of the six ASCII blanks that separate words.
BLANKS = r"[\x20\x09-\x0D]+"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole(text: str | Column) -> Column:
    """The text, null as empty."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def words(text: str | Column) -> Column:
    """Maximal runs of anything but the ASCII blanks; none for null."""
    return F.array_remove(F.split(whole(text), BLANKS), "")


def n_words(text: str | Column) -> Column:
    return F.size(words(text)).cast("bigint")


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Names like those given that no column of ``df`` has, whatever its case."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def row_key(doc_id: str | Column, text: str | Column) -> Column:
    """64 bits that tell rows apart which share an id; rows alike in id and text share it."""
    return F.xxhash64(doc_id, text)
