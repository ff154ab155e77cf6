"""Items from files and rankings to files, in the formats that Spark brings along."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "orc", "json", "csv")
#: Texts with line ends and quotes survive CSV with these; a null is written as NULL_MARK, so that it is no empty text.
NULL_MARK = "\\N"
CSV = {"header": "true", "multiLine": "true", "quote": '"', "escape": '"', "nullValue": NULL_MARK}


def _checked(fmt: str) -> dict[str, str]:
    if fmt not in FORMATS:
        raise ValueError(f"format is one of {', '.join(FORMATS)}")
    return CSV if fmt == "csv" else {}


def read_items(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table to be ranked. JSON and CSV need a schema, so that no pass over the data guesses one."""
    options = _checked(fmt)
    if schema is None and fmt in ("json", "csv"):
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_ranking(ranking: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "error") -> None:
    """A ranking in any of the formats, in folders by ``partition_by``."""
    ranking.write.format(fmt).options(**_checked(fmt)).mode(mode).partitionBy(*partition_by).save(path)
