"""SQL surfaces: a clause in query text, a table function, scalar and aggregate functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semrank.exec.packed import run_path
from semrank.operators.frame import llm_order_by
from semrank.plans.spec import EXT_MERGE, PathConfig
from semrank.sources.model import Key, ModelBackend, SimBackend, each

CLAUSE = re.compile(r"""\bORDER\s+BY\s+LLM_ORDER_BY\s*\(\s*(\w+)\s*,\s*'((?:[^']|'')*)'\s*\)\s*(ASC|DESC)?\s*(?:LIMIT\s+(\d+))?\s*;?\s*$""", re.I)


def semantic_sql(
    spark: SparkSession, text: str, *, id_col: str, latent: str | None = None, facts: DataFrame | None = None, path: PathConfig | None = None, budget_nano: int | None = None, backend: ModelBackend | None = None
) -> DataFrame:
    """Run a query that ends in ORDER BY LLM_ORDER_BY(column, 'criterion') [ASC|DESC] [LIMIT k].

    What stands before the clause is plain Spark SQL: its filters and limits run below the ranking. The result is ordered by ``rnk``.
    """
    m = CLAUSE.search(text)
    if not m:
        return spark.sql(text)
    below = spark.sql(text[: m.start()])
    out = llm_order_by(
        below, m[1], m[2].replace("''", "'"), desc=(m[3] or "ASC").upper() == "DESC", limit=int(m[4]) if m[4] else None, id_col=id_col, latent=latent, facts=facts, path=path, budget_nano=budget_nano, backend=backend
    )
    return out.drop(latent).orderBy("rnk") if latent else out.orderBy("rnk")


def register_udtf(spark: SparkSession, name: str = "semantic_rank", backend: ModelBackend | None = None, path: PathConfig = EXT_MERGE) -> None:
    """SELECT * FROM semantic_rank(TABLE(q) PARTITION BY (task_id), 'criterion', k): q has task_id, item_id, key, lat; best first."""
    model = backend or SimBackend()

    class SemanticRank:
        def __init__(self):
            self.rows, self.task, self.k, self.criterion = [], None, None, ""

        def eval(self, row, criterion: str, k: int):
            self.task, self.k, self.criterion = row["task_id"], k, criterion
            if row["key"]:
                self.rows.append(Key(int(row["item_id"]), len(row["key"]), int(row["lat"]), None, row["key"]))

        def terminate(self):
            if self.rows:
                keys = sorted(self.rows, key=lambda x: x.item_id)
                for r, i in enumerate(run_path(keys, path, self.k, model.about(self.criterion), self.task)[0], 1):
                    yield self.task, i, r

    spark.udtf.register(name, F.udtf(SemanticRank, returnType="task_id string, item_id bigint, rnk bigint"))


def semantic_score(spark: SparkSession, backend: ModelBackend | None = None, max_point: int = 10):
    """A scalar function (task_id, item_id, text, latent) -> score by the backend's criterion; not deterministic for Catalyst, so that it isn't evaluated twice."""
    model = backend or SimBackend()

    @F.pandas_udf(T.IntegerType())
    def score(tasks: pd.Series, ids: pd.Series, texts: pd.Series, latents: pd.Series) -> pd.Series:
        rows = list(zip(tasks, ids, texts, latents, strict=True))
        return pd.Series(each(model, lambda r: model.score(r[0], Key(int(r[1]), len(r[2]), int(r[3]), None, r[2]), max_point)[0] if r[2] else None, rows), dtype="Int32")

    return score.asNondeterministic()


def rank_agg(backend: ModelBackend | None = None, path: PathConfig = EXT_MERGE):
    """An aggregate (item_id, latent, text) -> ids in order by the backend's criterion. A group must fit one worker: for packed tasks only."""
    model = backend or SimBackend()

    @F.pandas_udf(T.ArrayType(T.LongType()))
    def ranked(ids: pd.Series, latents: pd.Series, texts: pd.Series) -> list:
        keys = [Key(int(i), len(t), int(x), None, t) for i, x, t in sorted(zip(ids, latents, texts, strict=True)) if t]
        return run_path(keys, path, None, model, "agg")[0]

    return ranked


def sem_filter(df: DataFrame, score, cut: int) -> DataFrame:
    """Rows whose semantic score (a column from ``semantic_score``) reaches the cut."""
    return df.withColumn("_sem", score).where(F.col("_sem") >= cut).drop("_sem")


def sem_extract(df: DataFrame, text: str, extract, returns: str, to: str = "extracted") -> DataFrame:
    """A column that ``extract`` (list of texts -> list of values, one call per Arrow batch) reads from a text."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield f.assign(**{to: extract(list(f[text]))})

    schema = T.StructType([*df.schema.fields, T.StructField(to, T._parse_datatype_string(returns))])
    return df.mapInPandas(run, schema)


def sem_join(left: DataFrame, right: DataFrame, verdict, most_left: int = 10_000) -> DataFrame:
    """Pairs that a model accepts: a stated left side, its size checked, meets all of the right in blocks of Arrow batches."""
    if left.limit(most_left + 1).count() > most_left:
        raise ValueError(f"more than {most_left} rows on the left: narrow it first")
    pairs = right.crossJoin(F.broadcast(left))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield f[[bool(x) for x in verdict(f)]]

    return pairs.mapInPandas(run, pairs.schema)
