"""Quality classifier: hashed word n-grams, logistic regression by follow-the-regularised-leader updates.

A text is cut into words and runs of symbols. Its features are hashed single words and word
pairs, and pairs and triples of word shapes (lower, title or upper case, digits, a symbol
run, a word that repeats the one before it), which carry over to words never seen in training. A feature's value
is its share of all features of its kind; a score is one sparse dot product.

Training reads a bounded sample: the ``SAMPLE`` labelled rows with the least MD5 of the id among
those that are not held out (crc32 of the id mod 5 is not 0). Their hashed counts, not their texts, reach the
driver. Every row is scored, by a vectorised function over its whole text.

Defined cases: null and empty texts have no features and score the bias; rows with a null id
count as held out and are never learnt from; labels that are null are ignored, and of conflicting labels
the least holds; without any label every score is 0.5; repeated rows score alike; an empty
table gives an empty table; extra columns are carried or left unread.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.llm.text import fresh

SAMPLE = 4000
DIM = 1 << 18
EPOCHS = 4
ALPHA, BETA, L1, L2 = 0.5, 1.0, 0.01, 1.0
SCALE = 10.0
CUT = 0.3
PIECE = re.compile(r"[^\W_]+|[^\w\s]+|_+")
CACHE, LONGEST = 100_000, 256
ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], dtype=np.uint64)


def shape(piece: str) -> str:
    if not piece[0].isalnum():
        return piece if len(piece) <= 3 else piece[:1] * 4
    if piece.isdigit():
        return "0"
    return "a" if piece.islower() else "A" if piece.isupper() and len(piece) > 1 else "Aa"


class Pieces(dict):
    """Piece -> the hash of its lower case in the low half, that of its shape in the high half."""

    def __missing__(self, piece: str) -> int:
        if len(self) > CACHE:
            self.clear()
        lex = xxhash.xxh32_intdigest(piece.lower().encode("utf-8", "surrogatepass"))
        out = xxhash.xxh32_intdigest(shape(piece).encode("utf-8", "surrogatepass"), 7) << 32 | lex
        if len(piece) <= LONGEST:
            self[piece] = out
        return out


def feature_ids(text: str | None, pieces: Pieces) -> list[np.ndarray]:
    """Hashed features by kind: words and word pairs, shape pairs and triples."""
    found = PIECE.findall(text or "")
    h = np.fromiter(map(pieces.__getitem__, found), np.uint64, len(found))
    if not len(h):
        return []
    lex, form = h & np.uint64(0xFFFFFFFF), h >> np.uint64(32)
    form = form.copy()
    form[1:][h[1:] == h[:-1]] += np.uint64(1)  # a repeated word has a shape of its own
    slot = lambda x, k: (x * ODD[k] >> np.uint64(64 - 18)).astype(np.int64)
    with np.errstate(over="ignore"):
        pair, forms = lex[:-1] * ODD[1] + lex[1:], form[:-1] * ODD[2] + form[1:]
        kinds = [np.concatenate([slot(lex + np.uint64(1), 0), slot(pair, 0)]), slot(forms, 1), slot(forms[:-1] * ODD[0] + form[2:], 2)]
    return [x for x in kinds if len(x)]


def sparse(text: str | None, pieces: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature ids and their values; id DIM is the bias."""
    kinds = feature_ids(text, pieces)
    ids = np.concatenate([*kinds, np.array([DIM])])
    values = np.concatenate([*[np.full(len(x), SCALE / len(x)) for x in kinds], np.array([1.0])])
    out, where = np.unique(ids, return_inverse=True)
    return out.astype(np.int32), np.bincount(where, values).astype(np.float32)


def fit_ftrl(rows: list[tuple[np.ndarray, np.ndarray, int]]) -> np.ndarray:
    """Weights after EPOCHS passes of FTRL-proximal updates over the rows, in the order given."""
    z, n, w = np.zeros(DIM + 1), np.zeros(DIM + 1), np.zeros(DIM + 1)
    for _ in range(EPOCHS):
        for ids, values, label in rows:
            zi, ni = z[ids], n[ids]
            wi = np.where(np.abs(zi) <= L1, 0.0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(ni)) / ALPHA + L2))
            g = (1 / (1 + np.exp(-np.clip(values @ wi, -30, 30))) - label) * values
            z[ids] = zi + g - (np.sqrt(ni + g * g) - np.sqrt(ni)) / ALPHA * wi
            n[ids] = ni + g * g
    seen = n > 0
    w[seen] = np.where(np.abs(z[seen]) <= L1, 0.0, -(z[seen] - np.sign(z[seen]) * L1) / ((BETA + np.sqrt(n[seen])) / ALPHA + L2))
    return w


def held_out(doc_id: str | Column) -> Column:
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.crc32(c.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def train(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text", label: str = "quality", sample: int = SAMPLE) -> np.ndarray:
    given = labels.select(F.col(doc_id).alias("_id"), F.col(label).cast("int").alias("_y")).where("_y is not null").where(~held_out("_id"))
    given = given.groupBy("_id").agg(F.min("_y").alias("_y")).orderBy(F.md5(F.col("_id").cast("string")), "_id").limit(sample)
    rows = docs.select(F.col(doc_id).alias("_id"), F.col(text).alias("_t")).join(F.broadcast(given), "_id")

    def counts(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pieces = Pieces()
        for f in frames:
            found = [sparse(t, pieces) for t in f["_t"]]
            yield pd.DataFrame({"_id": f["_id"], "_y": f["_y"], "ids": [a.tobytes() for a, _ in found], "values": [b.tobytes() for _, b in found]})
        # workers outlive tasks: what this one no longer needs goes back to the system
        pieces.clear()
        pa.default_memory_pool().release_unused()

    got = rows.mapInPandas(counts, "_id bigint, _y int, ids binary, values binary").toPandas()
    got["order"] = [xxhash.xxh64_intdigest(str(i)) for i in got["_id"]]
    got = got.sort_values(["order", "ids"])
    return fit_ftrl([(np.frombuffer(a, np.int32), np.frombuffer(b, np.float32).astype(float), int(y)) for a, b, y in zip(got["ids"], got["values"], got["_y"], strict=True)])


def scorer(spark: SparkSession, weights: np.ndarray):
    shared = spark.sparkContext.broadcast(weights.astype(np.float32))

    @F.pandas_udf("double")
    def score(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        w, pieces = shared.value.astype(float), Pieces()
        for s in texts:
            out = []
            for t in s:
                x = w[DIM] + sum(SCALE * w[k].mean() for k in feature_ids(t, pieces))
                out.append(1 / (1 + np.exp(-min(max(x, -30), 30))))
            yield pd.Series(out, dtype=float)
        pieces.clear()
        pa.default_memory_pool().release_unused()

    return score


def classify(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, held_out, score and predicted of every row."""
    score = scorer(docs.sparkSession, train(docs, labels, doc_id=doc_id, text=text))
    d = docs.select(F.col(doc_id).alias("doc_id"), held_out(doc_id).alias("held_out"), score(F.col(text)).alias("score"))
    return d.withColumn("predicted", (F.col("score") >= CUT).cast("int"))


def keep_quality(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the rows that the classifier rejects."""
    (s,) = fresh(docs, "_quality_score")
    score = scorer(docs.sparkSession, train(docs, labels, doc_id=doc_id, text=text))
    return docs.withColumn(s, score(F.col(text))).where(F.col(s) >= CUT).select(*docs.columns)
