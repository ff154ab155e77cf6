"""Token counts as delta-maintained rollups.

The store holds signed totals per committed batch: one row for each (source, lang, version) that
the batch touches. Inserts add, deletes subtract, a revised count adds the difference. A batch is a
folder named after its id; it counts once Spark's success marker is there, and a batch id that has been
committed is not committed again, so retries and replays change nothing. Totals are sums over batches, and
``compact`` folds committed batches into one snapshot. A snapshot lists all batches that it stands for and comes into
being by one rename; from then on the folders that it lists do not count, whether they have been deleted or not. So
a compaction that stops anywhere loses nothing and counts nothing twice.

At scale: changes are summed per task before they move (a hot source is a row per task), the store grows with
groups times batches rather than with documents, and ``compact`` bounds the batches.

Defined cases: null source or lang is a group of its own; null tokens count 0; a repeated change row is a
change of its own (idempotence is per batch id); an empty batch commits and adds nothing; groups whose documents have all
gone drop out of the totals; an empty store gives an empty table; extra columns are left unread.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.exec.scratch import delete_path, file_system, path_exists
from semrank.llm.text import n_words, whole

GROUP = ("source", "lang", "version")
CHANGES = "op string, source string, lang string, version string, tokens bigint, old_tokens bigint"
#: Documents of fewer words are deleted by the registered run.
SHORT = 10
TOTALS = "source string, lang string, version string, n_docs bigint, n_tokens bigint"


def signed(changes: DataFrame) -> DataFrame:
    """Changes (op insert, delete or revise) as signed documents and tokens per group."""
    tokens, old = F.coalesce("tokens", F.lit(0)), F.coalesce("old_tokens", F.lit(0))
    docs = F.when(F.col("op") == "insert", 1).when(F.col("op") == "delete", -1).otherwise(0)
    by = F.when(F.col("op") == "insert", tokens).when(F.col("op") == "delete", -tokens).when(F.col("op") == "revise", tokens - old).otherwise(0)
    return changes.groupBy(*GROUP).agg(F.sum(docs).cast("bigint").alias("n_docs"), F.sum(by).cast("bigint").alias("n_tokens"))


class TokenCounts:
    """A store of committed batches under ``root``."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def _at(self, batch: str) -> str:
        safe = hashlib.sha256(str(batch).encode()).hexdigest()[:24]
        return f"{self.root}/batch-{safe}"

    def committed(self, batch: str) -> bool:
        at = self._at(batch)
        return path_exists(self.spark, f"{at}/_SUCCESS") or at.rpartition("/")[2] in self._folded()

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Add a batch once; false if its id has been committed before."""
        if self.committed(batch):
            return False
        # an attempt that broke off has no marker: it is written anew, whole
        signed(changes).write.mode("overwrite").parquet(self._at(batch))
        return True

    def commit_stream(self, changes: DataFrame, epoch: int) -> None:
        """For foreachBatch: the epoch is the batch id, so a replayed epoch changes nothing."""
        self.commit(f"epoch-{epoch}", changes)

    def _folders(self) -> list[str]:
        """Names of complete batches and snapshots."""
        fs, root = file_system(self.spark, self.root)
        if not fs.exists(root):
            return []
        found = [s.getPath().getName() for s in fs.listStatus(root) if s.isDirectory()]
        return sorted(n for n in found if n.startswith(("batch-", "snapshot-")) and path_exists(self.spark, f"{self.root}/{n}/_SUCCESS"))

    def _folded(self) -> set[str]:
        """Names that a snapshot stands for."""
        out: set[str] = set()
        for n in self._folders():
            if n.startswith("snapshot-"):
                fs, listed = file_system(self.spark, f"{self.root}/{n}/_folded")
                stream = fs.open(listed)
                out |= set(self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8").split())
                stream.close()
        return out

    def _batches(self) -> list[str]:
        """Folders that count."""
        folded = self._folded()
        return [f"{self.root}/{n}" for n in self._folders() if n not in folded]

    def totals(self) -> DataFrame:
        """(source, lang, version) -> n_docs, n_tokens over all committed batches."""
        batches = self._batches()
        rows = self.spark.read.schema(TOTALS).parquet(*batches) if batches else self.spark.createDataFrame([], TOTALS)
        out = rows.groupBy(*GROUP).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        return out.where("n_docs <> 0 or n_tokens <> 0")

    def compact(self, label: str) -> None:
        """Fold all that counts into one snapshot; the ids of batches stay known. One writer at a time."""
        old = [p.rpartition("/")[2] for p in self._batches()]
        name = f"snapshot-{hashlib.sha256(label.encode()).hexdigest()[:24]}"
        if len(old) < 2 or name in self._folders():
            return
        made = f"{self.root}/making-{name}"
        self.totals().write.mode("overwrite").parquet(made)
        fs, listed = file_system(self.spark, f"{made}/_folded")
        stream = fs.create(listed, True)
        stream.write(bytearray("\n".join(sorted(self._folded() | set(old))).encode()))
        stream.close()
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        if not fs.rename(path(made), path(f"{self.root}/{name}")):
            raise RuntimeError(f"{made} could not be renamed")
        self.clean()

    def clean(self) -> None:
        """Delete what no longer counts: folded batches and snapshots that were never finished."""
        fs, root = file_system(self.spark, self.root)
        folded = self._folded()
        for s in fs.listStatus(root):
            n = s.getPath().getName()
            if n in folded or n.startswith("making-"):
                delete_path(self.spark, f"{self.root}/{n}")


#: Versions counted by built-in functions; a tokenizer's own counts come in as changes like these.
def counts(docs: DataFrame) -> DataFrame:
    """source, lang and, per version, a quick count and the exact one."""
    t = whole("text")
    chars = F.length(t)
    return docs.select(
        "source",
        "lang",
        F.explode(
            F.array(
                F.struct(F.lit("words-1").alias("version"), (F.length(t) - F.length(F.replace(t, F.lit(" "))) + 1).cast("bigint").alias("quick"), n_words("text").alias("exact")),
                F.struct(F.lit("bytes-4").alias("version"), F.ceil(chars / 4).cast("bigint").alias("quick"), F.ceil(F.octet_length(t) / 4).cast("bigint").alias("exact")),
            )
        ).alias("c"),
        (n_words("text") < SHORT).alias("short"),
    ).select("source", "lang", "c.*", "short")


def maintain(docs: DataFrame, root: str) -> DataFrame:
    """The life of a corpus in three batches: all documents come in with quick counts, all counts are revised to
    exact ones, documents of fewer than ``SHORT`` words are deleted; batches are folded between, and the revision and the deletes are replayed,
    which must change nothing."""
    store = TokenCounts(docs.sparkSession, root)
    c = counts(docs)
    none = F.lit(None).cast("bigint")
    change = lambda op, tokens, old, rows=c: rows.select(F.lit(op).alias("op"), "source", "lang", "version", tokens.alias("tokens"), old.alias("old_tokens"))
    store.commit("load", change("insert", F.col("quick"), none))
    store.commit("recount", change("revise", F.col("exact"), F.col("quick")))
    store.compact("first")
    store.commit("purge", change("delete", F.col("exact"), none, c.where("short")))
    store.commit("recount", change("revise", F.col("exact"), F.col("quick")))
    store.compact("second")
    store.commit("purge", change("delete", F.col("exact"), none, c.where("short")))
    return store.totals()
