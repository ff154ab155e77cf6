"""Written intermediate tables in the folder that driver and executors share.

A wave of paid model calls, or the input of several later jobs, is written once
as Parquet and read back: lineage ends there, and a lost executor costs no rerun
of what came before.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a temporary folder in local mode, and an error on a cluster, whose machines share no such folder."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        if not (spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        _OWN[app] = tempfile.mkdtemp(prefix="semrank-")
        atexit.register(shutil.rmtree, _OWN[app], ignore_errors=True)
    return _OWN[app]


_MADE: list[Scratch] = []


def _clear() -> None:
    """At the end of the process, while the session still runs: the tables go."""
    for s in _MADE:
        try:
            delete_path(s.spark, s.root)
        except Exception:  # the session has ended: what clears the checkpoint folder clears these
            return


class Scratch:
    """One operator run's folder of written tables; it lives as long as the process, as results read from it."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
        if not _MADE:
            atexit.register(_clear)
        _MADE.append(self)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def write(self, name: str, df: DataFrame) -> DataFrame:
        """Write ``df`` once, return it as read from there."""
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        """Delete tables that no returned DataFrame reads any more."""
        for name in names:
            delete_path(self.spark, self.path(name))


def file_system(spark: SparkSession, path: str):
    """Hadoop's file system and path object: works for any store that Spark reads."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def delete_path(spark: SparkSession, path: str) -> None:
    fs, where = file_system(spark, path)
    fs.delete(where, True)


def path_exists(spark: SparkSession, path: str) -> bool:
    fs, where = file_system(spark, path)
    return bool(fs.exists(where))
