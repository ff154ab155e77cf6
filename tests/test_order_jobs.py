"""An ordering of a few thousand rows: what it reads, and in how many jobs."""

from pyspark.sql import functions as F

from semrank.exec.packed import PACKED_MAX
from semrank.operators import frame
from semrank.operators.frame import llm_order_by
from semrank.plans.spec import EXT_MERGE, QUICK_3


def rows(spark, n):
    return spark.range(n).select("id", F.concat(F.lit("text "), "id").alias("t"), (F.col("id") % 5 > 1).cast("int").alias("lat"))


def test_quick_sort_beyond_packed_max_stays_in_a_worker(spark, monkeypatch):
    """Before, it went through the jobs of a level in waves, only to be sorted in one worker there."""
    n = PACKED_MAX + 300
    d = rows(spark, n).where("id <> 7").unionByName(spark.createDataFrame([(7, None, 1)], "id long, t string, lat int"))
    order = lambda **more: [r["id"] for r in llm_order_by(d, "t", "good", id_col="id", latent="lat", path=QUICK_3, **more).orderBy("rnk").collect()]
    waves = order(packed_max=PACKED_MAX)
    monkeypatch.setattr(frame, "run_in_waves", None)
    assert order() == waves == [*sorted((i for i in range(n) if i != 7), key=lambda i: (i % 5 <= 1, i)), 7]


def test_others_run_in_waves_as_before(spark, monkeypatch):
    asked, run = [], frame.run_in_waves
    monkeypatch.setattr(frame, "run_in_waves", lambda items, path, *more: asked.append(path) or run(items, path, *more))
    d = rows(spark, PACKED_MAX + 1)
    assert llm_order_by(d, "t", "good", id_col="id", latent="lat", path=EXT_MERGE, limit=3).count() == 3
    few = d.where("id < 60")
    assert llm_order_by(few, "t", "good", id_col="id", latent="lat", path=QUICK_3, limit=3, packed_max=50).count() == 3
    assert asked == [EXT_MERGE, QUICK_3]


def test_rows_are_read_once_before_they_are_ranked(spark):
    """Before, they were counted in a pass of their own, and their texts were written."""
    read = spark.sparkContext.accumulator(0)

    def count(frames):
        for f in frames:
            read.add(len(f))
            yield f

    d = rows(spark, 40).mapInPandas(count, "id long, t string, lat int")
    out = llm_order_by(d, "t", "good", id_col="id", latent="lat", path=QUICK_3)
    assert read.value == 40
    assert [r["id"] for r in out.orderBy("rnk").collect()] == sorted(range(40), key=lambda i: (i % 5 <= 1, i))
