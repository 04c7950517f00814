"""Tables written on the way leave no shuffle files behind, so that a stage's disk doesn't depend on the driver's garbage collection."""

from __future__ import annotations

import time
from pathlib import Path

from pyspark.sql import functions as F

from tracefl.llm.common import written


def _shuffle_files(spark) -> set[str]:
    dirs = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    return {p.name for d in dirs for p in Path(d).rglob("shuffle_*")}


def test_written_leaves_no_shuffle_files(spark):
    before = _shuffle_files(spark)
    rows = spark.range(1000).select((F.col("id") % 7).alias("k"), "id").repartition(5, "k")
    got = written(rows.join(rows.groupBy("k").agg(F.count("*").alias("n")), "k"))
    for _ in range(50):
        if not _shuffle_files(spark) - before:
            break
        time.sleep(0.1)
    assert not _shuffle_files(spark) - before
    assert got.count() == 1000 and spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled", None) is None
