"""Streams over events whose ids aren't in time order, and results that aren't held on the driver."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from tracefl import registry
from tracefl.carriers import read

TINY = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["sm_session_scripts", "src_stream_files", "sm_join_static_model"])
def test_appended_results_come_from_files(spark, name):
    got = registry.queries()[name](spark, TINY)
    assert got.inputFiles()  # a memory sink has none


def test_ids_out_of_time_order(spark, tmp_path):
    """Copies with shifted keys begin again in time: no session may be dropped as late."""
    e = read(spark, TINY, "events")
    copies = e.unionAll(e.withColumn("event_id", F.col("event_id") + 1_000_000).withColumn("user_id", F.col("user_id") + 1_000_000))
    copies.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    run = registry.queries()["sm_session_scripts"]
    one, two = run(spark, TINY), run(spark, str(tmp_path))
    assert two.agg(F.count("*"), F.sum("n")).first() == tuple(2 * x for x in one.agg(F.count("*"), F.sum("n")).first())


def test_no_event_is_lost(spark, tmp_path):
    e = read(spark, TINY, "events")
    e.withColumn("ts", F.when(F.col("event_id") % 3 != 0, F.col("ts"))).withColumn("event_id", F.when(F.col("event_id") % 2 != 0, F.col("event_id"))).write.parquet(f"{tmp_path}/events.parquet")
    assert registry.queries()["src_stream_files"](spark, str(tmp_path)).first()["n"] == e.count()


@pytest.mark.parametrize("files", [0, 5])
def test_static_model_reads_the_table_in_place(spark, tmp_path, monkeypatch, files):
    """No copy of the events is made first, be the table one file or a folder."""
    folder = TINY
    if files:
        folder = str(tmp_path)
        read(spark, TINY, "events").repartition(files).write.parquet(f"{folder}/events.parquet")
    monkeypatch.setattr("tracefl.streaming.event_streams.arrivals", lambda *a, **k: pytest.fail("copied"))
    got = registry.queries()["sm_join_static_model"](spark, folder)
    e = read(spark, TINY, "events")
    weight = F.expr("CASE event_type WHEN 'click' THEN 0.5D WHEN 'view' THEN 0.1D WHEN 'purchase' THEN 2.0D END")
    want = e.select("event_id", "user_id", F.round(F.col("value") * weight, 6).alias("score")).where(weight.isNotNull())
    assert got.count() == want.count() and got.exceptAll(want).isEmpty()
