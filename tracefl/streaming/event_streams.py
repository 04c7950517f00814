"""Streaming operators over the event trace, as files that arrive one after the other; each is checked against the batch answer.

Event time is UTC; the table's timestamps have no zone, which watermarks don't take, so they are cast first.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..carriers import read
from ..registry import query
from ..sources.io import EVENTS, BrowserTraces, scratch


def arrivals(spark: SparkSession, sf_dir: str, files: int = 4) -> tuple[DataFrame, str]:
    """(stream, folder): the events as a stream of files in time order, one a micro-batch. Whatever order their ids have, no file holds an event older than the file before; those without a time come last."""
    folder = scratch(spark)
    e = read(spark, sf_dir, "events")
    at = F.coalesce(F.unix_micros(F.col("ts").cast("timestamp")), F.lit((1 << 63) - 1))
    cuts = [*(e.agg(F.percentile_approx(at, [i / files for i in range(1, files)])).first()[0] or [0] * (files - 1)), None]
    lo = None
    for hi in cuts:
        mine = F.lit(True) if lo is None else at >= lo
        e.where(mine if hi is None else mine & (at < hi)).coalesce(1).write.mode("append").parquet(folder)
        lo = hi
    s = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(folder)
    return s.withColumn("ts", F.col("ts").cast("timestamp")), folder


def in_place(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of the table's own files, without copies in time order: for queries whose rows depend on no other row."""
    s = spark.readStream.schema(EVENTS).option("maxBytesPerTrigger", 1 << 28).parquet(f"{sf_dir}/events.parque[t]")  # a pattern: a stream takes a bare path for a folder, and the table may be one file
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str, spark: SparkSession) -> DataFrame:
    """All that the stream gives. What is appended goes to files, however much; the other modes' results have a row for each group at most in a batch and go to a memory sink."""
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch(spark)).trigger(availableNow=True)
    name = f"tf_{uuid.uuid4().hex[:12]}"
    target = scratch(spark) if mode == "append" else None
    q = writer.format("parquet").start(target) if target else writer.format("memory").queryName(name).start()
    q.awaitTermination()
    if q.exception():
        raise RuntimeError(str(q.exception()))
    return spark.read.schema(stream.schema).parquet(target) if target else spark.table(name)


def _windows(name: str, length: str, slide: str | None, sql_starts: str) -> None:
    hours = {"1 hour": "INTERVAL 1 HOUR"}[length]

    @query(name, f"WITH w AS ({sql_starts}) SELECT start, event_type, count(*) AS n FROM w GROUP BY 1, 2 HAVING start + {hours} <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)")
    def run(spark: SparkSession, d: str) -> DataFrame:
        s, _ = arrivals(spark, d)
        w = F.window("ts", length, slide) if slide else F.window("ts", length)
        out = s.withWatermark("ts", "10 minutes").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))
        return drain(out, "append", spark).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


_windows("sm_tumbling_counts", "1 hour", None, "SELECT date_trunc('hour', ts)::TIMESTAMP AS start, event_type FROM events")
_windows("sm_sliding_counts", "1 hour", "15 minutes", "SELECT time_bucket(INTERVAL 15 MINUTE, ts)::TIMESTAMP - to_minutes(CAST(15 * i AS INT)) AS start, event_type FROM events, range(4) r(i)")


@query("sm_session_scripts", "WITH s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events)")
def sm_session_scripts(spark: SparkSession, d: str) -> DataFrame:
    s, _ = arrivals(spark, d)
    out = s.withWatermark("ts", "0 seconds").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drain(out, "append", spark).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("sm_watermark_dedup", "SELECT DISTINCT event_type, user_id FROM events")
def sm_watermark_dedup(spark: SparkSession, d: str) -> DataFrame:
    s, _ = arrivals(spark, d)
    return drain(s.withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_type", "user_id"]), "append", spark).select("event_type", "user_id")


@query("sm_output_complete", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def sm_output_complete(spark: SparkSession, d: str) -> DataFrame:
    s, _ = arrivals(spark, d)
    return drain(s.groupBy("event_type").agg(F.count("*").alias("n")), "complete", spark)


@query("sm_output_update", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def sm_output_update(spark: SparkSession, d: str) -> DataFrame:
    s, _ = arrivals(spark, d)
    return drain(s.groupBy("event_type").agg(F.count("*").alias("n")), "update", spark).groupBy("event_type").agg(F.max("n").alias("n"))


@query("sm_join_static_model", "SELECT event_id, user_id, round(value * w, 6) AS score FROM events JOIN (VALUES ('click', 0.5), ('view', 0.1), ('purchase', 2.0)) m(event_type, w) USING (event_type)")
def sm_join_static_model(spark: SparkSession, d: str) -> DataFrame:
    model = spark.createDataFrame([("click", 0.5), ("view", 0.1), ("purchase", 2.0)], "event_type string, w double")
    s = in_place(spark, d)
    return drain(s.join(F.broadcast(model), "event_type").select("event_id", "user_id", F.round(F.col("value") * F.col("w"), 6).alias("score")), "append", spark)


@query("sm_stream_stream_interval", "SELECT a.event_id AS load, b.event_id AS call FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR WHERE a.event_type < b.event_type")
def sm_stream_stream_interval(spark: SparkSession, d: str) -> DataFrame:
    a, _ = arrivals(spark, d)
    b, _ = arrivals(spark, d)
    a = a.withWatermark("ts", "1 hour").select(F.col("event_id").alias("load"), F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_type").alias("k"))
    b = b.withWatermark("ts", "1 hour").select(F.col("event_id").alias("call"), "user_id", "ts", "event_type")
    return drain(a.join(b, F.expr("u = user_id AND ts > t AND ts <= t + INTERVAL 2 HOURS")).where("k < event_type").select("load", "call"), "append", spark)


@query("sm_late_drop")
def sm_late_drop(spark: SparkSession, d: str) -> DataFrame:
    """A second file older than the watermark: its rows don't count."""
    folder = scratch(spark)
    mk = lambda rows: spark.createDataFrame(rows, "event_id long, t string").select("event_id", F.col("t").cast("timestamp").alias("ts"))
    mk([(1, "2024-01-01 10:00:00"), (2, "2024-01-01 12:30:00")]).coalesce(1).write.mode("append").parquet(folder)
    name = f"tf_{uuid.uuid4().hex[:12]}"
    s = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(folder)
    out = s.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    q = out.writeStream.outputMode("update").format("memory").queryName(name).option("checkpointLocation", scratch(spark)).start()
    try:
        q.processAllAvailable()
        mk([(3, "2024-01-01 10:30:00"), (4, "2024-01-01 12:40:00")]).coalesce(1).write.mode("append").parquet(folder)
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.table(name).groupBy(F.col("w.start").cast("string").alias("start")).agg(F.max("n").alias("n"))


@query("sm_stateful_features", "SELECT user_id, event_type, count(*) AS calls FROM events GROUP BY 1, 2")
def sm_stateful_features(spark: SparkSession, d: str) -> DataFrame:
    """Running call counts of each participant in keyed state, as a device would keep them."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        so_far = dict(zip(*state.get, strict=True)) if state.exists else {}
        for f in frames:
            for k, n in f.groupby("event_type").size().items():
                so_far[k] = so_far.get(k, 0) + int(n)
        state.update((list(so_far), list(so_far.values())))
        yield pd.DataFrame({"user_id": [key[0]] * len(so_far), "event_type": list(so_far), "calls": list(so_far.values())})

    s, _ = arrivals(spark, d)
    out = s.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(count, "user_id long, event_type string, calls long", "kinds array<string>, counts array<long>", "update", "NoTimeout")
    return drain(out, "update", spark).groupBy("user_id", "event_type").agg(F.max("calls").alias("calls"))


@query("sm_refresh_available_now", "SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def sm_refresh_available_now(spark: SparkSession, d: str) -> DataFrame:
    """Each micro-batch is a refresh: its partial statistics are appended once (by batch id) and summed."""
    target = scratch(spark)
    s, _ = arrivals(spark, d)

    def refresh(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total")).write.mode("overwrite").parquet(f"{target}/batch={batch_id}")

    q = s.writeStream.foreachBatch(refresh).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(target).groupBy("user_id").agg(F.sum("n").cast("long").alias("n"), F.round(F.sum("total"), 4).alias("total"))


@query("sm_private_release")
def sm_private_release(spark: SparkSession, d: str) -> DataFrame:
    """Noised totals of each micro-batch until the ledger's budget is used up."""
    from ..hashing import py_normal
    from ..privacy import Ledger

    book, out = Ledger(12.0), []
    s, _ = arrivals(spark, d)

    def release(batch: DataFrame, batch_id: int) -> None:
        total = batch.groupBy("user_id").agg(F.least(F.count("*"), F.lit(20)).alias("c")).agg(F.sum("c")).first()[0] or 0
        try:
            eps = book.charge(f"release {batch_id}", 1.0, 1.0)
            out.append((batch_id, float(total) + 20.0 * py_normal("release", batch_id), eps, True))
        except RuntimeError:
            out.append((batch_id, None, book.spent(), False))

    q = s.writeStream.foreachBatch(release).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame(out, "batch long, total double, epsilon double, released boolean")


@query("g8_label_stream", "WITH c AS (SELECT user_id AS script_id, count(*) FILTER (event_type = 'click') AS a, count(*) FILTER (event_type = 'purchase') AS b FROM events GROUP BY 1) SELECT script_id, CAST(a > 20 AND b > 10 AS INT) AS y FROM c")
def g8_label_stream(spark: SparkSession, d: str) -> DataFrame:
    """A rule over counts that are kept up to date by the stream; the last state equals the batch's."""
    s, _ = arrivals(spark, d)
    c = s.groupBy(F.col("user_id").alias("script_id")).agg(F.count_if(F.col("event_type") == "click").alias("a"), F.count_if(F.col("event_type") == "purchase").alias("b"))
    last = drain(c, "update", spark).groupBy("script_id").agg(F.max("a").alias("a"), F.max("b").alias("b"))
    return last.select("script_id", ((F.col("a") > 20) & (F.col("b") > 10)).cast("int").alias("y"))


@query("src_stream_files", "SELECT count(*) AS n FROM events")
def src_stream_files(spark: SparkSession, d: str) -> DataFrame:
    s, _ = arrivals(spark, d)
    return drain(s.select("event_id"), "append", spark).agg(F.count("*").alias("n"))


@query("src_python_stream")
def src_python_stream(spark: SparkSession, d: str) -> DataFrame:
    spark.dataSource.register(BrowserTraces)
    s = spark.readStream.format("browser-traces").option("rows", 1000).load()
    name = f"tf_{uuid.uuid4().hex[:12]}"
    q = s.writeStream.format("memory").queryName(name).option("checkpointLocation", scratch(spark)).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.table(name).groupBy("api").agg(F.sum("n_calls").cast("long").alias("n"))


@query("src_rate_probe")
def src_rate_probe(spark: SparkSession, d: str) -> DataFrame:
    name = f"tf_{uuid.uuid4().hex[:12]}"
    s = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 100).load()
    q = s.writeStream.format("memory").queryName(name).option("checkpointLocation", scratch(spark)).start()
    try:
        while spark.table(name).count() < 100:
            q.awaitTermination(1)
    finally:
        q.stop()
    return spark.table(name).agg((F.count("*") >= 100).alias("enough"))
