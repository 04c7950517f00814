"""Sources and sinks: files of several formats with explicit schemas, layouts for shards, and a reader of browser traces."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

from ..carriers import order_trace, read
from ..registry import query

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def scratch(spark: SparkSession) -> str:
    """A new folder that all executors share: below spark.checkpoint.dir or else the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{base.rstrip('/')}/tracefl-{uuid.uuid4().hex}"


@query("src_parquet_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")))
def src_parquet_counts(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        one = read(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionAll(one)
    return out


_ROUND = "SELECT event_id, user_id, event_type, value, props FROM events"


def _round_trip(name: str, save, load) -> None:
    @query(name, _ROUND)
    def run(spark: SparkSession, d: str) -> DataFrame:
        path = scratch(spark)
        save(read(spark, d, "events").write, path)
        return load(spark.read.schema(EVENTS), path).drop("ts")


_round_trip("src_csv_roundtrip", lambda w, p: w.option("header", True).option("quote", '"').option("escape", '"').csv(p), lambda r, p: r.option("header", True).option("quote", '"').option("escape", '"').csv(p))
_round_trip("src_json_roundtrip", lambda w, p: w.json(p), lambda r, p: r.json(p))
_round_trip("src_orc_roundtrip", lambda w, p: w.orc(p), lambda r, p: r.orc(p))
_round_trip("snk_partitioned", lambda w, p: w.partitionBy("event_type").parquet(p), lambda r, p: r.parquet(p).select("event_id", "ts", "user_id", "event_type", "value", "props"))


@query("src_text", "SELECT count(*) AS lines FROM events")
def src_text(spark: SparkSession, d: str) -> DataFrame:
    path = scratch(spark)
    read(spark, d, "events").select("props").write.text(path)
    return spark.read.text(path).agg(F.count("*").alias("lines"))


@query("src_json_props", "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def src_json_props(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("src_html_scripts", r"SELECT page_id, len(regexp_extract_all(html, '(?s)<script[^>]*>(.*?)</script>', 1)) AS n FROM pages")
def src_html_scripts(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit(r"(?s)<script[^>]*>(.*?)</script>"), 1)).alias("n"))


@query("snk_bucketed", "SELECT script_id, CAST(sum(n) AS BIGINT) AS n FROM (SELECT l_orderkey AS script_id, CAST(l_quantity AS INT) AS n FROM lineitem) GROUP BY 1")
def snk_bucketed(spark: SparkSession, d: str) -> DataFrame:
    """The trace bucketed by script: the grouping by script needs no exchange."""
    name = f"tracefl_bucketed_{uuid.uuid4().hex[:12]}"
    order_trace(spark, d).select("script_id", "n_calls").write.bucketBy(8, "script_id").sortBy("script_id").saveAsTable(name)
    return spark.table(name).groupBy("script_id").agg(F.sum("n_calls").cast("long").alias("n"))


@query("snk_noop")
def snk_noop(spark: SparkSession, d: str) -> DataFrame:
    order_trace(spark, d).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([("noop",)], "sink string")


# a data source of browser traces: JSON lines of events, in batch and as a stream ---------------------------------------------------


def trace_lines(n: int, start: int = 0) -> Iterator[tuple[int, str, int]]:
    """Stand-in for a browser's trace channel: deterministic records, one JSON line each."""
    for i in range(start, start + n):
        rec = json.loads(json.dumps({"script": i % 97, "api": f"api_{i % 13}", "calls": 1 + i % 5}))
        yield rec["script"], rec["api"], rec["calls"]


class _Batch(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.rows, self.parts = int(options.get("rows", 1000)), int(options.get("partitions", 4))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        size = -(-self.rows // self.parts)
        lo = partition.value * size
        yield from trace_lines(max(0, min(size, self.rows - lo)), lo)


class _Stream(DataSourceStreamReader):
    def __init__(self, options: dict[str, str]):
        self.rows, self.step, self.at = int(options.get("rows", 1000)), int(options.get("step", 400)), 0

    def initialOffset(self):
        return {"at": 0}

    def latestOffset(self):
        self.at = min(self.rows, self.at + self.step)
        return {"at": self.at}

    def partitions(self, start, end):
        return [InputPartition((start["at"], end["at"]))]

    def read(self, partition):
        lo, hi = partition.value
        yield from trace_lines(hi - lo, lo)


class BrowserTraces(DataSource):
    """format("browser-traces"), options rows, partitions and (as a stream) step."""

    @classmethod
    def name(cls) -> str:
        return "browser-traces"

    def schema(self):
        return T.StructType([T.StructField("script_id", T.LongType()), T.StructField("api", T.StringType()), T.StructField("n_calls", T.IntegerType())])

    def reader(self, schema):
        return _Batch(self.options)

    def streamReader(self, schema):
        return _Stream(self.options)


@query("src_python_datasource")
def src_python_datasource(spark: SparkSession, d: str) -> DataFrame:
    spark.dataSource.register(BrowserTraces)
    return spark.read.format("browser-traces").option("rows", 5000).load().groupBy("api").agg(F.sum("n_calls").cast("long").alias("n"))
