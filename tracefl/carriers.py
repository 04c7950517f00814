"""Traces of API accesses from the tables at hand: orders (main), events (stream), documents and pages.

The order trace's rows: script_id, domain_id, api, api_id, n_calls, ret, arg1, arg2, ts. Only the columns that it
needs are read, and it is a projection: no shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalogue import AUDIO, GENERIC, NAMED, SLOT_ENDS


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def slot() -> Column:
    return (F.col("l_partkey") * 7 + F.col("l_suppkey") * 13 + F.col("l_linenumber") * 101) % 1000


def api_of(s: Column, line: Column) -> Column:
    out = None
    for name, end in SLOT_ENDS:
        value = F.element_at(F.array(*[F.lit(a) for a in AUDIO]), (line % 5 + 1).cast("int")) if name == "audio" else F.lit(name)
        out = F.when(s < end, value) if out is None else out.when(s < end, value)
    return out.otherwise(F.concat(F.lit("generic_"), (s % GENERIC).cast("string")))


def api_id_of(s: Column) -> Column:
    out = None
    for i, (_, end) in enumerate(SLOT_ENDS):
        out = F.when(s < end, F.lit(i)) if out is None else out.when(s < end, F.lit(i))
    return out.otherwise((s % GENERIC + len(NAMED)).cast("int"))


def order_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem").withColumn("slot", slot())
    return rows.select(
        F.col("l_orderkey").alias("script_id"), (F.col("l_suppkey") * 50 + F.col("l_partkey") % 50).alias("domain_id"), api_of(F.col("slot"), F.col("l_linenumber")).alias("api"), api_id_of(F.col("slot")).cast("int").alias("api_id"),
        F.col("l_quantity").cast("int").alias("n_calls"), F.concat("l_returnflag", "l_linestatus").alias("ret"), F.col("l_discount").alias("arg1"), F.col("l_tax").alias("arg2"), F.col("l_shipdate").alias("ts"),
    )


def order_trace_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each call: call_no 1..n_calls."""
    t = order_trace(spark, sf_dir)
    return t.withColumn("call_no", F.explode(F.sequence(F.lit(1), F.col("n_calls")))).drop("n_calls")


def event_trace(spark: SparkSession, sf_dir: str, gap_hours: int = 6) -> DataFrame:
    """Participant, session (a new one after a gap), api, argument and return value of each event."""
    e = read(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = e.withColumn("new", (F.coalesce(F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp")), F.lit(1 << 60)) > gap_hours * 3_600_000_000).cast("int"))
    e = e.withColumn("session", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return e.select(F.col("user_id").alias("participant_id"), F.col("session").alias("script_no"), F.col("event_type").alias("api"), F.get_json_object("props", "$.k").cast("int").alias("arg"), F.col("value").alias("ret"), "ts", "event_id")


def document_trace(spark: SparkSession, sf_dir: str, n_apis: int = 256) -> DataFrame:
    """Tokens of documents as calls: the bucket of a token is its API, the token its argument."""
    d = read(spark, sf_dir, "documents")
    t = d.select(F.col("doc_id").alias("script_id"), F.col("source").alias("domain"), F.explode(F.filter(F.split(F.lower("text"), r"[^a-zà-ÿ]+"), lambda x: x != "")).alias("token"))
    return t.withColumn("api_id", F.conv(F.substring(F.md5("token"), 1, 8), 16, 10).cast("long") % n_apis)


def page_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inline scripts of pages, with the host."""
    p = read(spark, sf_dir, "pages")
    return p.select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/:]+)", 1).alias("host"), F.posexplode(F.regexp_extract_all("html", F.lit(r"(?s)<script[^>]*>(.*?)</script>"), 1)).alias("script_no", "body"))


def _sql_case(values: list[str], rest: str, s: str) -> str:
    return "CASE " + " ".join(f"WHEN {s} < {end} THEN {v}" for v, (_, end) in zip(values, SLOT_ENDS, strict=True)) + f" ELSE {rest} END"


_SLOT = "((l_partkey*7 + l_suppkey*13 + l_linenumber*101) % 1000)"
_AUDIO_SQL = "list_extract([" + ", ".join(f"'{a}'" for a in AUDIO) + "], CAST(l_linenumber % 5 + 1 AS INT))"
#: DuckDB CTE of the order trace.
SQL_TRACE = f"""trace AS (
  SELECT l_orderkey AS script_id, l_suppkey*50 + l_partkey%50 AS domain_id,
         {_sql_case([_AUDIO_SQL if n == "audio" else f"'{n}'" for n, _ in SLOT_ENDS], f"'generic_' || ({_SLOT} % {GENERIC})", _SLOT)} AS api,
         {_sql_case([str(i) for i in range(len(SLOT_ENDS))], f"{len(NAMED)} + {_SLOT} % {GENERIC}", _SLOT)} AS api_id,
         CAST(l_quantity AS INT) AS n_calls, l_returnflag || l_linestatus AS ret, l_discount AS arg1, l_tax AS arg2, l_shipdate AS ts
  FROM lineitem)"""
