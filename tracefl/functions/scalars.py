"""Scalar functions in the detector's roles, with the same in DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..carriers import read
from ..hashing import normal, sql_normal, sql_uniform, uniform
from ..plans.core import r6
from ..registry import query


def _on(table: str) -> Callable[[str, str, Callable[[DataFrame], DataFrame]], None]:
    def add(name: str, sql: str, build: Callable[[DataFrame], DataFrame]) -> None:
        query(name, sql)(lambda spark, d: build(read(spark, d, table)))

    return add


docs, pages, events, orders, lines, vecs, parts, cust = (_on(t) for t in ("documents", "pages", "events", "orders", "lineitem", "embeddings", "part", "customer"))

# text
docs("fn_token_split", "SELECT doc_id, len(list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '')) AS tokens FROM documents", lambda d: d.select("doc_id", F.size(F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda x: x != "")).alias("tokens")))
pages("fn_host_from_url", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host FROM pages", lambda p: p.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host")))
parts("fn_regex_api", "SELECT p_partkey, regexp_extract(p_brand, '#([0-9])([0-9])', 2) AS d, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS t FROM part", lambda p: p.select("p_partkey", F.regexp_extract("p_brand", "#([0-9])([0-9])", 2).alias("d"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("t")))
parts("fn_levenshtein_copy", "SELECT p_partkey, levenshtein(p_name, p_type) AS d FROM part", lambda p: p.select("p_partkey", F.levenshtein("p_name", "p_type").alias("d")))
cust("fn_hash_md5_uniform", f"SELECT c_custkey, {sql_uniform('c_custkey', 'c_mktsegment')} AS u FROM customer", lambda c: c.select("c_custkey", uniform(F.col("c_custkey"), F.col("c_mktsegment")).alias("u")))
docs("fn_sha2_content", "SELECT doc_id, sha256(text) AS h FROM documents", lambda d: d.select("doc_id", F.sha2(F.col("text").cast("binary"), 256).alias("h")))
cust("fn_translate_obfuscated", "SELECT c_custkey, translate(c_mktsegment, 'AEIOU', '4310') AS s FROM customer", lambda c: c.select("c_custkey", F.translate("c_mktsegment", "AEIOU", "4310").alias("s")))
parts("fn_like_escape", "SELECT p_partkey FROM part WHERE p_brand LIKE 'Brand#1_'", lambda p: p.where(F.col("p_brand").like("Brand#1_")).select("p_partkey"))
orders("fn_lpad_format", "SELECT o_orderkey, lpad(CAST(o_custkey AS VARCHAR), 9, '0') AS k, upper(o_orderstatus) || '-' || substr(o_orderpriority, 1, 1) AS s FROM orders", lambda o: o.select("o_orderkey", F.lpad(F.col("o_custkey").cast("string"), 9, "0").alias("k"), F.concat_ws("-", F.upper("o_orderstatus"), F.substring("o_orderpriority", 1, 1)).alias("s")))
# time
orders("fn_trunc_refresh_month", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m FROM orders", lambda o: o.select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m")))
orders("fn_datediff", "SELECT o_orderkey, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days FROM orders", lambda o: o.select("o_orderkey", F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days")))
orders("fn_interval_add", "SELECT o_orderkey, o_orderdate + INTERVAL 30 DAY AS due FROM orders", lambda o: o.select("o_orderkey", (F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS")).alias("due")))
events("fn_window_start", "SELECT date_trunc('hour', ts)::TIMESTAMP AS start, count(*) AS n FROM events GROUP BY 1", lambda e: e.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n"))
events("fn_unix_roundtrip", "SELECT event_id, epoch_us(ts) AS us FROM events", lambda e: e.select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us")))
# numbers
lines("fn_sigmoid", "SELECT l_orderkey, l_linenumber, round(1 / (1 + exp(-(l_quantity - 25) / 10)), 6) AS p FROM lineitem", lambda x: r6(x.select("l_orderkey", "l_linenumber", (1 / (1 + F.exp(-(F.col("l_quantity") - 25) / 10))).alias("p")), "p"))
lines("fn_log_loss", "SELECT l_orderkey, l_linenumber, round(-ln(greatest(l_discount, 1e-9)), 6) AS loss FROM lineitem", lambda x: r6(x.select("l_orderkey", "l_linenumber", (-F.ln(F.greatest(F.col("l_discount"), F.lit(1e-9)))).alias("loss")), "loss"))
vecs("fn_norm_clip", "SELECT vec_id, round(least(1.0, 2.0 / sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)))), 4) AS factor FROM embeddings", lambda v: v.select("vec_id", F.round(F.least(F.lit(1.0), 2.0 / F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))), 4).alias("factor")))
cust("fn_box_muller", f"SELECT c_custkey, round({sql_normal(repr('n'), 'c_custkey')}, 6) AS z FROM customer", lambda c: r6(c.select("c_custkey", normal("n", F.col("c_custkey")).alias("z")), "z"))
cust("fn_fixed_point_mod", "SELECT c_custkey, ((CAST(round(c_acctbal * 1048576) AS BIGINT) % 1073741824) + 1073741824) % 1073741824 AS m FROM customer", lambda c: c.select("c_custkey", F.pmod(F.round(F.col("c_acctbal") * 1048576).cast("long"), F.lit(1 << 30)).alias("m")))
cust("fn_round_half_up", "SELECT c_custkey, round(c_acctbal * 4) / 4 AS r, floor(c_acctbal) AS f FROM customer", lambda c: c.select("c_custkey", (F.round(F.col("c_acctbal") * 4) / 4).alias("r"), F.floor("c_acctbal").cast("double").alias("f")))
lines("fn_log1p_counts", "SELECT l_orderkey, l_linenumber, round(ln(1 + l_quantity), 6) AS v FROM lineitem", lambda x: r6(x.select("l_orderkey", "l_linenumber", F.log1p("l_quantity").alias("v")), "v"))
lines("fn_greatest_least_caps", "SELECT l_orderkey, l_linenumber, greatest(least(l_quantity, 40.0), 4.0) AS v FROM lineitem", lambda x: x.select("l_orderkey", "l_linenumber", F.greatest(F.least(F.col("l_quantity"), F.lit(40.0)), F.lit(4.0)).alias("v")))
# arrays
vecs("fn_dot_zip_with", "SELECT vec_id, round(list_sum(list_transform(range(64), lambda i: embedding[i + 1]::DOUBLE * (i % 7))), 3) AS dot FROM embeddings", lambda v: v.select("vec_id", F.round(F.aggregate(F.zip_with("embedding", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: i % 7), lambda x, w: x.cast("double") * w), F.lit(0.0), lambda a, x: a + x), 3).alias("dot")))
vecs("fn_l2_norm_aggregate", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS norm FROM embeddings", lambda v: v.select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 4).alias("norm")))
vecs("fn_array_filter_nonzero", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings", lambda v: v.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive")))
lines("fn_sequence_explode", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(unnest(range(1, CAST(l_quantity AS INT) // 10 + 1)) AS INT) AS i FROM lineitem", lambda x: x.select("l_orderkey", "l_linenumber", "l_partkey", F.explode(F.when(F.col("l_quantity") >= 10, F.sequence(F.lit(1), F.floor(F.col("l_quantity") / 10).cast("int"))).otherwise(F.array().cast("array<int>"))).alias("i")))
orders("fn_array_set_ops", "SELECT o_custkey, len(list_distinct(list(o_orderstatus))) AS n, list_contains(list(o_orderpriority), '1-URGENT') AS urgent FROM orders GROUP BY 1", lambda o: o.groupBy("o_custkey").agg(F.size(F.array_distinct(F.collect_list("o_orderstatus"))).alias("n"), F.array_contains(F.collect_list("o_orderpriority"), "1-URGENT").alias("urgent")))
orders("fn_slice_topk", "SELECT o_custkey, list_sort(list(o_orderkey), 'DESC')[1:3] AS top FROM orders GROUP BY 1", lambda o: o.groupBy("o_custkey").agg(F.slice(F.reverse(F.array_sort(F.collect_list("o_orderkey"))), 1, 3).alias("top")))
orders("fn_flatten", "SELECT o_custkey, CAST(2 * count(*) AS INT) AS n FROM orders GROUP BY 1", lambda o: o.groupBy("o_custkey").agg(F.size(F.flatten(F.collect_list(F.array("o_orderkey", "o_custkey")))).alias("n")))
orders("fn_sort_by_comparator", "SELECT o_custkey, arg_max(o_orderkey, o_totalprice * 1000000 + o_orderkey / 1000000.0) AS best FROM orders GROUP BY 1", lambda o: o.groupBy("o_custkey").agg(F.array_sort(F.collect_list(F.struct("o_totalprice", "o_orderkey")), lambda a, b: F.when(a["o_totalprice"] > b["o_totalprice"], -1).when(a["o_totalprice"] < b["o_totalprice"], 1).otherwise(b["o_orderkey"] - a["o_orderkey"]).cast("int"))[0]["o_orderkey"].alias("best")))
# maps


def _status_map(o: DataFrame) -> DataFrame:
    return o.groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))


orders("fn_map_counts_lookup", "SELECT o_custkey, coalesce(count(*) FILTER (o_orderstatus = 'F'), 0) AS f FROM orders GROUP BY 1", lambda o: _status_map(o).select("o_custkey", F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f")))
orders("fn_map_filter", "SELECT o_custkey, count(*) AS k FROM (SELECT o_custkey, o_orderstatus FROM orders GROUP BY ALL HAVING count(*) > 2) GROUP BY 1", lambda o: _status_map(o).select("o_custkey", F.size(F.map_filter("m", lambda k, v: v > 2)).alias("k")).where("k > 0"))
orders("fn_transform_values_normalise", "SELECT o_custkey, round(max(n) / sum(n), 6) AS top FROM (SELECT o_custkey, o_orderstatus, count(*) AS n FROM orders GROUP BY ALL) GROUP BY 1", lambda o: _status_map(o).select("o_custkey", F.round(F.array_max(F.map_values(F.transform_values("m", lambda k, v: v / F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x)))), 6).alias("top")))
orders("fn_map_zip_default", "SELECT o_custkey, 2 * count(DISTINCT o_orderstatus) AS s FROM orders GROUP BY 1", lambda o: _status_map(o).select("o_custkey", F.aggregate(F.map_values(F.map_zip_with("m", "m", lambda k, a, b: F.lit(2).cast("long"))), F.lit(0).cast("long"), lambda a, x: a + x).alias("s")))
# JSON
events("fn_from_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events", lambda e: e.select("event_id", F.from_json("props", "k int")["k"].alias("k")))
events("fn_get_json_object", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events", lambda e: e.select("event_id", F.get_json_object("props", "$.k").alias("k")))
events("fn_json_tuple", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events", lambda e: e.select("event_id", F.json_tuple("props", "k").alias("k")))
cust("fn_to_json_update", "SELECT c_custkey, '{\"id\":' || c_custkey || ',\"seg\":\"' || c_mktsegment || '\"}' AS j FROM customer", lambda c: c.select("c_custkey", F.to_json(F.struct(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("seg"))).alias("j")))
# conditions
lines("fn_case_families", "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity > 40 THEN 'high' WHEN l_quantity > 20 THEN 'middle' ELSE 'low' END AS c FROM lineitem", lambda x: x.select("l_orderkey", "l_linenumber", F.when(F.col("l_quantity") > 40, "high").when(F.col("l_quantity") > 20, "middle").otherwise("low").alias("c")))
events("fn_schema_explicit", "SELECT event_id, CAST(props->>'$.k' AS INTEGER) AS k, CAST(props->>'$.absent' AS DOUBLE) AS absent FROM events", lambda e: e.select("event_id", F.from_json("props", "k int, absent double").alias("p")).select("event_id", "p.k", "p.absent"))
