"""Projections, filters, joins, aggregates, windows, sorts and set operations of the detector, with the same in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import catalogue, features, labels, participants
from ..carriers import SQL_TRACE, order_trace, read
from ..hashing import sql_uniform, uniform
from ..labels import SQL_EVIDENCE, SQL_LABELLED
from ..plans.core import SQL_SITES, SQL_ZIPF, crawl_hits, r6, with_
from ..plans.core import _HITS as HITS
from ..registry import query

T = with_(SQL_TRACE)
LAB = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED)

# projections and filters ------------------------------------------------------------------------------------------------------------


@query("prj_api_case", T + "SELECT api, count(*) AS n FROM trace GROUP BY 1")
def prj_api_case(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).groupBy("api").agg(F.count("*").alias("n"))


@query("prj_struct_pack", T + "SELECT script_id, max(n_calls) AS n, max(struct_pack(n := n_calls, a := api)).a AS api FROM trace GROUP BY 1")
def prj_struct_pack(spark: SparkSession, d: str) -> DataFrame:
    g = order_trace(spark, d).groupBy("script_id").agg(F.max(F.struct(F.col("n_calls").alias("n"), F.col("api").alias("a"))).alias("m"))
    return g.select("script_id", F.col("m.n").alias("n"), F.col("m.a").alias("api"))


@query("prj_widen_types", "SELECT l_orderkey, CAST(floor(l_extendedprice) AS BIGINT) AS price, TRY_CAST(l_returnflag AS INT) AS flag FROM lineitem")
def prj_widen_types(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "lineitem").select("l_orderkey", F.floor("l_extendedprice").cast("long").alias("price"), F.expr("try_cast(l_returnflag AS INT)").alias("flag"))


@query("flt_monitored_api", T + "SELECT script_id, api FROM trace WHERE api IN ('fillText', 'toDataURL', 'measureText')")
def flt_monitored_api(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).where(F.col("api").isin("fillText", "toDataURL", "measureText")).select("script_id", "api")


@query("flt_rlike_arg", r"SELECT event_id FROM events WHERE regexp_matches(props, '\"k\": ?[1-4][0-9]?\}')")
def flt_rlike_arg(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").where(F.col("props").rlike(r'"k": ?[1-4][0-9]?\}')).select("event_id")


@query("flt_between_slots", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_partkey*7 + l_suppkey*13 + l_linenumber*101) % 1000 BETWEEN 160 AND 229")
def flt_between_slots(spark: SparkSession, d: str) -> DataFrame:
    from ..carriers import slot

    return read(spark, d, "lineitem").where(slot().between(160, 229)).select("l_orderkey", "l_linenumber")


@query("flt_null_default", "SELECT doc_id, coalesce(quality, -1) AS quality, nullif(lang, 'en') AS lang FROM documents LEFT JOIN labels USING (doc_id)")
def flt_null_default(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.expr("nullif(lang, 'en')").alias("lang"))


@query("flt_exists_subquery", "SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)")
def flt_exists_subquery(spark: SparkSession, d: str) -> DataFrame:
    read(spark, d, "orders").createOrReplaceTempView("tf_orders")
    read(spark, d, "lineitem").createOrReplaceTempView("tf_lineitem")
    return spark.sql("SELECT o_orderkey FROM tf_orders o WHERE EXISTS (SELECT 1 FROM tf_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)")


@query("flt_not_exists", "SELECT o_orderkey FROM orders o WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def flt_not_exists(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").join(read(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("flt_any_all", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 3)) > 0 AS any_above, len(list_filter(embedding, lambda x: x > -2)) = 64 AS all_above FROM embeddings")
def flt_any_all(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "embeddings").select("vec_id", F.exists("embedding", lambda x: x > 3).alias("any_above"), F.forall("embedding", lambda x: x > -2).alias("all_above"))


@query("flt_hash_sample", f"SELECT c_custkey FROM customer WHERE {sql_uniform(repr('s'), 'c_custkey')} < 0.1")
def flt_hash_sample(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "customer").where(uniform("s", F.col("c_custkey")) < 0.1).select("c_custkey")


@query("flt_scalar_subquery", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > (SELECT avg(l_quantity) * 1.9 FROM lineitem)")
def flt_scalar_subquery(spark: SparkSession, d: str) -> DataFrame:
    read(spark, d, "lineitem").createOrReplaceTempView("tf_lineitem")
    return spark.sql("SELECT l_orderkey, l_linenumber, l_quantity FROM tf_lineitem WHERE l_quantity > (SELECT avg(l_quantity) * 1.9 FROM tf_lineitem)")


# joins ------------------------------------------------------------------------------------------------------------------------------

CAT = catalogue.sql_values()


@query("jn_broadcast_catalogue", T + f"SELECT c.api, is_native, count(*) AS n FROM trace JOIN {CAT} ON api_id = feature_id GROUP BY ALL")
def jn_broadcast_catalogue(spark: SparkSession, d: str) -> DataFrame:
    cat = catalogue.table(spark).select("feature_id", F.col("api").alias("name"), "is_native")
    return order_trace(spark, d).join(F.broadcast(cat), F.col("api_id") == F.col("feature_id")).groupBy(F.col("name").alias("api"), "is_native").agg(F.count("*").alias("n"))


@query("jn_shuffle_hash_features_labels", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED) + "SELECT api_id, CAST(sum(y) AS BIGINT) AS positives FROM trace JOIN labelled USING (script_id) GROUP BY 1")
def jn_shuffle_hash_features_labels(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return trace.join(labels.apply(trace).hint("shuffle_hash"), "script_id").groupBy("api_id").agg(F.sum("y").cast("long").alias("positives"))


@query("jn_sortmerge_trace_scripts", "SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def jn_sortmerge_trace_scripts(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "lineitem").join(read(spark, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "o_custkey")


@query("jn_left_label_default", "SELECT doc_id, coalesce(toxic, 0) AS toxic FROM documents LEFT JOIN labels USING (doc_id)")
def jn_left_label_default(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(0)).alias("toxic"))


@query("jn_full_crawl_diff", HITS + "SELECT script_id, a.family IS NOT NULL AS basic, b.family IS NOT NULL AS stealth FROM (SELECT * FROM hits WHERE crawler = 'basic' AND family = 'canvas') a FULL JOIN (SELECT * FROM hits WHERE crawler = 'stealth' AND family = 'canvas') b USING (script_id)")
def jn_full_crawl_diff(spark: SparkSession, d: str) -> DataFrame:
    h = crawl_hits(spark, d).where("family = 'canvas'")
    a, b = (h.where(F.col("crawler") == c).select("script_id", F.lit(True).alias(c)) for c in ("basic", "stealth"))
    return a.join(b, "script_id", "full").select("script_id", F.coalesce("basic", F.lit(False)).alias("basic"), F.coalesce("stealth", F.lit(False)).alias("stealth"))


@query("jn_right_sites", "SELECT s_suppkey, count(l_orderkey) AS n FROM (SELECT * FROM lineitem WHERE l_quantity > 49) RIGHT JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def jn_right_sites(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "lineitem").where("l_quantity > 49").join(read(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"), "right").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("n"))


@query("jn_semi_positive_scripts", LAB + "SELECT domain_id, script_id FROM (SELECT DISTINCT domain_id, script_id FROM trace) WHERE script_id IN (SELECT script_id FROM labelled WHERE y = 1)")
def jn_semi_positive_scripts(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return participants.bridge(trace).join(labels.apply(trace).where("y = 1"), "script_id", "left_semi").select("domain_id", "script_id")


@query("jn_anti_missed_scripts", HITS + "SELECT DISTINCT script_id FROM hits WHERE crawler = 'manual' AND script_id NOT IN (SELECT script_id FROM hits WHERE crawler <> 'manual')")
def jn_anti_missed_scripts(spark: SparkSession, d: str) -> DataFrame:
    h = crawl_hits(spark, d)
    return h.where("crawler = 'manual'").join(h.where("crawler != 'manual'"), "script_id", "left_anti").select("script_id").distinct()


@query("jn_cross_grid", "SELECT s, e, w FROM (SELECT DISTINCT l_returnflag AS s FROM lineitem), (SELECT DISTINCT o_orderpriority AS e FROM orders), (SELECT DISTINCT event_type AS w FROM events)")
def jn_cross_grid(spark: SparkSession, d: str) -> DataFrame:
    """A grid over the values that three tables have."""
    some = lambda t, c, n: read(spark, d, t).select(F.col(c).alias(n)).distinct()
    return some("lineitem", "l_returnflag", "s").crossJoin(some("orders", "o_orderpriority", "e")).crossJoin(some("events", "event_type", "w"))


@query("jn_range_cdf", with_(SQL_TRACE, SQL_SITES, SQL_ZIPF) + f"SELECT c_custkey, domain_id FROM (SELECT c_custkey, {sql_uniform(repr('r'), 'c_custkey')} AS u FROM customer) JOIN cdf ON u >= lo AND u < hi")
def jn_range_cdf(spark: SparkSession, d: str) -> DataFrame:
    """Intervals cut into cells: an equi-join with a residual instead of a nested loop."""
    cells = 1024
    cdf = participants.zipf(participants.sites(order_trace(spark, d))).withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") * cells), F.least(F.floor(F.col("hi") * cells), F.lit(cells - 1)))))
    u = read(spark, d, "customer").select("c_custkey", uniform("r", F.col("c_custkey")).alias("u")).withColumn("cell", F.floor(F.col("u") * cells))
    return u.join(cdf, "cell").where("u >= lo AND u < hi").select("c_custkey", "domain_id")


@query("jn_theta_rank", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def jn_theta_rank(spark: SparkSession, d: str) -> DataFrame:
    a, b = (read(spark, d, "nation").select(F.col("n_regionkey").alias("r"), F.col("n_nationkey").alias(x)) for x in "ab")
    return a.join(b, "r").where("a < b").select("a", "b")


@query("jn_asof_model_version", "WITH v AS (SELECT event_id AS version, ts AS since FROM events WHERE event_id % 500 = 0) SELECT e.event_id, v.version FROM events e ASOF LEFT JOIN v ON e.ts >= v.since")
def jn_asof_model_version(spark: SparkSession, d: str) -> DataFrame:
    """The latest version at each event's time, by day: a day's rows are sorted with the versions among them, and a day without a version takes the last of the days before."""
    e = read(spark, d, "events").select("event_id", "ts")
    v = e.where("event_id % 500 = 0").select(F.col("event_id").alias("version"), F.col("ts").alias("since"))
    day = lambda c: F.to_date(c)
    last = v.groupBy(day("since").alias("day")).agg(F.max(F.struct("since", "version")).alias("last"))
    days = e.select(day("ts").alias("day")).distinct().join(last, "day", "left")  # a row for each day
    days = days.withColumn("carried", F.last("last.version", True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1))).select("day", "carried")
    both = e.select("ts", "event_id", F.lit(None).cast("long").alias("version"), F.lit(1).alias("o")).unionAll(v.select("since", F.lit(None).cast("long"), "version", F.lit(0)))
    w = Window.partitionBy("day").orderBy("ts", "o", "version").rowsBetween(Window.unboundedPreceding, 0)
    got = both.withColumn("day", day("ts")).withColumn("v", F.last("version", True).over(w)).where("o = 1")
    return got.join(days, "day").select("event_id", F.coalesce("v", "carried").alias("version"))


@query("jn_skew_salted", T + "SELECT d.domain_id, count(*) AS n, max(n_scripts) AS scripts FROM trace d JOIN (SELECT domain_id, count(DISTINCT script_id) AS n_scripts FROM trace GROUP BY 1) s USING (domain_id) GROUP BY 1")
def jn_skew_salted(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    small = trace.groupBy("domain_id").agg(F.count_distinct("script_id").alias("n_scripts")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(7))))
    salted = trace.withColumn("salt", F.pmod(F.hash("script_id"), F.lit(8)))
    return salted.join(small, ["domain_id", "salt"]).groupBy("domain_id").agg(F.count("*").alias("n"), F.max("n_scripts").alias("scripts"))


@query("jn_self_pairs", T + ", c AS (SELECT DISTINCT script_id, api_id FROM trace WHERE api_id < 15) SELECT a.api_id AS a, b.api_id AS b, count(*) AS scripts FROM c a JOIN c b ON a.script_id = b.script_id AND a.api_id < b.api_id GROUP BY ALL")
def jn_self_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of a script's APIs (15 at most) from its one sorted set: no self-join."""
    s = order_trace(spark, d).where("api_id < 15").groupBy("script_id").agg(F.array_sort(F.collect_set("api_id")).alias("s"))
    p = s.select(F.explode("s").alias("a"), "s").select("a", F.explode("s").alias("b")).where("a < b")
    return p.groupBy("a", "b").agg(F.count("*").alias("scripts"))


@query("jn_nullsafe", "SELECT count(*) AS n FROM (SELECT doc_id, toxic FROM documents LEFT JOIN labels USING (doc_id)) a JOIN (VALUES (0), (1), (NULL)) v(t) ON toxic IS NOT DISTINCT FROM t")
def jn_nullsafe(spark: SparkSession, d: str) -> DataFrame:
    v = spark.createDataFrame([(0,), (1,), (None,)], "t int")
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left").join(v, F.col("toxic").eqNullSafe(F.col("t"))).agg(F.count("*").alias("n"))


@query("jn_bloom_runtime", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE {sql_uniform(repr('b'), 'o_custkey')} < 0.02)")
def jn_bloom_runtime(spark: SparkSession, d: str) -> DataFrame:
    """The sampled side filters the large one's scan at run time where Spark finds that worthwhile."""
    o = read(spark, d, "orders").where(uniform("b", F.col("o_custkey")) < 0.02).select("o_orderkey")
    return read(spark, d, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").select("l_orderkey", "l_linenumber")


@query("jn_lateral_topk", "SELECT c_custkey, o_orderkey, o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
def jn_lateral_topk(spark: SparkSession, d: str) -> DataFrame:
    read(spark, d, "orders").createOrReplaceTempView("tf_orders")
    read(spark, d, "customer").createOrReplaceTempView("tf_customer")
    return spark.sql("SELECT c_custkey, o_orderkey, o_totalprice FROM tf_customer, LATERAL (SELECT o_orderkey, o_totalprice FROM tf_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")


# aggregates -------------------------------------------------------------------------------------------------------------------------


def _agg(name: str, sql: str, build) -> None:
    query(name, sql)(lambda spark, d: build(order_trace(spark, d), spark, d))


_agg("ag_hash_call_counts", T + "SELECT api, CAST(sum(n_calls) AS BIGINT) AS n FROM trace GROUP BY 1", lambda t, s, d: t.groupBy("api").agg(F.sum("n_calls").cast("long").alias("n")))
_agg("ag_sort_collect", T + "SELECT script_id, list(n_calls ORDER BY n_calls) AS calls FROM trace GROUP BY 1", lambda t, s, d: t.groupBy("script_id").agg(F.array_sort(F.collect_list("n_calls")).alias("calls")))
_agg("ag_partial_final_sum", T + "SELECT script_id % 8 AS coord, CAST(sum(CAST(round(arg1 * 1048576) AS BIGINT)) AS BIGINT) AS total FROM trace GROUP BY 1", lambda t, s, d: t.groupBy((F.col("script_id") % 8).alias("coord")).agg(F.sum(F.round(F.col("arg1") * 1048576).cast("long")).alias("total")))
_agg("ag_distinct_fonts", T + "SELECT script_id, count(DISTINCT arg1) AS n FROM trace WHERE api = 'font' GROUP BY 1", lambda t, s, d: t.where("api = 'font'").groupBy("script_id").agg(F.count_distinct("arg1").alias("n")))
_agg("ag_multi_distinct", T + "SELECT count(DISTINCT api) AS apis, count(DISTINCT script_id) AS scripts, count(DISTINCT domain_id) AS domains FROM trace", lambda t, s, d: t.agg(*[F.count_distinct(c).alias(n) for c, n in (("api", "apis"), ("script_id", "scripts"), ("domain_id", "domains"))]))
_agg("ag_filter_clause", T + "SELECT ret, count(*) FILTER (api_id < 15) AS named, count(*) FILTER (api_id >= 15) AS generic FROM trace GROUP BY 1", lambda t, s, d: t.groupBy("ret").agg(F.count_if(F.col("api_id") < 15).alias("named"), F.count_if(F.col("api_id") >= 15).alias("generic")))
_agg("ag_bool_or_rules", T + "SELECT script_id, bool_or(api = 'toDataURL') AS reads, bool_and(n_calls > 10) AS busy FROM trace GROUP BY 1", lambda t, s, d: t.groupBy("script_id").agg(F.bool_or(F.col("api") == "toDataURL").alias("reads"), F.bool_and(F.col("n_calls") > 10).alias("busy")))
_agg("ag_rollup_rank_bucket", T + "SELECT ret, api_id % 5 AS g, count(*) AS n FROM trace GROUP BY ROLLUP (ret, api_id % 5)", lambda t, s, d: t.withColumn("g", F.col("api_id") % 5).rollup("ret", "g").agg(F.count("*").alias("n")))
_agg("ag_cube_grouping_id", T + "SELECT ret, api_id % 5 AS g, CAST(grouping_id(ret, api_id % 5) AS BIGINT) AS gid, count(*) AS n FROM trace GROUP BY CUBE (ret, api_id % 5)", lambda t, s, d: t.withColumn("g", F.col("api_id") % 5).cube("ret", "g").agg(F.grouping_id().alias("gid"), F.count("*").alias("n")))
_agg("ag_pivot_features", T + "SELECT script_id, CAST(sum(n_calls) FILTER (api = 'font') AS BIGINT) AS font, CAST(sum(n_calls) FILTER (api = 'save') AS BIGINT) AS save FROM trace GROUP BY 1", lambda t, s, d: t.groupBy("script_id").pivot("api", ["font", "save"]).agg(F.sum("n_calls").cast("long")))
_agg("ag_unpivot_features", "SELECT l_orderkey, l_linenumber, which, v FROM (SELECT l_orderkey, l_linenumber, l_discount, l_tax FROM lineitem) UNPIVOT (v FOR which IN (l_discount, l_tax))", lambda t, s, d: read(s, d, "lineitem").unpivot(["l_orderkey", "l_linenumber"], ["l_discount", "l_tax"], "which", "v"))
_agg("ag_min_by_content", "SELECT text, min(doc_id) AS doc_id, arg_min(source, doc_id) AS source FROM documents GROUP BY 1", lambda t, s, d: read(s, d, "documents").groupBy("text").agg(F.min("doc_id").alias("doc_id"), F.min_by("source", "doc_id").alias("source")))
_agg("ag_moments", T + "SELECT api, round(avg(n_calls), 6) AS mean, round(var_samp(n_calls), 6) AS var, round(kurtosis_pop(n_calls), 6) AS kurt FROM trace WHERE api_id < 15 GROUP BY 1", lambda t, s, d: r6(t.where("api_id < 15").groupBy("api").agg(F.avg("n_calls").alias("mean"), F.var_samp("n_calls").alias("var"), F.kurtosis("n_calls").alias("kurt")), "mean", "var", "kurt"))
_agg("ag_percentiles", T + "SELECT ret, round(quantile_cont(n_calls, 0.5), 6) AS p50, round(quantile_cont(n_calls, 0.9), 6) AS p90 FROM trace GROUP BY 1", lambda t, s, d: r6(t.groupBy("ret").agg(F.percentile("n_calls", F.lit(0.5)).alias("p50"), F.percentile("n_calls", F.lit(0.9)).alias("p90")), "p50", "p90"))
_agg("ag_mode_family", "SELECT c_nationkey, arg_max(c_mktsegment, n) AS mode FROM (SELECT c_nationkey, c_mktsegment, count(*) * 10 - any_value(ascii(c_mktsegment)) / 100.0 AS n FROM customer GROUP BY ALL) GROUP BY 1", lambda t, s, d: read(s, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg((F.count("*") * 10 - F.first(F.ascii("c_mktsegment")) / 100.0).alias("n")).groupBy("c_nationkey").agg(F.max_by("c_mktsegment", "n").alias("mode")))
_agg("ag_corr_features", "SELECT round(corr(l_discount, l_tax), 6) AS c1, round(corr(l_quantity, l_extendedprice), 6) AS c2 FROM lineitem", lambda t, s, d: r6(read(s, d, "lineitem").agg(F.corr("l_discount", "l_tax").alias("c1"), F.corr("l_quantity", "l_extendedprice").alias("c2")), "c1", "c2"))
_agg("ag_having_prevalence", LAB + "SELECT domain_id, CAST(sum(y) AS BIGINT) AS positives FROM (SELECT DISTINCT domain_id, script_id FROM trace) JOIN labelled USING (script_id) GROUP BY 1 HAVING sum(y) > 2", lambda t, s, d: participants.bridge(t).join(labels.apply(t), "script_id").groupBy("domain_id").agg(F.sum("y").cast("long").alias("positives")).where("positives > 2"))
_agg("ag_regr_slope_growth", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 6) AS slope FROM lineitem GROUP BY 1", lambda t, s, d: r6(read(s, d, "lineitem").groupBy("l_returnflag").agg(F.regr_slope("l_extendedprice", "l_quantity").alias("slope")), "slope"))
_agg("ag_map_counts", T + "SELECT script_id, CAST(coalesce(sum(n_calls) FILTER (api = 'font'), 0) AS BIGINT) AS font FROM trace GROUP BY 1", lambda t, s, d: features.call_counts(t).groupBy("script_id").agg(F.map_from_entries(F.collect_list(F.struct("api", "n"))).alias("m")).select("script_id", F.coalesce(F.try_element_at("m", F.lit("font")), F.lit(0)).alias("font")))
_agg("ag_bitmap_scripts", T + "SELECT count(DISTINCT script_id) AS scripts FROM trace", lambda t, s, d: t.select("script_id").distinct().groupBy(F.bitmap_bucket_number("script_id").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("script_id")).alias("m")).agg(F.sum(F.bitmap_count("m")).cast("long").alias("scripts")))
_agg("ag_array_sum_vectors", "SELECT label, i AS coord, round(sum(embedding[i + 1]), 3) AS total FROM embeddings, range(64) r(i) GROUP BY ALL", lambda t, s, d: read(s, d, "embeddings").select("label", F.posexplode("embedding").alias("coord", "v")).groupBy("label", "coord").agg(F.round(F.sum(F.col("v").cast("double")), 3).alias("total")).withColumn("coord", F.col("coord").cast("long")))


@query("ag_approx_distinct_fonts")
def ag_approx_distinct(spark: SparkSession, d: str) -> DataFrame:
    """HyperLogLog against the exact count; the standard error asked for is 2 %."""
    return order_trace(spark, d).groupBy("ret").agg(F.approx_count_distinct("script_id", 0.02).alias("approx"), F.count_distinct("script_id").alias("exact"))


@query("ag_sketch_union")
def ag_sketch_union(spark: SparkSession, d: str) -> DataFrame:
    """Sketches of parts, united: the whole's distinct count without its rows."""
    parts = order_trace(spark, d).groupBy("ret").agg(F.hll_sketch_agg("script_id", F.lit(14)).alias("s"))
    return parts.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("scripts"))


@query("ag_count_min_sketch")
def ag_count_min_sketch(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).agg(F.length(F.count_min_sketch(F.col("domain_id"), F.lit(0.01), F.lit(0.95), F.lit(7))).alias("bytes"))


@query("ag_histogram_numeric")
def ag_histogram_numeric(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).agg(F.histogram_numeric("n_calls", F.lit(10)).alias("h")).select(F.size("h").alias("bins"))


@query("ag_grouping_sets_crawl", HITS + "SELECT crawler, family, count(*) AS n FROM hits GROUP BY GROUPING SETS ((crawler, family), (family), ())")
def ag_grouping_sets_crawl(spark: SparkSession, d: str) -> DataFrame:
    crawl_hits(spark, d).createOrReplaceTempView("tf_hits")
    return spark.sql("SELECT crawler, family, count(*) AS n FROM tf_hits GROUP BY GROUPING SETS ((crawler, family), (family), ())")


# windows ----------------------------------------------------------------------------------------------------------------------------

_E = "FROM events"


def _events(name: str, sql: str, build) -> None:
    query(name, sql)(lambda spark, d: build(read(spark, d, "events")))


def _U():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_events("wn_row_number", f"SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n {_E}", lambda e: e.select("event_id", F.row_number().over(_U()).alias("n")))
_events("wn_rank", f"SELECT event_id, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS r, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr {_E}", lambda e: e.select("event_id", F.rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("r"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("dr")))
_events("wn_percent_rank", f"SELECT event_id, round(percent_rank() OVER (PARTITION BY user_id ORDER BY value), 6) AS p, round(cume_dist() OVER (PARTITION BY user_id ORDER BY value), 6) AS c {_E}", lambda e: e.select("event_id", F.round(F.percent_rank().over(Window.partitionBy("user_id").orderBy("value")), 6).alias("p"), F.round(F.cume_dist().over(Window.partitionBy("user_id").orderBy("value")), 6).alias("c")))
_events("wn_ntile_bins", f"SELECT event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b {_E}", lambda e: e.select("event_id", F.ntile(4).over(_U()).alias("b")))
_events("wn_lag_gap_session", f"SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap {_E}", lambda e: e.select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(_U()).cast("timestamp"))).alias("gap")))
_events("wn_lead_next_call", f"SELECT event_id, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next {_E}", lambda e: e.select("event_id", F.lead("event_type").over(_U()).alias("next")))
_events("wn_running_total", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS m {_E}", lambda e: e.select("event_id", F.count("*").over(_U().rowsBetween(Window.unboundedPreceding, 0)).alias("n"), F.max("value").over(_U().rowsBetween(Window.unboundedPreceding, 0)).alias("m")))
_events("wn_range_ties", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_type RANGE UNBOUNDED PRECEDING) AS n {_E}", lambda e: e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("event_type").rangeBetween(Window.unboundedPreceding, 0)).alias("n")))
_events("wn_moving_rounds", f"SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS m {_E}", lambda e: e.select("event_id", F.max("value").over(_U().rowsBetween(-4, 0)).alias("m")))
_events("wn_range_interval_1h", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n {_E}", lambda e: e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")))
_events("wn_first_last", f"SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l, nth_value(event_type, 2) OVER w AS s {_E} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", lambda e: e.select("event_id", *[f.over(_U().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for f, n in ((F.first("event_type"), "f"), (F.last("event_type"), "l"), (F.nth_value("event_type", 2), "s"))]))
_events("wn_cume_dist", f"SELECT event_id, round(cume_dist() OVER (PARTITION BY user_id ORDER BY event_type), 6) AS c {_E}", lambda e: e.select("event_id", F.round(F.cume_dist().over(Window.partitionBy("user_id").orderBy("event_type")), 6).alias("c")))
_events("wn_nth_value", f"SELECT event_id, nth_value(event_type, 3) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS third {_E}", lambda e: e.select("event_id", F.nth_value("event_type", 3).over(_U().rowsBetween(Window.unboundedPreceding, 0)).alias("third")))
_events("wn_dense_rank_importance", f"SELECT user_id, event_type, dense_rank() OVER (PARTITION BY user_id ORDER BY n DESC) AS rank FROM (SELECT user_id, event_type, count(*) AS n {_E} GROUP BY user_id, event_type)", lambda e: e.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).select("user_id", "event_type", F.dense_rank().over(Window.partitionBy("user_id").orderBy(F.desc("n"))).alias("rank")))
_events("wn_ratio_total", f"SELECT DISTINCT user_id, event_type, round(count(*) OVER (PARTITION BY user_id, event_type) / count(*) OVER (PARTITION BY user_id), 6) AS share {_E}", lambda e: r6(e.groupBy("user_id", "event_type").agg(F.count("*").alias("c")).select("user_id", "event_type", (F.col("c") / F.sum("c").over(Window.partitionBy("user_id"))).alias("share")), "share"))

# sorts, limits, sets ---------------------------------------------------------------------------------------------------------------


@query("so_multi_key_nulls", "SELECT doc_id FROM (SELECT doc_id, toxic FROM documents LEFT JOIN labels USING (doc_id)) ORDER BY toxic DESC NULLS LAST, doc_id")
def so_multi_key_nulls(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "documents").join(read(spark, d, "labels"), "doc_id", "left").orderBy(F.desc_nulls_last("toxic"), "doc_id").select("doc_id")


@query("so_topk_importance", T + "SELECT api, CAST(sum(n_calls) AS BIGINT) AS n FROM trace GROUP BY 1 ORDER BY n DESC, api LIMIT 20")
def so_topk_importance(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).groupBy("api").agg(F.sum("n_calls").cast("long").alias("n")).orderBy(F.desc("n"), "api").limit(20)


@query("so_topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def so_topk_per_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return read(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("so_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 50 OFFSET 100")
def so_limit_offset(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").orderBy("o_totalprice", "o_orderkey").offset(100).limit(50).select("o_orderkey")


@query("so_sort_within_partitions", "SELECT count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS s FROM orders")
def so_sort_within_partitions(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderdate").agg(F.count("*").alias("n"), F.sum("o_custkey").alias("s"))


@query("so_range_repartition", "SELECT count(*) AS n, max(o_totalprice) AS top FROM orders")
def so_range_repartition(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").repartitionByRange(4, "o_totalprice").agg(F.count("*").alias("n"), F.max("o_totalprice").alias("top"))


def _pair(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    o = read(spark, d, "orders")
    return o.where("o_totalprice > 200000").select("o_custkey"), o.where("o_orderpriority LIKE '1%'").select("o_custkey")


_A, _B = "SELECT o_custkey FROM orders WHERE o_totalprice > 200000", "SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%'"
for _n, _op, _f in (("union_distinct", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    query(f"st_{_n}", f"{_A} {_op} {_B}")(lambda spark, d, f=_f: f(*_pair(spark, d)))


@query("st_union_by_name_missing", "SELECT o_custkey, o_orderkey, NULL AS c_name FROM orders WHERE o_totalprice > 400000 UNION ALL SELECT c_custkey, NULL, c_name FROM customer WHERE c_acctbal > 9000")
def st_union_by_name_missing(spark: SparkSession, d: str) -> DataFrame:
    a = read(spark, d, "orders").where("o_totalprice > 400000").select("o_custkey", "o_orderkey")
    return a.unionByName(read(spark, d, "customer").where("c_acctbal > 9000").select(F.col("c_custkey").alias("o_custkey"), "c_name"), allowMissingColumns=True)


@query("st_symmetric_diff", f"({_A} EXCEPT {_B}) UNION ALL ({_B} EXCEPT {_A})")
def st_symmetric_diff(spark: SparkSession, d: str) -> DataFrame:
    a, b = _pair(spark, d)
    return a.subtract(b).unionAll(b.subtract(a))
