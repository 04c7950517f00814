"""Collection, features, labels, participants and scaling as queries, each with the same in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import carriers, catalogue, crawl, features, labels, noniid, participants, scaling
from ..carriers import SQL_TRACE, order_trace, read
from ..hashing import sql_normal, sql_uniform
from ..labels import SQL_EVIDENCE, SQL_FEATURES, SQL_LABELLED
from ..registry import query

WIDE = ("fillText", "toDataURL", "font", "measureText")


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n"


def r6(df: DataFrame, *columns: str) -> DataFrame:
    """Doubles that depend on the order of summation, rounded."""
    return df.withColumns({c: F.round(c, 6) for c in columns})


@query("f1_order_trace", with_(SQL_TRACE) + "SELECT script_id, domain_id, api, api_id, n_calls, ret, arg1, arg2 FROM trace")
def f1_order_trace(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).drop("ts")


@query("f1_raw_equals_compact", with_(SQL_TRACE) + "SELECT script_id, api, CAST(sum(n_calls) AS BIGINT) AS n FROM trace GROUP BY ALL")
def f1_raw_equals_compact(spark: SparkSession, d: str) -> DataFrame:
    return carriers.order_trace_raw(spark, d).groupBy("script_id", "api").agg(F.count("*").alias("n"))


SQL_SESSIONS = """ev AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) > 21600000000 THEN 1 ELSE 0 END AS new
  FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
sess AS (SELECT user_id AS participant_id, CAST(sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS script_no,
  event_type AS api, CAST(json_extract_string(props, '$.k') AS INT) AS arg, value AS ret, event_id FROM ev)"""


@query("f1_event_trace", with_(SQL_SESSIONS) + "SELECT * FROM sess")
def f1_event_trace(spark: SparkSession, d: str) -> DataFrame:
    return carriers.event_trace(spark, d).drop("ts")


@query("f1_document_trace", "WITH t AS (SELECT doc_id AS script_id, source AS domain, unnest(list_filter(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+'), lambda x: x <> '')) AS token FROM documents) SELECT script_id, domain, CAST('0x' || substr(md5(token), 1, 8) AS BIGINT) % 256 AS api_id, count(*) AS calls FROM t GROUP BY ALL")
def f1_document_trace(spark: SparkSession, d: str) -> DataFrame:
    return carriers.document_trace(spark, d).groupBy("script_id", "domain", "api_id").agg(F.count("*").alias("calls"))


@query("f1_page_trace", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, len(regexp_extract_all(html, '(?s)<script[^>]*>(.*?)</script>', 1)) AS scripts, length(array_to_string(regexp_extract_all(html, '(?s)<script[^>]*>(.*?)</script>', 1), '')) AS chars FROM pages WHERE len(regexp_extract_all(html, '(?s)<script[^>]*>(.*?)</script>', 1)) > 0")
def f1_page_trace(spark: SparkSession, d: str) -> DataFrame:
    return carriers.page_trace(spark, d).groupBy("page_id", "host").agg(F.count("*").alias("scripts"), F.sum(F.length("body")).alias("chars"))


@query("f2_unique_scripts", "SELECT sha256(text) AS content, min(doc_id) AS script_id, count(*) AS copies FROM documents GROUP BY 1")
def f2_unique_scripts(spark: SparkSession, d: str) -> DataFrame:
    return features.unique_scripts(read(spark, d, "documents"))


@query("f3_call_counts", with_(SQL_TRACE) + "SELECT script_id, api, CAST(sum(n_calls) AS BIGINT) AS n FROM trace GROUP BY ALL")
def f3_call_counts(spark: SparkSession, d: str) -> DataFrame:
    return features.call_counts(order_trace(spark, d))


@query("f3a_call_counts_wide", with_(SQL_TRACE) + "SELECT script_id, " + ", ".join(f"CAST(coalesce(sum(n_calls) FILTER (api = '{a}'), 0) AS BIGINT) AS \"n_{a}\"" for a in WIDE) + " FROM trace GROUP BY 1")
def f3a_call_counts_wide(spark: SparkSession, d: str) -> DataFrame:
    return features.call_counts_wide(order_trace(spark, d), WIDE)


@query("f3_features_long", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + "SELECT script_id, feature_id, v FROM feats")
def f3_features_long(spark: SparkSession, d: str) -> DataFrame:
    return features.features_long(order_trace(spark, d))


@query("f3b_packed", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + "SELECT script_id, list(feature_id ORDER BY feature_id) AS idx, list(v ORDER BY feature_id) AS val FROM feats GROUP BY 1")
def f3b_packed(spark: SparkSession, d: str) -> DataFrame:
    return features.pack(features.features_long(order_trace(spark, d)))


@query(
    "f4_customs",
    with_(SQL_TRACE)
    + """SELECT script_id,
  CAST(max(CASE WHEN api = 'toDataURL' AND ret = 'RF' THEN 1 ELSE 0 END) AS BIGINT) AS returns_rf,
  CAST(max(CASE WHEN api = 'font' AND arg1 = 0.05 THEN 1 ELSE 0 END) AS BIGINT) AS arg_is,
  CAST(max(CASE WHEN api = 'fillStyle' AND regexp_matches(CAST(arg2 AS VARCHAR), '^0\\.0[1-4]') THEN 1 ELSE 0 END) AS BIGINT) AS arg_like,
  CAST(max(CASE WHEN api = 'font' THEN length(ret) END) AS BIGINT) AS arg_length,
  CAST(count(DISTINCT CASE WHEN api = 'measureText' THEN arg1 END) AS BIGINT) AS arg_distinct
FROM trace GROUP BY 1""",
)
def f4_customs(spark: SparkSession, d: str) -> DataFrame:
    c = features.Custom
    wanted = [c.returns("toDataURL", "RF"), c.arg("font", "arg1", 0.05), c.arg_kind("fillStyle", "arg2", r"^0\.0[1-4]"), c.arg_length("font", "ret"), c.arg_distinct("measureText", "arg1")]
    return features.customs(order_trace(spark, d), wanted).toDF("script_id", "returns_rf", "arg_is", "arg_like", "arg_length", "arg_distinct")


def seen(spark: SparkSession, d: str) -> DataFrame:
    """(feature_id): the features that scripts of the order trace show."""
    return features.features_long(order_trace(spark, d)).select("feature_id").distinct()


_SEEN_SQL = "(SELECT feature_id FROM feats)"


@query("f5_admissible", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + f"SELECT feature_id, api, kind, is_native FROM {catalogue.sql_values()} WHERE default_value IS NOT NULL AND feature_id IN {_SEEN_SQL}")
def f5_admissible(spark: SparkSession, d: str) -> DataFrame:
    """Of the features that the trace shows."""
    return features.admissible(catalogue.table(spark)).join(seen(spark, d), "feature_id", "left_semi").drop("default_value")


SETS = ("full", "lab", "extension", "native", "counts")
_SET_SQL = "(VALUES " + ", ".join(f"('{s}', {i})" for s in SETS for i in catalogue.feature_set(s)) + ") s(name, feature_id)"


def sets_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(s, i) for s in SETS for i in catalogue.feature_set(s)], "name string, feature_id int")


@query("f6_feature_sets", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + f"SELECT name, count(*) AS size, count(*) FILTER (kind = 'count') AS counts, round(count(*) / {catalogue.N_FEATURES}.0, 6) AS share FROM {_SET_SQL} JOIN {catalogue.sql_values()} USING (feature_id) WHERE feature_id IN {_SEEN_SQL} GROUP BY 1")
def f6_feature_sets(spark: SparkSession, d: str) -> DataFrame:
    """Of each set, the features that the trace shows."""
    j = sets_table(spark).join(F.broadcast(catalogue.table(spark)), "feature_id").join(seen(spark, d), "feature_id", "left_semi")
    return j.groupBy("name").agg(F.count("*").alias("size"), F.count_if(F.col("kind") == "count").alias("counts"), F.round(F.count("*") / catalogue.N_FEATURES, 6).alias("share"))


@query("f6a_set_algebra", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES, f"s AS (SELECT * FROM {_SET_SQL} WHERE feature_id IN {_SEEN_SQL})", "l AS (SELECT feature_id FROM s WHERE name = 'lab')", "e AS (SELECT feature_id FROM s WHERE name = 'extension')") + "SELECT 'both' AS op, count(*) AS n FROM (SELECT * FROM l INTERSECT SELECT * FROM e) UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM l UNION SELECT * FROM e) UNION ALL SELECT 'lab only', count(*) FROM (SELECT * FROM l EXCEPT SELECT * FROM e)")
def f6a_set_algebra(spark: SparkSession, d: str) -> DataFrame:
    """Of the features that the trace shows."""
    s = sets_table(spark).join(seen(spark, d), "feature_id", "left_semi")
    a, b = (s.where(F.col("name") == n).select("feature_id") for n in ("lab", "extension"))
    size = lambda op, x: x.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
    return size("both", a.intersect(b)).unionAll(size("either", a.union(b).distinct())).unionAll(size("lab only", a.exceptAll(b)))


@query("f7_static_features", "WITH t AS (SELECT doc_id AS script_id, list_filter(regexp_split_to_array(lower(text), '[^a-z0-9]+'), lambda w: w <> '') AS t FROM documents), g AS (SELECT script_id, unnest(CASE WHEN len(t) < 2 THEN [t[1]] ELSE list_transform(range(1, len(t)), lambda i: t[i] || ' ' || t[i + 1]) END) AS g FROM t WHERE len(t) > 0) SELECT script_id, CAST(CAST('0x' || substr(md5(g), 1, 8) AS BIGINT) % 256 AS INT) AS feature_id, CAST(count(*) AS DOUBLE) AS v FROM g GROUP BY ALL")
def f7_static_features(spark: SparkSession, d: str) -> DataFrame:
    from ..baselines import static_features

    return static_features(read(spark, d, "documents"))


@query("f8_extraction_cost", with_(SQL_TRACE) + f"SELECT CAST(sum(n_calls) AS BIGINT) AS calls FROM trace WHERE api_id IN ({', '.join(str(i) for i in catalogue.feature_set('native'))})")
def f8_extraction_cost(spark: SparkSession, d: str) -> DataFrame:
    return features.extraction_cost(order_trace(spark, d), catalogue.feature_set("native")).select("calls")


_LABELS = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED)


@query("g5_rule_labels", _LABELS + "SELECT script_id, canvas, canvas_font, webrtc, audio, y FROM labelled")
def g5_rule_labels(spark: SparkSession, d: str) -> DataFrame:
    return labels.apply(order_trace(spark, d))


for _f in labels.FAMILIES:  # one query for each family's rule

    @query(f"g_rule_{_f}", _LABELS + f"SELECT script_id FROM labelled WHERE {_f}")
    def _rule(spark: SparkSession, d: str, name: str = _f) -> DataFrame:
        return labels.apply(order_trace(spark, d)).where(name).select("script_id")


@query("g4_audio_strict", with_(SQL_TRACE, SQL_EVIDENCE) + "SELECT script_id FROM evidence WHERE audio_members >= 2")
def g4_audio_strict(spark: SparkSession, d: str) -> DataFrame:
    return labels.apply(order_trace(spark, d), strict=True).where("audio").select("script_id")


@query("g5_families", _LABELS + "SELECT script_id, array_to_string(list_filter([CASE WHEN canvas THEN 'canvas' END, CASE WHEN canvas_font THEN 'canvas_font' END, CASE WHEN webrtc THEN 'webrtc' END, CASE WHEN audio THEN 'audio' END], lambda x: x IS NOT NULL), ',') AS families FROM labelled WHERE y = 1")
def g5_families(spark: SparkSession, d: str) -> DataFrame:
    return labels.families(labels.apply(order_trace(spark, d)).where("y = 1")).select("script_id", F.array_join("families", ",").alias("families"))


@query("g6_sweep", with_(SQL_TRACE, SQL_EVIDENCE) + "SELECT cut, count(script_id) AS scripts FROM (VALUES (5), (10), (20), (30), (40)) g(cut) LEFT JOIN evidence ON fonts > cut AND n_measureText > cut GROUP BY 1")
def g6_sweep(spark: SparkSession, d: str) -> DataFrame:
    return labels.sweep(order_trace(spark, d), spark.createDataFrame([(c,) for c in (5, 10, 20, 30, 40)], "cut int"))


@query("g7_prevalence", _LABELS + "SELECT count(*) AS scripts, CAST(sum(y) AS BIGINT) AS positives, " + ", ".join(f"count(*) FILTER ({f}) AS {f}" for f in labels.FAMILIES) + " FROM labelled")
def g7_prevalence(spark: SparkSession, d: str) -> DataFrame:
    return labels.prevalence(labels.apply(order_trace(spark, d)))


def _ranked_split(frac: float) -> str:
    u = sql_uniform("'split'", "script_id")
    return f"""split AS (SELECT script_id, y, CASE WHEN row_number() OVER (PARTITION BY y ORDER BY {u}, script_id) <= ceil(count(*) OVER (PARTITION BY y) * {frac}) THEN 'test' ELSE 'train' END AS part FROM labelled)"""


SQL_SPLIT = _ranked_split(0.2)


def labelled_split(spark: SparkSession, d: str) -> DataFrame:
    return participants.split(labels.apply(order_trace(spark, d)))


@query("p1_split_stratified", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT) + "SELECT script_id, y, part FROM split")
def p1_split_stratified(spark: SparkSession, d: str) -> DataFrame:
    return labelled_split(spark, d)


@query("p1_split_plain", _LABELS + f"SELECT script_id, y, CASE WHEN {sql_uniform(repr('split'), 'script_id')} < 0.2 THEN 'test' ELSE 'train' END AS part FROM labelled")
def p1_split_plain(spark: SparkSession, d: str) -> DataFrame:
    return participants.split(labels.apply(order_trace(spark, d)), stratify=False)


SQL_SITES = "sites AS (SELECT *, CAST(pow(10, ceil(log10(rank))) AS BIGINT) AS rank_bucket FROM (SELECT domain_id, n_scripts, row_number() OVER (ORDER BY n_scripts DESC, domain_id) AS rank FROM (SELECT domain_id, count(DISTINCT script_id) AS n_scripts FROM trace GROUP BY 1)))"
SQL_ZIPF = "cdf AS (SELECT domain_id, rank, m / total AS mass, (c - m) / total AS lo, c / total AS hi FROM (SELECT domain_id, rank, pow(rank, -1.0) AS m, sum(pow(rank, -1.0)) OVER (ORDER BY rank) AS c, sum(pow(rank, -1.0)) OVER () AS total FROM sites))"


@query("p2_sites", with_(SQL_TRACE, SQL_SITES) + "SELECT domain_id, n_scripts, rank, rank_bucket FROM sites")
def p2_sites(spark: SparkSession, d: str) -> DataFrame:
    return participants.sites(order_trace(spark, d))


@query("p3_crawl_frame", with_(SQL_TRACE, SQL_SITES) + f"SELECT domain_id, rank, 'top' AS stratum FROM sites WHERE rank <= 100 UNION ALL (SELECT domain_id, rank, 'tail' FROM sites WHERE rank > 100 AND rank <= 400 ORDER BY {sql_uniform(repr('frame'), 'domain_id')}, domain_id LIMIT 100)")
def p3_crawl_frame(spark: SparkSession, d: str) -> DataFrame:
    return participants.crawl_frame(participants.sites(order_trace(spark, d)), 100, 100, 100, 400).select("domain_id", "rank", "stratum")


@query("p4_zipf", with_(SQL_TRACE, SQL_SITES, SQL_ZIPF) + "SELECT domain_id, rank, round(mass, 6) AS mass, round(lo, 6) AS lo, round(hi, 6) AS hi FROM cdf")
def p4_zipf(spark: SparkSession, d: str) -> DataFrame:
    return r6(participants.zipf(participants.sites(order_trace(spark, d))), "mass", "lo", "hi")


W, D = 200, 20
SQL_DRAW = f"draws AS (SELECT DISTINCT participant_id, domain_id FROM (SELECT participant_id, {sql_uniform(repr('draw'), 'participant_id', 'i')} AS u FROM (SELECT range AS participant_id FROM range({W})), (SELECT range AS i FROM range(1, {D + 1}))) JOIN cdf ON u >= lo AND u < hi)"


def draws(spark: SparkSession, d: str, w: int = W, urls: int = D) -> DataFrame:
    return participants.draw(participants.people(spark, w), participants.zipf(participants.sites(order_trace(spark, d))), urls)


@query("p5_draw", with_(SQL_TRACE, SQL_SITES, SQL_ZIPF, SQL_DRAW) + "SELECT participant_id, domain_id FROM draws")
def p5_draw(spark: SparkSession, d: str) -> DataFrame:
    return draws(spark, d)


@query("p5_draw_without_replacement")
def p5_draw_without_replacement(spark: SparkSession, d: str) -> DataFrame:
    return participants.draw_without(participants.people(spark, 50), participants.zipf(participants.sites(order_trace(spark, d))), D)


SQL_SHARD = "shard AS (SELECT DISTINCT participant_id, script_id FROM draws JOIN (SELECT DISTINCT domain_id, script_id FROM trace) USING (domain_id) JOIN split USING (script_id) WHERE part = 'train')"
_SHARDED = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT, SQL_SITES, SQL_ZIPF, SQL_DRAW, SQL_SHARD)


def virtual_shards(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return participants.shards(draws(spark, d), participants.bridge(trace), labelled_split(spark, d).where("part = 'train'"))


@query("p6_shards", _SHARDED + "SELECT participant_id, script_id FROM shard")
def p6_shards(spark: SparkSession, d: str) -> DataFrame:
    return virtual_shards(spark, d)


SQL_NATURAL = "shard AS (SELECT o_custkey AS participant_id, o_orderkey AS script_id FROM orders JOIN split ON script_id = o_orderkey WHERE part = 'train')"


@query("p6a_natural_shards", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT, SQL_NATURAL) + "SELECT participant_id, script_id FROM shard")
def p6a_natural_shards(spark: SparkSession, d: str) -> DataFrame:
    return participants.natural(read(spark, d, "orders"), labelled_split(spark, d).where("part = 'train'"))


@query("p7_poisson_cohort", f"SELECT range AS participant_id FROM range(10000) WHERE {sql_uniform(repr('cohort'), '3', 'range')} < 0.01")
def p7_poisson_cohort(spark: SparkSession, d: str) -> DataFrame:
    return participants.cohort(participants.people(spark, 10_000), 0.01, 3)


@query("p7a_fixed_cohort", f"SELECT range AS participant_id FROM range(10000) ORDER BY {sql_uniform(repr('cohort'), '3', 'range')}, range LIMIT 100")
def p7a_fixed_cohort(spark: SparkSession, d: str) -> DataFrame:
    return participants.cohort_fixed(participants.people(spark, 10_000), 100, 3)


@query("p7b_full_participation", "SELECT range AS participant_id FROM range(1000)")
def p7b_full_participation(spark: SparkSession, d: str) -> DataFrame:
    return participants.cohort(participants.people(spark, 1000), 1.0, 1)


@query("p8_limited", _SHARDED + f"""SELECT participant_id, script_id FROM shard JOIN labelled USING (script_id) WHERE NOT ({sql_uniform(repr('limited'), 'participant_id')} < 0.5 AND (
  {' OR '.join(f"({f} AND CAST(floor({sql_uniform(repr('limited-family'), 'participant_id')} * 4) AS INT) <> {i})" for i, f in enumerate(labels.FAMILIES))}))""")
def p8_limited(spark: SparkSession, d: str) -> DataFrame:
    return participants.limit_knowledge(virtual_shards(spark, d), labels.apply(order_trace(spark, d)), 0.5)


@query("p9_describe", _SHARDED + "SELECT count(*) AS participants, min(n) AS least, max(n) AS most, CAST(sum(n) AS BIGINT) AS rows, CAST(sum(p) AS BIGINT) AS positives, count(*) FILTER (p = 0) AS without_positives FROM (SELECT participant_id, count(*) AS n, sum(y) AS p FROM shard JOIN labelled USING (script_id) GROUP BY 1)")
def p9_describe(spark: SparkSession, d: str) -> DataFrame:
    return participants.describe(virtual_shards(spark, d), labels.apply(order_trace(spark, d)))


# scaling ------------------------------------------------------------------------------------------------------------------------

_CAT_SQL = catalogue.sql_values()
SQL_LOCAL = """rows_of AS (SELECT participant_id, count(*) AS n FROM shard GROUP BY 1),
local AS (SELECT participant_id, feature_id, n, s1, s2 FROM (SELECT participant_id, feature_id, sum(v) AS s1, sum(v * v) AS s2 FROM shard JOIN feats USING (script_id) GROUP BY 1, 2) JOIN rows_of USING (participant_id))"""
_MU, _VAR = "least(s1 / n, 4.0)", "least(CASE WHEN n > 1 THEN greatest((s2 - s1 * s1 / n) / (n - 1), 0.0) ELSE 0.0 END, 100.0)"
_NATURAL = (SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT, SQL_NATURAL, SQL_FEATURES, SQL_LOCAL)


def natural_case(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, int]:
    """(natural shards, long features, number of participants: all customers)."""
    return p6a_natural_shards(spark, d), features.features_long(order_trace(spark, d)), read(spark, d, "customer").count()


@query("n1_local_mean", with_(*_NATURAL) + f"SELECT participant_id, feature_id, round({_MU}, 6) AS mu FROM local")
def n1_local_mean(spark: SparkSession, d: str) -> DataFrame:
    shard, feats, w = natural_case(spark, d)
    return r6(scaling.local_stats(shard, feats, scaling.ScaleConfig(w)), "mu").select("participant_id", "feature_id", "mu")


@query("n2_local_var", with_(*_NATURAL) + f"SELECT participant_id, feature_id, round({_VAR}, 6) AS var FROM local")
def n2_local_var(spark: SparkSession, d: str) -> DataFrame:
    shard, feats, w = natural_case(spark, d)
    return r6(scaling.local_stats(shard, feats, scaling.ScaleConfig(w)), "var").select("participant_id", "feature_id", "var")


def _fit_sql(q: float, z: float, pooling: str = "mean_of_local") -> str:
    second = _VAR if pooling == "mean_of_local" else "least(s2 / n, 100.0)"
    pick = lambda tag: f"FILTER ({sql_uniform(repr('scale'), repr(tag), 'feature_id', 'participant_id')} < {q})" if q < 1 else ""
    noise = lambda tag, cap: f" + {sql_normal(repr('scale'), repr('noise-' + tag), 'c.feature_id')} * ({cap} * {z} / qw)" if z else ""
    var = f"coalesce(b, 0.0) / qw{noise('var', 100.0)}"
    var = var if pooling == "mean_of_local" else f"{var} - pow(coalesce(a, 0.0) / qw{noise('mu', 4.0)}, 2)"
    return with_(*_NATURAL, f"sums AS (SELECT feature_id, sum({_MU}) {pick('mu')} AS a, sum({second}) {pick('var')} AS b FROM local GROUP BY 1), k AS (SELECT {q} * count(*) AS qw FROM customer)") + f"SELECT c.feature_id, round(coalesce(a, 0.0) / qw{noise('mu', 4.0)}, 6) AS mean, round({var}, 6) AS var FROM {_CAT_SQL} LEFT JOIN sums USING (feature_id), k"


def _fit(spark: SparkSession, d: str, **how) -> DataFrame:
    shard, feats, w = natural_case(spark, d)
    return r6(scaling.fit(shard, feats, catalogue.table(spark), scaling.ScaleConfig(w, noise="seeded", **how)), "mean", "var")


@query("n3_private_scaling", _fit_sql(0.5, 1.0))
def n3_private_scaling(spark: SparkSession, d: str) -> DataFrame:
    return _fit(spark, d, q=0.5, z=1.0)


@query("n5_scaling_without_noise", _fit_sql(1.0, 0.0))
def n5_scaling_without_noise(spark: SparkSession, d: str) -> DataFrame:
    return _fit(spark, d)


@query("n8_pooled_moments", _fit_sql(1.0, 0.0, "moments"))
def n8_pooled_moments(spark: SparkSession, d: str) -> DataFrame:
    return _fit(spark, d, pooling="moments")


SQL_GLOBAL = f"k AS (SELECT count(*) AS n FROM labelled), exact AS (SELECT c.feature_id, coalesce(s1, 0.0) / n AS mean, (coalesce(s2, 0.0) - coalesce(s1, 0.0) * coalesce(s1, 0.0) / n) / (n - 1) AS var FROM {_CAT_SQL} LEFT JOIN (SELECT feature_id, sum(v) AS s1, sum(v * v) AS s2 FROM feats GROUP BY 1) USING (feature_id), k)"
_GLOBAL = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_FEATURES, SQL_GLOBAL)


def exact_stats(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    n = trace.select("script_id").distinct().count()
    return scaling.global_stats(features.features_long(trace), catalogue.table(spark), n)


@query("n7_global_stats", _GLOBAL + "SELECT feature_id, round(mean, 6) AS mean, round(var, 6) AS var FROM exact")
def n7_global_stats(spark: SparkSession, d: str) -> DataFrame:
    return r6(exact_stats(spark, d), "mean", "var")


for _div in ("stddev", "variance"):
    _scale = "sqrt(greatest(var, 0.02))" if _div == "stddev" else "greatest(var, 0.02)"

    @query(f"n4_transform_{_div}", _GLOBAL + f"SELECT script_id, feature_id, round((v - mean) / {_scale}, 6) AS v FROM feats JOIN exact USING (feature_id)")
    def _transform(spark: SparkSession, d: str, how: str = _div) -> DataFrame:
        return r6(scaling.transform(features.features_long(order_trace(spark, d)), exact_stats(spark, d), scaling.ScaleConfig(1, divisor=how)), "v")


@query("n6_scaling_off", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + "SELECT script_id, feature_id, v FROM feats")
def n6_scaling_off(spark: SparkSession, d: str) -> DataFrame:
    feats = features.features_long(order_trace(spark, d))
    return scaling.transform(feats, feats, scaling.ScaleConfig(1, off=True))


@query("n10_scaling_error", with_(*_NATURAL, SQL_GLOBAL.replace("k AS", "kk AS").replace(", k)", ", kk)"), f"sums AS (SELECT feature_id, sum({_MU}) / (SELECT count(*) FROM customer) AS mean, sum({_VAR}) / (SELECT count(*) FROM customer) AS var FROM local GROUP BY 1)") + "SELECT round(avg(coalesce(p.mean, 0) - e.mean), 6) AS mean_bias, round(sqrt(avg(pow(coalesce(p.mean, 0) - e.mean, 2))), 6) AS mean_rmse, round(avg(coalesce(p.var, 0) - e.var), 6) AS var_bias, round(sqrt(avg(pow(coalesce(p.var, 0) - e.var, 2))), 6) AS var_rmse FROM exact e LEFT JOIN sums p USING (feature_id)")
def n10_scaling_error(spark: SparkSession, d: str) -> DataFrame:
    shard, feats, w = natural_case(spark, d)
    fitted = scaling.fit(shard, feats, catalogue.table(spark), scaling.ScaleConfig(w))
    return r6(scaling.error_report(fitted, exact_stats(spark, d)), "mean_bias", "mean_rmse", "var_bias", "var_rmse")


# crawl, distribution --------------------------------------------------------------------------------------------------------------

SQL_HITS = "hits AS (SELECT DISTINCT crawler, script_id, family FROM (SELECT DISTINCT domain_id, script_id FROM trace) JOIN labelled USING (script_id), (VALUES ('manual', 1.0), ('basic', 0.25), ('stealth', 0.2)) c(crawler, reach), (VALUES ('canvas'), ('canvas_font'), ('webrtc'), ('audio')) f(family) WHERE " + sql_uniform("'crawl'", "crawler", "script_id", "domain_id") + " < reach AND CASE family WHEN 'canvas' THEN canvas WHEN 'canvas_font' THEN canvas_font WHEN 'webrtc' THEN webrtc ELSE audio END)"
_HITS = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_HITS)


def crawl_hits(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return crawl.hits(participants.bridge(trace), labels.apply(trace))


@query("k11_crawl_coverage", _HITS + "SELECT crawler, family, count(DISTINCT script_id) AS scripts FROM hits GROUP BY GROUPING SETS ((crawler, family), (crawler))")
def k11_crawl_coverage(spark: SparkSession, d: str) -> DataFrame:
    return crawl.coverage(crawl_hits(spark, d))


@query("k12_coverage_lift", _HITS + "SELECT round((a - b) / b, 6) AS increase, round(a / b, 6) AS ratio FROM (SELECT count(DISTINCT script_id) FILTER (crawler = 'manual') AS a, count(DISTINCT script_id) FILTER (crawler = 'basic') AS b FROM hits)")
def k12_coverage_lift(spark: SparkSession, d: str) -> DataFrame:
    return r6(crawl.lift(crawl_hits(spark, d)), "increase", "ratio")


@query("k13_crawl_outcomes", with_(SQL_TRACE, f"v AS (SELECT {sql_uniform(repr('visit'), 'domain_id')} AS u FROM (SELECT DISTINCT domain_id FROM trace))") + "SELECT count(*) AS attempted, round(count(*) FILTER (u < 0.915) / count(*), 6) AS loaded, round(count(*) FILTER (u >= 0.915 AND u < 0.915 + 0.085 * 0.643) / greatest(count(*) FILTER (u >= 0.915), 1), 6) AS forbidden_share FROM v")
def k13_crawl_outcomes(spark: SparkSession, d: str) -> DataFrame:
    return r6(crawl.outcomes(crawl.visits(order_trace(spark, d).select("domain_id").distinct())), "loaded", "forbidden_share")


@query("k14_overhead", "WITH p AS (SELECT l_orderkey AS page_id, avg(1 - l_discount) AS base, avg(1 - l_discount - l_tax / 20) AS with_ext FROM lineitem GROUP BY 1) SELECT round(avg(base - with_ext), 6) AS mean_drop, round(max(base - with_ext), 6) AS max_drop FROM p")
def k14_overhead(spark: SparkSession, d: str) -> DataFrame:
    pages = read(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("page_id")).agg(F.avg(1 - F.col("l_discount")).alias("base"), F.avg(1 - F.col("l_discount") - F.col("l_tax") / 20).alias("with_ext"))
    return r6(crawl.overhead(pages), "mean_drop", "max_drop")


@query("e15_trend", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED) + "SELECT date_trunc('year', ts)::TIMESTAMP AS period, count(DISTINCT script_id) AS scripts, count(DISTINCT CASE WHEN y = 1 THEN script_id END) AS positives FROM trace JOIN labelled USING (script_id) GROUP BY 1")
def e15_trend(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return crawl.trend(labels.apply(trace), trace.select("script_id", "ts"))


_HISTOGRAM = "h AS (SELECT participant_id, family, c, c / sum(c) OVER (PARTITION BY participant_id) AS share FROM (SELECT participant_id, family, count(*) AS c FROM (SELECT participant_id, unnest(CASE WHEN y = 0 THEN ['none'] ELSE list_filter([CASE WHEN canvas THEN 'canvas' END, CASE WHEN canvas_font THEN 'canvas_font' END, CASE WHEN webrtc THEN 'webrtc' END, CASE WHEN audio THEN 'audio' END], lambda x: x IS NOT NULL) END) AS family FROM shard JOIN labelled USING (script_id)) GROUP BY 1, 2)), pooled AS (SELECT family, sum(c) / (SELECT sum(c) FROM h) AS pool FROM h GROUP BY 1)"
_DISTANCES = {"tv": "sum(abs(coalesce(share, 0) - pool)) / 2", "hellinger": "sqrt(sum(pow(sqrt(coalesce(share, 0)) - sqrt(pool), 2)) / 2)", "js": "sqrt(sum(CASE WHEN share > 0 THEN share * log2(share / ((share + pool) / 2)) ELSE 0 END + CASE WHEN pool > 0 THEN pool * log2(pool / ((coalesce(share, 0) + pool) / 2)) ELSE 0 END) / 2)"}
for _name, _d in _DISTANCES.items():

    @query(f"k8_noniid_{_name}", _SHARDED.rstrip() + f",\n{_HISTOGRAM} SELECT round(avg(d), 6) AS spread FROM (SELECT p.participant_id, {_d} AS d FROM (SELECT DISTINCT participant_id FROM h) p CROSS JOIN pooled LEFT JOIN h USING (participant_id, family) GROUP BY 1)")
    def _noniid(spark: SparkSession, d: str, how: str = _name) -> DataFrame:
        return r6(noniid.spread(virtual_shards(spark, d), labels.apply(order_trace(spark, d)), how), "spread")
