"""Training, accounting, baselines and measures as queries."""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import baselines, catalogue, experiments, features, federated, importance, labels, metrics, model, participants, privacy, secure_agg
from ..carriers import SQL_TRACE, order_trace, read
from ..hashing import sql_normal, sql_uniform
from ..labels import SQL_EVIDENCE, SQL_FEATURES, SQL_LABELLED
from ..registry import FLAGSHIP, query
from .core import _SET_SQL, SQL_NATURAL, SQL_SPLIT, natural_case, r6, seen, sets_table, with_

NF = catalogue.N_FEATURES


@contextmanager
def case_of(spark: SparkSession, d: str) -> Iterator[experiments.Case]:
    case = experiments.prepare(spark, d)
    try:
        yield case
    finally:
        case.done()


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)


@query(FLAGSHIP)
def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Traces, features, labels, private scaling, private rounds, scores of the test part."""
    with case_of(spark, d) as case:
        w, rounds = 2_000, 3
        cfg = experiments.base(w, rounds=rounds)
        z = privacy.BudgetPlan(10.0, NF, rounds, cfg.q).resolve()[0]
        ledger = privacy.Ledger(10.0)
        mean, scale = experiments.private_scale(case, w, cfg.q, z, ledger=ledger)
        run = federated.run_of(federated.replace(cfg, z=z), mean, scale)
        got = federated.train_many({"run": run}, {"run": participants.people(spark, w)}, experiments.virtual(case), case.train, ledger=ledger)
        return model.score_packed(case.test, got["run"].theta, mean, scale)


# rounds in DataFrame operations, checked against SQL ----------------------------------------------------------------------------------

_CASE = (SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT, SQL_NATURAL, SQL_FEATURES)
_THETA0 = f"theta0 AS (SELECT range - 1 AS coord, 0.0::DOUBLE AS w FROM range({NF + 1}))"


def theta0(spark: SparkSession) -> DataFrame:
    return spark.range(-1, NF).select(F.col("id").cast("int").alias("coord"), F.lit(0.0).alias("w"))


def gradient_rounds(spark: SparkSession, d: str, rounds: int, q: float, z: float, clip: float, w: int = 100) -> DataFrame:
    shard, feats, _ = natural_case(spark, d)
    lab, theta = labels.apply(order_trace(spark, d)), theta0(spark)
    for r in range(1, rounds + 1):
        theta = federated.gradient_round(shard, feats, lab, theta, w, q, z, clip, 0.1, r)
    return r6(theta, "w")


def _rounds_sql(rounds: int, q: float, z: float, clip: float, w: int = 100) -> str:
    ctes = [federated.sql_gradient_round(f"theta{r - 1}", f"theta{r}", w, q, z, clip, 0.1, r) for r in range(1, rounds + 1)]
    return with_(*_CASE, _THETA0, *ctes) + f"SELECT CAST(coord AS INT) AS coord, round(w, 6) AS w FROM theta{rounds}"


for _name, _args in {"a1f_private_round": (1, 0.5, 1.0, 0.5), "a2f_two_private_rounds": (2, 0.5, 1.0, 0.5), "a1f_round_without_noise": (1, 1.0, 0.0, 1e9)}.items():

    @query(_name, _rounds_sql(*_args))
    def _round(spark: SparkSession, d: str, args: tuple = _args) -> DataFrame:
        return gradient_rounds(spark, d, *args)


_DELTA = "upd AS (SELECT o_custkey AS participant_id, CAST(o_orderkey % 8 AS INT) AS coord, sum(o_totalprice) / 1e6 - 0.5 AS delta FROM orders GROUP BY 1, 2)"


def deltas(spark: SparkSession, d: str) -> DataFrame:
    """Updates of few coordinates for the placements: customers' sums of orders."""
    return read(spark, d, "orders").groupBy(F.col("o_custkey").alias("participant_id"), (F.col("o_orderkey") % 8).cast("int").alias("coord")).agg((F.sum("o_totalprice") / 1e6 - 0.5).alias("delta"))


@query("x1_central_noise", f"WITH {_DELTA} SELECT coord, round(sum(delta) / 100 + {sql_normal(repr('x1'), 'coord')} * 0.01, 6) AS total FROM upd GROUP BY coord")
def x1_central_noise(spark: SparkSession, d: str) -> DataFrame:
    from ..hashing import normal

    s = deltas(spark, d).groupBy("coord").agg((F.sum("delta") / 100).alias("t"))
    return r6(s.select("coord", (F.col("t") + normal("x1", F.col("coord")) * 0.01).alias("total")), "total")


@query("x2_local_noise", f"WITH {_DELTA} SELECT coord, round(sum(delta + {sql_normal(repr('x2'), 'participant_id', 'coord')}) / 100, 6) AS total FROM upd GROUP BY coord")
def x2_local_noise(spark: SparkSession, d: str) -> DataFrame:
    from ..hashing import normal

    return r6(deltas(spark, d).groupBy("coord").agg((F.sum(F.col("delta") + normal("x2", F.col("participant_id"), F.col("coord"))) / 100).alias("total")), "total")


@query("x3_masked_sum", "WITH upd AS (SELECT o_custkey AS participant_id, CAST(o_orderkey % 8 AS INT) AS coord, floor(round(sum(o_totalprice) * 100) / 100) / 1e6 - 0.5 AS delta FROM orders GROUP BY 1, 2) SELECT coord, sum(CAST(round(delta * 1048576.0) AS BIGINT)) / 1048576.0 AS total FROM upd GROUP BY coord")
def x3_masked_sum(spark: SparkSession, d: str) -> DataFrame:
    """All participants' masks, with partners in rings of some 64, cancel in the modular sum, bit for bit. Whole units of the price, so that no order of the sums shows."""
    whole = F.floor(F.round(F.sum("o_totalprice") * 100) / 100) / 1e6 - 0.5
    u = read(spark, d, "orders").groupBy(F.col("o_custkey").alias("participant_id"), (F.col("o_orderkey") % 8).cast("int").alias("coord")).agg(whole.alias("delta"))
    full = u.select("participant_id").distinct().crossJoin(u.select("coord").distinct()).join(u, ["participant_id", "coord"], "left").fillna(0.0, ["delta"])
    return secure_agg.unmask(secure_agg.mask(full, full, neighbours=3)).where(F.col("coord").isNotNull())


@query("u2_update_norms", f"WITH {_DELTA} SELECT round(avg(n), 6) AS mean_norm, round(max(n), 6) AS max_norm, count(*) FILTER (n > 1) AS clipped FROM (SELECT participant_id, sqrt(sum(delta * delta)) AS n FROM upd GROUP BY 1)")
def u2_update_norms(spark: SparkSession, d: str) -> DataFrame:
    n = deltas(spark, d).groupBy("participant_id").agg(F.sqrt(F.sum(F.col("delta") * F.col("delta"))).alias("n"))
    return r6(n.agg(F.avg("n").alias("mean_norm"), F.max("n").alias("max_norm"), F.count_if(F.col("n") > 1).alias("clipped")), "mean_norm", "max_norm")


# scores and measures --------------------------------------------------------------------------------------------------------------

#: A fixed model to check scores with: weights by hash, and an offset.
_W = f"w AS (SELECT range AS feature_id, ({sql_uniform(repr('model'), 'range')} - 0.4) / 4 AS w FROM range({NF}))"
_SCORED = with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_FEATURES, _W, "scores AS (SELECT l.script_id, y, round(1 / (1 + exp(-(coalesce(m, 0) - 1.5))), 4) AS score FROM labelled l LEFT JOIN (SELECT script_id, sum(v * w) AS m FROM feats JOIN w USING (feature_id) GROUP BY 1) USING (script_id))")


def fixed_scores(spark: SparkSession, d: str) -> DataFrame:
    from ..hashing import uniform

    trace = order_trace(spark, d)
    w = spark.range(NF).select(F.col("id").cast("int").alias("feature_id"), ((uniform("model", F.col("id")) - 0.4) / 4).alias("w"))
    return model.score(features.features_long(trace), labels.apply(trace), w, -1.5).withColumn("score", F.round("score", 4))


@query("m1_score", _SCORED + "SELECT script_id, y, score FROM scores")
def m1_score(spark: SparkSession, d: str) -> DataFrame:
    return fixed_scores(spark, d)


@query("m2_log_loss", _SCORED + "SELECT round(avg(-(y * ln(p) + (1 - y) * ln(1 - p))), 6) AS log_loss FROM (SELECT y, greatest(least(score, 1 - 1e-12), 1e-12) AS p FROM scores)")
def m2_log_loss(spark: SparkSession, d: str) -> DataFrame:
    return r6(model.log_loss(fixed_scores(spark, d)), "log_loss")


@query("m3_classify", _SCORED + "SELECT script_id, CAST(score >= 0.5 AS INT) AS predicted FROM scores")
def m3_classify(spark: SparkSession, d: str) -> DataFrame:
    return model.classify(fixed_scores(spark, d), 0.5).select("script_id", "predicted")


_CURVE = "curve AS (SELECT score, p, c, sum(p) OVER w AS tp, sum(c) OVER w AS n, sum(p) OVER () AS total FROM (SELECT score, sum(y) AS p, count(*) AS c FROM scores GROUP BY 1) WINDOW w AS (ORDER BY score DESC))"


@query("k1_auprc_step", _SCORED.rstrip() + f", {_CURVE} SELECT round(sum(p / total * tp / n), 6) AS auprc FROM curve")
def k1_auprc_step(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.auprc(fixed_scores(spark, d)), "auprc")


@query("k1a_auprc_trapezoid", _SCORED.rstrip() + f", {_CURVE} SELECT round(sum(p / total * (pr + coalesce(before, pr)) / 2), 6) AS auprc FROM (SELECT p, total, tp / n AS pr, lag(tp / n) OVER (ORDER BY score DESC) AS before FROM curve)")
def k1a_auprc_trapezoid(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.auprc(fixed_scores(spark, d), "trapezoid"), "auprc")


@query("k1a_auprc_binned", _SCORED.rstrip() + ", binned AS (SELECT floor(score * 100) / 100 AS score, y FROM scores), " + _CURVE.replace("FROM scores", "FROM binned") + " SELECT round(sum(p / total * tp / n), 6) AS auprc FROM curve")
def k1a_auprc_binned(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.auprc(fixed_scores(spark, d), "binned", bins=100), "auprc")


@query("k2_pr_curve", _SCORED.rstrip() + f", {_CURVE} SELECT score, CAST(tp AS BIGINT) AS tp, CAST(n AS BIGINT) AS n, round(tp / n, 6) AS precision, round(tp / total, 6) AS recall FROM curve")
def k2_pr_curve(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.pr_curve(fixed_scores(spark, d)).select("score", "tp", "n", "precision", "recall"), "precision", "recall")


@query("k3_at_threshold", _SCORED + "SELECT tp, fp, fn, tn, round(tp / greatest(tp + fp, 1), 6) AS precision, round(tp / greatest(tp + fn, 1), 6) AS recall, round(2 * tp / greatest(2 * tp + fp + fn, 1), 6) AS f1, round(fp / greatest(fp + tn, 1), 6) AS fpr FROM (SELECT count(*) FILTER (h AND y = 1) AS tp, count(*) FILTER (h AND y = 0) AS fp, count(*) FILTER (NOT h AND y = 1) AS fn, count(*) FILTER (NOT h AND y = 0) AS tn FROM (SELECT score >= 0.3 AS h, y FROM scores))")
def k3_at_threshold(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.at_threshold(fixed_scores(spark, d), 0.3), "precision", "recall", "f1", "fpr")


@query("k3_best_threshold", _SCORED.rstrip() + f", {_CURVE} SELECT min(score) AS threshold, round(max(tp / total), 6) AS recall FROM curve WHERE tp / n >= 0.05")
def k3_best_threshold(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.best_threshold(fixed_scores(spark, d), 0.05), "recall")


@query("k4_repeats", _SCORED.rstrip() + " SELECT y, round(avg(score), 6) AS mean, round(coalesce(stddev_samp(score), 0), 6) AS std, count(*) AS runs FROM scores GROUP BY 1")
def k4_repeats(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.repeats(fixed_scores(spark, d), ["y"], "score"), "mean", "std")


_CONTRAST = f"k AS (SELECT count(*) FILTER (y = 1) AS p, count(*) FILTER (y = 0) AS q FROM labelled), s AS (SELECT feature_id, sum(CASE WHEN y = 1 THEN v ELSE 0 END) AS a, sum(CASE WHEN y = 0 THEN v ELSE 0 END) AS b FROM feats JOIN labelled USING (script_id) GROUP BY 1), w AS (SELECT feature_id, coalesce(coalesce(a, 0) / nullif(p, 0), 0) - coalesce(coalesce(b, 0) / nullif(q, 0), 0) AS w FROM {catalogue.sql_values()} LEFT JOIN s USING (feature_id), k)"


@query("k7_importance", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_FEATURES, _CONTRAST) + "SELECT feature_id, round(abs(w), 6) AS weight, dense_rank() OVER (ORDER BY abs(w) DESC) AS rank FROM w")
def k7_importance(spark: SparkSession, d: str) -> DataFrame:
    """Of the linear model that weighs a feature by its mean over positive less that over negative scripts; sums of whole numbers, so ranks are exact."""
    trace = order_trace(spark, d)
    lab = labels.apply(trace).select("script_id", "y")
    total = lab.agg(F.count_if(F.col("y") == 1).alias("p"), F.count_if(F.col("y") == 0).alias("q"))
    part = lambda y: F.sum(F.when(F.col("y") == y, F.col("v")).otherwise(0.0))
    sums = features.features_long(trace).join(lab, "script_id").groupBy("feature_id").agg(part(1).alias("a"), part(0).alias("b"))
    mean = lambda s, n: F.coalesce(F.coalesce(s, F.lit(0.0)) / F.nullif(F.col(n), F.lit(0)), F.lit(0.0))
    theta = catalogue.table(spark).select("feature_id").join(sums, "feature_id", "left").crossJoin(F.broadcast(total)).select("feature_id", (mean(F.col("a"), "p") - mean(F.col("b"), "q")).alias("w"))
    return r6(importance.rank(theta), "weight")


@query("k7c_composition", f"WITH {_W} SELECT kind, count(*) AS features FROM (SELECT feature_id FROM w ORDER BY abs(w) DESC, feature_id LIMIT 40) JOIN {catalogue.sql_values()} USING (feature_id) GROUP BY 1")
def k7c_composition(spark: SparkSession, d: str) -> DataFrame:
    from ..hashing import uniform

    theta = spark.range(NF).select(F.col("id").cast("int").alias("feature_id"), ((uniform("model", F.col("id")) - 0.4) / 4).alias("w"))
    return importance.composition(theta.orderBy(F.desc(F.abs("w")), "feature_id").limit(40), catalogue.table(spark))


@query("k7b_knee", "WITH c AS (SELECT range * 20 AS k, 0.9 - 0.5 / (1 + range) AS auprc FROM range(6)) SELECT min(k) AS k, any_value(b) AS best FROM c, (SELECT max(auprc) AS b FROM c) WHERE auprc >= b - 0.05")
def k7b_knee(spark: SparkSession, d: str) -> DataFrame:
    return importance.knee(spark.range(6).select((F.col("id") * 20).alias("k"), (0.9 - 0.5 / (1 + F.col("id"))).alias("auprc")), 0.05)


_COUNTS = "counts AS (SELECT script_id, api, sum(n_calls) AS n FROM trace GROUP BY ALL)"


@query("e4_association", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, _COUNTS) + "SELECT api, CAST(sum(y) AS BIGINT) AS support, round(sum(y) * any_value(scripts) / (count(*) * any_value(pos)), 6) AS lift, round(CASE WHEN sum(y) > 0 THEN log2(sum(y) * any_value(scripts) / (count(*) * any_value(pos))) END, 6) AS pmi FROM counts JOIN labelled USING (script_id), (SELECT count(*) AS scripts, sum(y) AS pos FROM labelled) GROUP BY 1")
def e4_association(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return r6(importance.association(features.call_counts(trace), labels.apply(trace)), "lift", "pmi")


@query("e1_discover_apis", with_(SQL_TRACE) + "SELECT DISTINCT api FROM trace WHERE api NOT IN (SELECT 'generic_' || range FROM range(40)) AND api NOT IN ('fillText', 'font')")
def e1_discover_apis(spark: SparkSession, d: str) -> DataFrame:
    known = spark.range(40).select(F.concat(F.lit("generic_"), F.col("id").cast("string")).alias("api")).unionAll(spark.createDataFrame([("fillText",), ("font",)], "api string"))
    return features.discover_apis(order_trace(spark, d), known)


@query("e2_engine_availability", with_(SQL_TRACE) + "SELECT api_id % 2 AS engine, count(DISTINCT api) AS apis, CAST(sum(n_calls) AS BIGINT) AS calls FROM trace GROUP BY 1")
def e2_engine_availability(spark: SparkSession, d: str) -> DataFrame:
    return order_trace(spark, d).groupBy((F.col("api_id") % 2).alias("engine")).agg(F.count_distinct("api").alias("apis"), F.sum("n_calls").cast("long").alias("calls"))


_NATIVE_IDS = ", ".join(str(i) for i in catalogue.feature_set("native"))


@query("e3_evasion", with_(SQL_TRACE.replace("trace AS (", "trace0 AS (", 1), f"trace AS (SELECT * FROM trace0 WHERE NOT ({sql_uniform(repr('evade'), 'script_id')} < 0.5 AND api_id NOT IN ({_NATIVE_IDS})))", SQL_EVIDENCE, SQL_LABELLED) + "SELECT count(*) AS scripts, CAST(sum(y) AS BIGINT) AS positives FROM labelled")
def e3_evasion(spark: SparkSession, d: str) -> DataFrame:
    from ..hashing import uniform

    hidden = (uniform("evade", F.col("script_id")) < 0.5) & ~F.col("api_id").isin(*catalogue.feature_set("native"))
    return labels.apply(order_trace(spark, d).where(~hidden)).agg(F.count("*").alias("scripts"), F.sum("y").cast("long").alias("positives"))


@query("e5_api_entropy", with_(SQL_TRACE) + "SELECT api, round(sum(-p * log2(p)), 6) AS entropy FROM (SELECT api, sum(n_calls) / sum(sum(n_calls)) OVER (PARTITION BY api) AS p FROM trace GROUP BY api, ret) GROUP BY 1")
def e5_api_entropy(spark: SparkSession, d: str) -> DataFrame:
    return r6(metrics.api_entropy(order_trace(spark, d)), "entropy")


@query("e6_anonymity_sets", "SELECT n AS set_size, count(*) AS sets, CAST(sum(n) AS BIGINT) AS rows FROM (SELECT count(*) AS n FROM customer GROUP BY c_nationkey, c_mktsegment) GROUP BY 1")
def e6_anonymity_sets(spark: SparkSession, d: str) -> DataFrame:
    return metrics.anonymity_sets(read(spark, d, "customer"), ["c_nationkey", "c_mktsegment"])


@query("e16_unique_signatures", with_(SQL_TRACE, "sig AS (SELECT script_id, array_to_string(list_sort(list(DISTINCT api)), ',') AS s FROM trace GROUP BY 1)", "one AS (SELECT s FROM sig JOIN (SELECT DISTINCT domain_id, script_id FROM trace) USING (script_id) GROUP BY 1 HAVING count(DISTINCT domain_id) = 1)") + "SELECT count(DISTINCT script_id) AS scripts, count(DISTINCT s) AS signatures FROM sig JOIN one USING (s)")
def e16_unique_signatures(spark: SparkSession, d: str) -> DataFrame:
    trace = order_trace(spark, d)
    return metrics.unique_signatures(trace.select("script_id", "api").distinct(), participants.bridge(trace))


# accounting -----------------------------------------------------------------------------------------------------------------------


@query("q2_accountant")
def q2_accountant(spark: SparkSession, d: str) -> DataFrame:
    return rows(spark, [(float(w), z, round(e, 4)) for w, z, e in privacy.amplification_table(100, [10_000, 100_000, 1_000_000], [0.5, 0.7, 1.0], 100)], "participants double, z double, epsilon double")


@query("q3_calibrated_noise")
def q3_calibrated_noise(spark: SparkSession, d: str) -> DataFrame:
    return rows(spark, [(float(w), e, round(privacy.calibrate(e, 100 / w, 100), 4)) for w in (10_000, 100_000, 1_000_000) for e in (1.0, 5.0, 10.0, math.inf)], "participants double, epsilon double, z double")


@query("q1_composition")
def q1_composition(spark: SparkSession, d: str) -> DataFrame:
    return rows(spark, [(k, *privacy.basic(0.05, 1e-7, k), *privacy.advanced(0.05, 1e-7, k, 1e-6)) for k in (1, 10, 100, 1000)], "steps int, basic_eps double, basic_delta double, advanced_eps double, advanced_delta double")


@query("q5_budget_split")
def q5_budget_split(spark: SparkSession, d: str) -> DataFrame:
    return rows(spark, [(a, *(round(z, 4) for z in privacy.BudgetPlan(5.0, NF, 20, 1e-3, a).resolve())) for a in (0.05, 0.1, 0.25, 0.5)], "alpha double, z_scaling double, z_training double")


@query("q8_ledger")
def q8_ledger(spark: SparkSession, d: str) -> DataFrame:
    book = privacy.Ledger(10.0)
    book.charge("statistics", 1e-3, 1.0, 2 * NF)
    for r in range(5):
        book.charge(f"round {r + 1}", 1e-3, 1.0)
    return book.table(spark)


@query("q9_audit_lower_bound")
def q9_audit_lower_bound(spark: SparkSession, d: str) -> DataFrame:
    """A canary of the full clip against noise z: the bound must stay below the mechanism's epsilon."""
    rng = np.random.default_rng(7)
    out = [(z, privacy.audit_lower_bound(list(rng.normal(1, z, 4000)), list(rng.normal(0, z, 4000))), privacy.epsilon(1.0, z, 1)) for z in (0.5, 1.0, 2.0)]
    return rows(spark, out, "z double, lower_bound double, epsilon double")


def seen_sizes(spark: SparkSession, d: str) -> DataFrame:
    """(name, features): how many features of each set the trace shows."""
    return sets_table(spark).join(seen(spark, d), "feature_id", "left_semi").groupBy("name").agg(F.count("*").alias("features"))


@query("e9_noise_by_features")
def e9_noise_by_features(spark: SparkSession, d: str) -> DataFrame:
    """For each set, over the features of it that the trace shows."""
    sizes = {r["name"]: r["features"] for r in seen_sizes(spark, d).collect()}  # a row for each set
    return rows(spark, [(n, *privacy.features_tradeoff([f], 1.0, 20, 0.01)[0]) for n, f in sizes.items()], "name string, features long, z double")


@query("e14_footprint", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + f"SELECT name, f AS features, 8 * (f + 1) AS model_bytes, 8 * (f + 1) AS update_bytes, 1600 * (f + 1) AS round_bytes FROM (SELECT name, count(*) AS f FROM {_SET_SQL} WHERE feature_id IN (SELECT feature_id FROM feats) GROUP BY 1)")
def e14_footprint(spark: SparkSession, d: str) -> DataFrame:
    """Of a model over the features of each set that the trace shows."""
    return seen_sizes(spark, d).select("name", "features", *[c.alias(n) for n, c in metrics.footprint(F.col("features")).items()])


@query("e10_discrete_gaussian")
def e10_discrete_gaussian(spark: SparkSession, d: str) -> DataFrame:
    """Each event's count of one, released with noise: mean and deviation of the error. Noise is drawn for 4,096 ids at once, from the chunk's number."""

    def release(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        rng = np.random.default_rng(zlib.crc32(f"discrete|{key[0].as_py()}".encode()))
        errors = [secure_agg.discrete_gaussian(s, len(table), rng) for s in sigmas]
        return pa.table({"sigma": pa.array(sigmas), "n": pa.array([len(table)] * len(sigmas), pa.int64()), "s1": pa.array([int(x.sum()) for x in errors], pa.int64()), "s2": pa.array([int((x * x).sum()) for x in errors], pa.int64())})

    sigmas = [0.7, 2.0, 10.0]
    chunks = read(spark, d, "events").select(F.floor(F.col("event_id") / 4096).alias("chunk"), F.lit(1).alias("count"))
    sums = chunks.groupBy("chunk").applyInArrow(release, "sigma double, n long, s1 long, s2 long").groupBy("sigma").agg(*[F.sum(c).alias(c) for c in ("n", "s1", "s2")])
    mean = F.col("s1") / F.col("n")
    return sums.select("sigma", mean.alias("mean"), F.sqrt(F.col("s2") / F.col("n") - mean * mean).alias("std"))


# baselines ------------------------------------------------------------------------------------------------------------------------


@query("b5_rules_only", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED) + "SELECT count(*) FILTER (y = 1 AND t = 1) AS tp, count(*) FILTER (y = 1 AND t = 0) AS fp, count(*) FILTER (y = 0 AND t = 1) AS fn FROM (SELECT y, CAST(canvas OR webrtc AS INT) AS t FROM labelled)")
def b5_rules_only(spark: SparkSession, d: str) -> DataFrame:
    lab = labels.apply(order_trace(spark, d))
    return baselines.rules_only(lab, lab.select("script_id", (F.col("canvas") | F.col("webrtc")).cast("int").alias("truth")))


@query("b6_blocklist", r"WITH d AS (SELECT doc_id, array_to_string(list_filter(regexp_split_to_array(text, '\s+'), lambda w: w <> ''), ' ') AS t FROM documents), k AS (SELECT item_id, array_to_string(list_filter(regexp_split_to_array(text, '\s+'), lambda w: w <> ''), ' ') AS p FROM benchmark) SELECT DISTINCT doc_id, item_id FROM d, k WHERE p <> '' AND contains(' ' || t || ' ', ' ' || p || ' ')")
def b6_blocklist(spark: SparkSession, d: str) -> DataFrame:
    return baselines.blocklist(read(spark, d, "documents"), read(spark, d, "benchmark"))


@query("b8_tree_histogram", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED, SQL_SPLIT, SQL_NATURAL, SQL_FEATURES, "r AS (SELECT script_id, y FROM shard JOIN labelled USING (script_id))", "t AS (SELECT count(*) AS n, sum(y) AS p FROM r)", "a AS (SELECT feature_id, edge, count(*) AS rn, sum(y) AS rp FROM r JOIN feats USING (script_id), (VALUES (0.5), (5.0), (20.0), (60.0)) e(edge) WHERE v > edge GROUP BY 1, 2)") + "SELECT feature_id, CAST(edge AS DOUBLE) AS edge, round(2 * (p / n) * (1 - p / n) - rn / n * (2 * (rp / rn) * (1 - rp / rn)) - (n - rn) / n * CASE WHEN n > rn THEN 2 * ((p - rp) / (n - rn)) * (1 - (p - rp) / (n - rn)) ELSE 0 END, 6) AS gain FROM a, t")
def b8_tree_histogram(spark: SparkSession, d: str) -> DataFrame:
    shard, feats, _ = natural_case(spark, d)
    return r6(baselines.fed_tree_histogram(shard, feats, labels.apply(order_trace(spark, d))), "gain")


@query("b12_prior_scorer", with_(SQL_TRACE, SQL_EVIDENCE, SQL_LABELLED) + f"SELECT script_id, y, {sql_uniform(repr('prior'), 'script_id')} AS score FROM labelled")
def b12_prior_scorer(spark: SparkSession, d: str) -> DataFrame:
    return baselines.prior_scorer(labels.apply(order_trace(spark, d)))


def _area(spark: SparkSession, name: str, scored: DataFrame) -> tuple[str, float]:
    return name, float(metrics.auprc(scored).first()["auprc"])


@query("b1_b2_b3_headline")
def headline(spark: SparkSession, d: str) -> DataFrame:
    """Centralised, local-only, federated without noise, averaged models and a first-order optimiser, by area."""
    with case_of(spark, d) as case:
        central = baselines.centralised(case.train, NF, case.mean, case.scale, iters=15)
        out = [_area(spark, "centralised", model.score_packed(case.test, central, case.mean, case.scale))]
        few = participants.people(spark, 5).withColumn("run", F.lit("r"))
        own = baselines.local_only(experiments.virtual(case)(few).select("participant_id", "script_id"), case.train, case.test, experiments.base(5), case.mean, case.scale)
        out.append(("local only", float(metrics.auprc(own, keys=("participant_id",)).agg(F.avg("auprc")).first()[0])))
        base = experiments.base(10_000, rounds=4)
        kinds = {"federated": base, "averaged": federated.replace(base, clip=math.inf, denominator="realised"), "by rows": federated.replace(base, clip=math.inf, weights="rows"), "first order": federated.replace(base, optimiser="gradient"), "sgd": federated.replace(base, optimiser="sgd")}
        out += experiments.sweep(case, {n: federated.run_of(c, case.mean, case.scale) for n, c in kinds.items()}).items()
        return rows(spark, [(n, round(a, 6)) for n, a in out], "method string, auprc double")


@query("b7_library_models")
def b7_library_models(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    with case_of(spark, d) as case:
        train, models = baselines.library_models(case.train, NF)
        test, _ = baselines.library_models(case.test, NF)
        out = []
        for n, m in models.items():
            s = m.fit(train).transform(test)
            raw = vector_to_array("rawPrediction")[1] if n == "svm" else vector_to_array("probability")[1]
            out.append(_area(spark, n, s.select("script_id", F.col("label").cast("int").alias("y"), (model.sigmoid(raw) if n == "svm" else raw).alias("score"))))
        return rows(spark, out, "method string, auprc double")


@query("a2f_training_history")
def a2f_training_history(spark: SparkSession, d: str) -> DataFrame:
    """Rounds of one private run, with the budget spent so far."""
    with case_of(spark, d) as case:
        cfg = federated.replace(experiments.base(10_000, rounds=4), z=1.0)
        got = federated.train(participants.people(spark, cfg.participants), experiments.virtual(case), case.train, cfg, case.mean, case.scale)
        return rows(spark, [(h["round"], h["cohort"], h["clipped_share"], h["mean_norm"], h["moved"], privacy.epsilon(cfg.q, cfg.z, h["round"])) for h in got.history], "round int, cohort int, clipped_share double, mean_norm double, moved double, epsilon double")


@query("x4_placements_and_units")
def x4_placements_and_units(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        b = federated.replace(experiments.base(10_000, rounds=3), z=1.0)
        kinds = {"central": b, "local": federated.replace(b, placement="local"), "record": federated.replace(b, unit="record", epochs=3), "final clip": federated.replace(b, clip_when="final", epochs=2), "two epochs": federated.replace(b, epochs=2)}
        got = experiments.sweep(case, {n: federated.run_of(c, case.mean, case.scale) for n, c in kinds.items()})
        return rows(spark, list(got.items()), "kind string, auprc double")


# experiments ----------------------------------------------------------------------------------------------------------------------


@query("w3_participants")
def w3_participants(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, experiments.by_participants(case), "feature_set string, participants double, seed int, auprc double")


@query("w4_budget")
def w4_budget(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, experiments.by_budget(case, rounds=4), "feature_set string, participants double, epsilon double, z double, seed int, auprc double")


@query("w5_sets")
def w5_sets(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        out = experiments.by_budget(case, (1_000_000,), rounds=3, sets=("full", "lab", "extension", "native"))
        return rows(spark, out, "feature_set string, participants double, epsilon double, z double, seed int, auprc double")


def _pool(case: experiments.Case) -> np.ndarray:
    return baselines.centralised(case.train, NF, case.mean, case.scale, iters=10)


@query("w6_growth_counts")
def w6_growth_counts(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        order = [i for i in importance.order(_pool(case)) if i < catalogue.N_COUNTS]
        return rows(spark, experiments.by_growth(case, order, 20, 80, rounds=3), "k int, auprc double")


@query("w7_growth_all")
def w7_growth_all(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, experiments.by_growth(case, importance.order(_pool(case)), 20, 100, rounds=3), "k int, auprc double")


@query("w8_compact")
def w8_compact(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        sets = {"full": catalogue.feature_set("full"), "compact": catalogue.feature_set("compact", importance.order(_pool(case))), "native": catalogue.feature_set("native")}
        got = experiments.sweep(case, {n: federated.run_of(experiments.base(100_000, rounds=4), case.mean, case.scale, ids) for n, ids in sets.items()})
        return rows(spark, [(n, len(sets[n]), a) for n, a in got.items()], "feature_set string, size int, auprc double")


@query("w9_scaling")
def w9_scaling(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, experiments.by_scaling(case, rounds=4), "feature_set string, scaling string, auprc double")


@query("w10_limited")
def w10_limited(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, experiments.by_limited(case, rounds=3), "share double, seed int, unlikeness double, auprc double")


@query("w17_poisoning")
def w17_poisoning(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        out = [(f, s, *experiments.poison(case, f, s, w=100).values()) for f in (1.0, 10.0) for s in (0.05, 0.2)]
        return rows(spark, out, "factor double, share double, free double, clipped double, bound double")


@query("w14_independent_truth")
def w14_independent_truth(spark: SparkSession, d: str) -> DataFrame:
    """Documents' own labels as truth, words' shapes as calls, sources as participants: no rule takes part."""
    docs = read(spark, d, "documents")
    feats = features.pack(baselines.shape_features(docs, 256))
    lab = read(spark, d, "labels").select(F.col("doc_id").alias("script_id"), (1 - F.col("quality")).alias("y"))
    parts = participants.split(lab)
    packed = feats.join(parts, "script_id")
    train, test = (packed.where(F.col("part") == p).drop("part").cache() for p in ("train", "test"))
    long = train.select("script_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).select(F.col("p.idx").alias("feature_id"), F.col("p.val").alias("v"))
    n = train.count()
    stats = long.groupBy("feature_id").agg((F.sum("v") / n).alias("mean"), ((F.sum(F.col("v") * F.col("v")) - F.sum("v") * F.sum("v") / n) / (n - 1)).alias("var")).collect()
    mean, scale = federated.scale_vectors(stats, 256)
    people = docs.select(F.pmod(F.xxhash64("source"), F.lit(1 << 40)).alias("participant_id"), F.col("doc_id").alias("script_id"))
    cfg = federated.TrainConfig(256, 20, rounds=4, q=1.0, l2=1e-2)
    out = []
    for name, z in (("no noise", 0.0), ("noise 1", 1.0)):
        got = federated.train(people.select("participant_id").distinct(), lambda g: g.join(people, "participant_id").select("run", "participant_id", "script_id"), train, federated.replace(cfg, z=z), mean, scale)
        out.append(_area(spark, name, model.score_packed(test, got.theta, mean, scale)))
    prior = test.agg(F.avg("y")).first()[0]
    train.unpersist()
    test.unpersist()
    return rows(spark, [*out, ("prevalence", float(prior or 0.0))], "method string, auprc double")
