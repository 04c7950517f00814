"""Probes, ablations and measures that the text mentions beside its main experiments."""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import baselines, catalogue, experiments, features, federated, labels, metrics, model, optim, participants, privacy, scaling
from ..carriers import SQL_TRACE, order_trace, read
from ..hashing import sql_uniform, uniform
from ..labels import SQL_EVIDENCE, SQL_FEATURES
from ..registry import query
from .core import SQL_DRAW, SQL_SITES, SQL_ZIPF, draws, natural_case, r6, seen, with_
from .learning import NF, _SCORED, case_of, fixed_scores, rows


@query("w2_popularity", with_(SQL_TRACE, SQL_SITES, SQL_ZIPF, SQL_DRAW) + "SELECT rank, round(mass, 6) AS mass, count(participant_id) AS participants FROM cdf LEFT JOIN draws USING (domain_id) WHERE rank <= 100 GROUP BY ALL")
def w2_popularity(spark: SparkSession, d: str) -> DataFrame:
    """The mass of the hundred first domains beside the participants who drew them."""
    cdf = participants.zipf(participants.sites(order_trace(spark, d))).where("rank <= 100")
    return r6(cdf.join(draws(spark, d), "domain_id", "left").groupBy("rank", "mass").agg(F.count("participant_id").alias("participants")), "mass")


@query("w2_page_hosts", "SELECT host, n, row_number() OVER (ORDER BY n DESC, host) AS rank FROM (SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1)")
def w2_page_hosts(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    g = read(spark, d, "pages").groupBy(F.regexp_extract("url", r"^[a-z]+://([^/:]+)", 1).alias("host")).agg(F.count("*").alias("n"))
    return g.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "host")))


@query("k16_extra_detections", _SCORED + "SELECT count(*) FILTER (score >= 0.3 AND y = 0) AS extra, count(*) FILTER (y = 1) AS by_rules FROM scores")
def k16_extra_detections(spark: SparkSession, d: str) -> DataFrame:
    """Scripts that the model flags and the rules don't, beside those that the rules flag."""
    s = fixed_scores(spark, d)
    extra = s.where("score >= 0.3").join(s.where("y = 1").select("script_id"), "script_id", "left_anti").agg(F.count("*").alias("extra"))
    return extra.crossJoin(s.agg(F.count_if(F.col("y") == 1).alias("by_rules")))


@query("k5_k6_comparisons", "WITH g AS (SELECT avg(value) FILTER (event_type = 'view') AS a, coalesce(stddev_samp(value) FILTER (event_type = 'view'), 0) AS sa, avg(value) FILTER (event_type = 'purchase') AS b, coalesce(stddev_samp(value) FILTER (event_type = 'purchase'), 0) AS sb FROM events) SELECT 'within two deviations' AS measure, CAST(abs(b - a) <= 2 * greatest(sa, sb) AS DOUBLE) AS value FROM g UNION ALL SELECT 'relative gain in percent', round(100 * (b - a) / nullif(a, 0), 6) FROM g")
def k5_k6_comparisons(spark: SparkSession, d: str) -> DataFrame:
    """Values of purchases against those of views."""
    of = lambda f, kind: f(F.when(F.col("event_type") == kind, F.col("value")))
    a, sa, b, sb = read(spark, d, "events").agg(*[of(f, k) for k in ("view", "purchase") for f in (F.avg, F.stddev_samp)]).first()
    both = a is not None and b is not None
    out = [("within two deviations", float(metrics.within(b, sb or 0.0, a, sa or 0.0)) if both else None), ("relative gain in percent", round(metrics.relative(b, a), 6) if both and a else None)]
    return rows(spark, out, "measure string, value double")


@query("k10_feature_budget", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + f"SELECT kind, is_native, count(*) AS features, round(count(*) / {NF}.0, 6) AS share FROM {catalogue.sql_values()} WHERE feature_id IN (SELECT feature_id FROM feats) GROUP BY 1, 2")
def k10_feature_budget(spark: SparkSession, d: str) -> DataFrame:
    """Of the features that the trace shows."""
    return r6(catalogue.table(spark).join(seen(spark, d), "feature_id", "left_semi").groupBy("kind", "is_native").agg(F.count("*").alias("features"), (F.count("*") / NF).alias("share")), "share")


@query("k15_round_cost")
def k15_round_cost(spark: SparkSession, d: str) -> DataFrame:
    """Seconds, cohort and bytes of a round."""
    import time

    with case_of(spark, d) as case:
        out = []
        for w in (1_000, 100_000):
            start = time.time()
            got = federated.train(participants.people(spark, w), experiments.virtual(case), case.train, experiments.base(w, rounds=2), case.mean, case.scale)
            cohort = got.history[-1]["cohort"]
            out.append((w, cohort, (time.time() - start) / 2, metrics.footprint(NF, cohort)["round_bytes"]))
        return rows(spark, out, "participants int, cohort int, seconds double, bytes long")


@query("n9_suggested_caps", with_(SQL_TRACE, SQL_EVIDENCE, SQL_FEATURES) + f"SELECT feature_id >= {catalogue.FIRST_FLAG} AS flag, quantile_disc(v, 0.95) AS cap FROM feats GROUP BY 1")
def n9_suggested_caps(spark: SparkSession, d: str) -> DataFrame:
    """Caps from exact quantiles by kind of feature: not private, for comparison with the caps that need no data."""
    return features.features_long(order_trace(spark, d)).groupBy((F.col("feature_id") >= catalogue.FIRST_FLAG).alias("flag")).agg(F.expr("percentile_disc(0.95) WITHIN GROUP (ORDER BY v)").alias("cap"))


@query("n8_clip_both_sides", "SELECT label, round(avg(greatest(least(m, 0.05), -0.05)), 6) AS mean FROM (SELECT label, vec_id, list_avg(embedding) AS m FROM embeddings) GROUP BY 1")
def n8_clip_both_sides(spark: SparkSession, d: str) -> DataFrame:
    """Signed statistics need both bounds: means of vectors, capped, averaged by label."""
    cfg = scaling.ScaleConfig(1, cap_mean=0.05, clip="both")
    m = read(spark, d, "embeddings").select("label", F.lit(0).alias("feature_id"), (F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")) / F.size("embedding")).alias("m"))
    return r6(m.groupBy("label").agg(F.avg(scaling._cap(F.col("m"), scaling._caps(cfg, "mu"), cfg.clip)).alias("mean")), "mean")


@query("q4_gaussian_release")
def q4_gaussian_release(spark: SparkSession, d: str) -> DataFrame:
    return rows(spark, [(e, privacy.gaussian_sigma(1.0, e, 1e-5)) for e in (0.1, 0.5, 1.0)], "epsilon double, sigma double")


@query("e7_font_probe", "SELECT o_custkey AS script_id, count(*) > 20 AS canvas_font FROM orders GROUP BY 1")
def e7_font_probe(spark: SparkSession, d: str) -> DataFrame:
    """The printed example's pattern with each customer as a script: one font set and one measurement for each order; 20 aren't flagged, 21 are."""
    font, measure = catalogue.NAMED.index("font"), catalogue.NAMED.index("measureText")
    n = read(spark, d, "orders").groupBy(F.col("o_custkey").alias("script_id")).agg(F.count("*").cast("int").alias("n_calls"))
    t = n.select("script_id", "n_calls", F.explode(F.array(*[F.struct(F.lit(a).alias("api"), F.lit(i).alias("api_id")) for a, i in (("font", font), ("measureText", measure))])).alias("x")).select("script_id", "n_calls", "x.*")
    return labels.apply(t).select("script_id", "canvas_font")


@query("e8_imbalance")
def e8_imbalance(spark: SparkSession, d: str) -> DataFrame:
    """Positives thinned or negatives thinned by hash to a prevalence; logistic regression against the linear machine."""
    from pyspark.ml.functions import vector_to_array

    with case_of(spark, d) as case:
        n = {r["y"]: r["count"] for r in case.train.groupBy("y").count().collect()}
        out = []
        for share in (0.57, 0.0041):
            keep_pos = min(1.0, share * n[0] / ((1 - share) * n[1]))
            keep_neg = min(1.0, (1 - share) * n[1] / (share * n[0]))
            u = uniform("imbalance", F.col("script_id"))
            thin = case.train.where(F.when(F.col("y") == 1, u < keep_pos).otherwise(u < keep_neg))
            fitted, kinds = baselines.library_models(thin, NF)
            test, _ = baselines.library_models(case.test, NF)
            for name in ("logistic", "svm"):
                kinds[name].setMaxIter(15)
                s = kinds[name].fit(fitted).transform(test)
                raw = vector_to_array("rawPrediction")[1]
                out.append((share, name, float(metrics.auprc(s.select("script_id", F.col("label").cast("int").alias("y"), model.sigmoid(raw).alias("score"))).first()[0])))
        return rows(spark, out, "prevalence double, method string, auprc double")


@query("w15_dense_parity")
def w15_dense_parity(spark: SparkSession, d: str) -> DataFrame:
    """Vectors, one label against the rest: our optimiser's loss against the library's on the same objective."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    v = read(spark, d, "embeddings").select(F.col("embedding").cast("array<double>").alias("e"), (F.col("label") == 0).cast("double").alias("label"))
    l2 = 0.01
    fitted = LogisticRegression(regParam=l2, standardization=False, maxIter=200, tol=1e-10).fit(v.select(array_to_vector("e").alias("features"), "label"))
    data = v.collect()  # a fixture of a few hundred vectors
    x, y = np.array([r["e"] for r in data]), np.array([r["label"] for r in data])
    fun = optim.logistic(x, y, l2)
    ours = optim.lbfgs(fun, np.zeros(x.shape[1] + 1), 10, 200)
    theirs = np.append(fitted.coefficients.toArray(), fitted.intercept)
    return rows(spark, [("ours", fun(ours)[0], 0.0), ("library", fun(theirs)[0], float(np.abs(ours - theirs).max()))], "optimiser string, loss double, largest_difference double")


def _membership(case: experiments.Case, z: float, targets: int = 40) -> float:
    """How well the loss of a participant's shard tells whether it took part (1/2: not at all)."""
    w = 2 * targets
    everyone = participants.people(case.spark, w).where("participant_id % 2 = 0")
    cfg = replace(experiments.base(w, rounds=2), q=1.0, z=z)
    theta = federated.train(everyone, experiments.virtual(case, 3), case.train, cfg, case.mean, case.scale).theta
    shard = experiments.virtual(case, 3)(participants.people(case.spark, w))
    s = model.score_packed(case.train, theta, case.mean, case.scale).join(shard, "script_id")
    p = F.greatest(F.least(F.col("score"), F.lit(1 - 1e-9)), F.lit(1e-9))
    loss = s.groupBy("participant_id").agg(F.avg(-(F.col("y") * F.ln(p) + (1 - F.col("y")) * F.ln(1 - p))).alias("loss")).collect()
    member, other = ([r["loss"] for r in loss if r["participant_id"] % 2 == k] for k in (0, 1))
    return float(np.mean([[(a < b) + 0.5 * (a == b) for b in other] for a in member]))


@query("e11_membership_probe")
def e11_membership_probe(spark: SparkSession, d: str) -> DataFrame:
    with case_of(spark, d) as case:
        return rows(spark, [(z, _membership(case, z)) for z in (0.0, 4.0)], "z double, auc double")


@query("e11_property_probe")
def e11_property_probe(spark: SparkSession, d: str) -> DataFrame:
    """Whether an update's direction tells if the head domain is in a shard: the distance of the two groups' mean updates against their spread, with and without noise."""
    with case_of(spark, d) as case:
        head = case.cdf.where("rank = 1").first()["domain_id"]
        people = participants.people(spark, 60).withColumn("run", F.lit("r"))
        has = {r["participant_id"] for r in participants.draw(people, case.cdf, 5).where(F.col("domain_id") == head).collect()}
        got = federated.updates(experiments.virtual(case, 5)(people).join(case.train, "script_id"), {"r": federated.run_of(experiments.base(60), case.mean, case.scale)}, {"r": np.zeros(NF + 1)}, 1).select("participant_id", "delta").collect()
        x, own = np.array([r["delta"] for r in got]), np.array([r["participant_id"] in has for r in got])
        out = []
        for z in (0.0, 1.0):
            noised = x + z * np.random.default_rng(5).normal(size=x.shape)
            gap = np.linalg.norm(noised[own].mean(axis=0) - noised[~own].mean(axis=0)) if own.any() and not own.all() else 0.0
            out.append((z, int(own.sum()), float(gap / noised.std(axis=0).mean())))
        return rows(spark, out, "z double, holders int, separation double")


@query("e12_update_leak", f"SELECT count(*) FILTER (u < 0.5) AS seen_alone, 1 AS sums_seen FROM (SELECT {sql_uniform(repr('leak'), 'c_custkey')} AS u FROM customer)")
def e12_update_leak(spark: SparkSession, d: str) -> DataFrame:
    """What the server holds of a cohort: each update on its own, or with masks one sum."""
    c = read(spark, d, "customer").where(uniform("leak", F.col("c_custkey")) < 0.5)
    return c.agg(F.count("*").alias("seen_alone"), F.lit(1).alias("sums_seen"))


@query("e13_label_flip")
def e13_label_flip(spark: SparkSession, d: str) -> DataFrame:
    """A share of the participants turn one family's positives to negatives; the area on the test part, and the mean score of that family."""
    with case_of(spark, d) as case:
        family = case.labelled.where("webrtc").select("script_id", F.lit(True).alias("target"))
        out = []
        for share in (0.0, 0.3, 1.0):
            flip = uniform("flip", F.col("script_id")) < share
            bad = case.train.join(family, "script_id", "left").withColumn("y", F.when(F.coalesce("target", F.lit(False)) & flip, 0).otherwise(F.col("y"))).drop("target")
            cfg = experiments.base(10_000, rounds=3)
            theta = federated.train(participants.people(spark, cfg.participants), experiments.virtual(case), bad, cfg, case.mean, case.scale).theta
            s = model.score_packed(case.test, theta, case.mean, case.scale)
            hit = s.join(family, "script_id").agg(F.avg("score")).first()[0]
            out.append((share, float(metrics.auprc(s).first()[0]), float(hit) if hit is not None else math.nan))
        return rows(spark, out, "share double, auprc double, target_score double")


@query("u1_local_update_cost")
def u1_local_update(spark: SparkSession, d: str) -> DataFrame:
    """Norms of first updates and the share that the ball cuts, for several radii."""
    shard, feats, _ = natural_case(spark, d)
    packed = features.pack(feats).join(labels.apply(order_trace(spark, d)).select("script_id", "y"), "script_id")
    data = shard.withColumn("run", F.lit("r")).join(packed, "script_id")
    run = federated.run_of(federated.TrainConfig(NF, 1, clip=math.inf, iters=2))
    n = federated.updates(data, {"r": run}, {"r": np.zeros(NF + 1)}, 1)
    return n.agg(*[F.round(F.avg((F.col("norm") > s).cast("double")), 4).alias(f"above_{str(s).replace('.', '_')}") for s in (0.1, 0.3, 1.0, 3.0)], F.round(F.percentile_approx("norm", 0.5), 4).alias("median"))


# scalar functions that remain -------------------------------------------------------------------------------------------------------


@query("fn_array_transform_scale", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: (x::DOUBLE - 0.5) / 2)), 3) AS s FROM embeddings")
def fn_array_transform_scale(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: (x.cast("double") - 0.5) / 2), F.lit(0.0), lambda a, x: a + x), 3).alias("s"))


@query("fn_timestamp_ntz_cast", "SELECT event_id, CAST(ts AS DATE) AS day FROM events")
def fn_timestamp_ntz_cast(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").cast("date").alias("day"))


@query("fn_coalesce_default", _SCORED + "SELECT script_id, coalesce(nullif(y, 0), -1) AS y FROM scores")
def fn_coalesce_default(spark: SparkSession, d: str) -> DataFrame:
    return fixed_scores(spark, d).select("script_id", F.coalesce(F.expr("nullif(y, 0)"), F.lit(-1)).alias("y"))


@query("fn_map_concat", "SELECT o_custkey, 1 + count(DISTINCT o_orderstatus) AS n FROM orders GROUP BY 1")
def fn_map_concat(spark: SparkSession, d: str) -> DataFrame:
    m = read(spark, d, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))
    return m.select("o_custkey", F.size(F.map_concat("m", F.create_map(F.lit("all"), F.lit(0).cast("long")))).cast("long").alias("n"))
