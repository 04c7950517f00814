"""Worked examples, invariants and the accountant's regression values."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tracefl import catalogue, features, federated, labels, metrics, noniid, optim, participants, privacy, scaling, secure_agg
from tracefl.carriers import order_trace
from tracefl.hashing import normal, py_normal, py_uniform, uniform


def script(spark, calls):
    """calls: (api, n_calls) of one script."""
    ids = {f.api: f.feature_id for f in catalogue.features() if f.kind == "count"}
    ids |= dict.fromkeys(catalogue.AUDIO, ids["audio"])
    return spark.createDataFrame([(1, 1, a, ids[a], n, "AF", 0.0, 0.0) for a, n in calls], "script_id long, domain_id long, api string, api_id int, n_calls int, ret string, arg1 double, arg2 double")


CASES = [
    ([("fillText", 1), ("fillStyle", 1), ("toDataURL", 1)], "canvas", True),
    ([("strokeText", 1), ("strokeStyle", 1), ("toDataURL", 1)], "canvas", True),
    ([("fillText", 1), ("fillStyle", 1)], "canvas", False),
    ([("fillText", 1), ("toDataURL", 1)], "canvas", False),
    ([("fillText", 1), ("fillStyle", 1), ("toDataURL", 1), ("save", 1)], "canvas", False),
    ([("fillText", 1), ("fillStyle", 1), ("toDataURL", 1), ("addEventListener", 1)], "canvas", False),
    ([("font", 21), ("measureText", 21)], "canvas_font", True),
    ([("font", 20), ("measureText", 21)], "canvas_font", False),
    ([("font", 21), ("measureText", 20)], "canvas_font", False),
    ([("createDataChannel", 1), ("onicecandidate", 1)], "webrtc", True),
    ([("createOffer", 1), ("localDescription", 1)], "webrtc", True),
    ([("createOffer", 1), ("createDataChannel", 1)], "webrtc", False),
    *[([(m, 1)], "audio", True) for m in catalogue.AUDIO],
    ([("generic_3", 9)], "audio", False),
]


@pytest.mark.parametrize("calls, family, expected", CASES)
def test_rules(spark, calls, family, expected):
    row = labels.apply(script(spark, calls)).first()
    assert row[family] is expected
    assert row["y"] == int(any(row[f] for f in labels.FAMILIES))


def test_positive_counts(spark, tiny, small):
    for d, scripts, positives in ((tiny, 1473, 45), (small, 14743, 519)):
        row = labels.prevalence(labels.apply(order_trace(spark, d))).first()
        assert (row["scripts"], row["positives"]) == (scripts, positives)


def test_hashing_is_engine_independent(spark):
    got = spark.range(5).select(uniform("7", F.col("id")).alias("u"), normal("7", F.col("id")).alias("z")).collect()
    for i, r in enumerate(got):
        assert r["u"] == py_uniform(7, i) and abs(r["z"] - py_normal(7, i)) < 1e-12
    assert [round(r["u"], 6) for r in got] == [0.275680, 0.111751, 0.428451, 0.723805, 0.870545]


def test_catalogue_sizes():
    assert catalogue.N_FEATURES == 197
    for name, (size, counts, customs) in catalogue.PUBLISHED.items():
        ids = catalogue.synthetic_set(name)
        assert (len(ids), sum(i < 684 for i in ids), sum(i >= 684 for i in ids)) == (size, counts, customs)


def shard_case(spark):
    """Three participants with 1, 2 and 3 scripts and one feature."""
    shard = spark.createDataFrame([(1, 1), (2, 2), (2, 3), (3, 4), (3, 5), (3, 6)], "participant_id long, script_id long")
    feats = spark.createDataFrame([(1, 0, 9.0), (2, 0, 2.0), (4, 0, 3.0), (5, 0, 6.0)], "script_id long, feature_id int, v double")
    return shard, feats, spark.createDataFrame([(0,), (1,)], "feature_id int")


def test_local_statistics_by_hand(spark):
    shard, feats, _ = shard_case(spark)
    got = {r["participant_id"]: (r["mu"], r["var"]) for r in scaling.local_stats(shard, feats, scaling.ScaleConfig(3)).collect()}
    assert got[1] == (4.0, 0.0)  # capped; one row has no variance
    assert got[2] == (1.0, 2.0)
    assert got[3] == (3.0, pytest.approx(9.0))


def test_absent_feature_is_pure_noise(spark):
    shard, feats, cat = shard_case(spark)
    got = {r["feature_id"]: r for r in scaling.fit(shard, feats, cat, scaling.ScaleConfig(3, z=1.0, noise="seeded")).collect()}
    assert got[1]["mean"] == pytest.approx(py_normal("scale", "noise-mu", 1) * 4.0 / 3)
    assert got[0]["mean"] == pytest.approx((4 + 1 + 3) / 3 + py_normal("scale", "noise-mu", 0) * 4.0 / 3)


def test_only_the_root_gives_unit_variance(spark):
    rows = spark.range(1, 101).select(F.col("id").alias("script_id"), F.lit(0).alias("feature_id"), (F.col("id") * 3.0).alias("v"))
    cat = spark.createDataFrame([(0,)], "feature_id int")
    stats = scaling.global_stats(rows, cat, 100)
    var = {k: scaling.transform(rows, stats, scaling.ScaleConfig(1, divisor=k)).agg(F.var_samp("v")).first()[0] for k in ("stddev", "variance")}
    assert var["stddev"] == pytest.approx(1.0) and var["variance"] != pytest.approx(1.0, rel=0.1)


def test_projection():
    d = np.array([3.0, 4.0])
    assert np.allclose(optim.project(d, 5.0), d) and np.allclose(optim.project(d, 10.0), d)
    assert np.linalg.norm(optim.project(d, 1.0)) == pytest.approx(1.0)
    assert np.allclose(optim.project(np.zeros(2), 1.0), 0)


def test_lbfgs_quadratic_and_gradient():
    a = np.diag([1.0, 4.0, 9.0, 16.0])
    x = optim.lbfgs(lambda v: (0.5 * v @ a @ v - v.sum(), a @ v - 1), np.zeros(4), iters=30)
    assert np.allclose(a @ x, 1, atol=1e-6)
    rng = np.random.default_rng(1)
    f = optim.logistic(rng.normal(size=(40, 3)), rng.integers(0, 2, 40).astype(float), 0.1)
    w = rng.normal(size=4)
    numeric = [(f(w + e)[0] - f(w - e)[0]) / 2e-6 for e in np.eye(4) * 1e-6]
    assert np.allclose(f(w)[1], numeric, atol=1e-6)


def test_clip_bounds_every_update():
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(30, 5)) * 10, rng.integers(0, 2, 30).astype(float)
    for kind in ("lbfgs", "gradient", "sgd"):
        for epochs in (1, 3):
            delta, _, _ = federated.local_update(x, y, np.zeros(6), federated.TrainConfig(5, 1, optimiser=kind, epochs=epochs, clip=0.3, lr=2.0))
            assert np.linalg.norm(delta) <= 0.3 * (1 + 1e-9)


def test_one_participant_round_is_its_own_update(spark):
    packed = spark.createDataFrame([(i, i % 2, [0, 1], [float(i), float(i % 3)]) for i in range(12)], "script_id long, y int, idx array<int>, val array<double>")
    cfg = federated.TrainConfig(2, 1, rounds=1, clip=math.inf, optimiser="gradient", l2=0.0)
    got = federated.train(participants.people(spark, 1), lambda g: g.crossJoin(packed.select("script_id")), packed, cfg).theta
    x = np.array([[float(i), float(i % 3)] for i in range(12)])
    y = np.array([i % 2 for i in range(12)], float)
    assert np.allclose(got, federated.local_update(x, y, np.zeros(3), cfg)[0])


def test_repartitioning_changes_nothing(spark):
    packed = spark.createDataFrame([(i, i % 2, [0], [float(i % 5)]) for i in range(40)], "script_id long, y int, idx array<int>, val array<double>")
    cfg = federated.TrainConfig(1, 8, rounds=2, z=0.5, q=0.5)
    shards = lambda g: g.join(packed.select("script_id", (F.col("script_id") % 8).alias("participant_id")), "participant_id").select("run", "participant_id", "script_id")
    a = federated.train(participants.people(spark, 8), shards, packed, cfg).theta
    b = federated.train(participants.people(spark, 8), shards, packed.repartition(5), cfg).theta
    assert np.allclose(a, b)


def test_area_with_ties(spark):
    rows = spark.createDataFrame([(1, 1, 0.9), (2, 0, 0.9), (3, 1, 0.5), (4, 0, 0.2), (5, 1, 0.2)], "script_id long, y int, score double")
    assert metrics.auprc(rows).first()[0] == pytest.approx((1 / 3) * (1 / 2) + (1 / 3) * (2 / 3) + (1 / 3) * (3 / 5))


def test_unlikeness_of_equal_shards_is_zero(spark):
    lab = spark.createDataFrame([(i, i % 2 == 0, False, False, False, int(i % 2 == 0)) for i in range(8)], "script_id long, canvas boolean, canvas_font boolean, webrtc boolean, audio boolean, y int")
    shard = spark.createDataFrame([(i // 2, i) for i in range(8)], "participant_id long, script_id long")
    for d in ("tv", "hellinger", "js"):
        assert noniid.spread(shard, lab, d).first()[0] == pytest.approx(0, abs=1e-9)


def test_masks_cancel_and_hide(spark):
    u = spark.createDataFrame([(p, c, 0.1 * p - c) for p in range(5) for c in range(3)], "participant_id long, coord int, delta double")
    for ring in (None, 2):
        masked = secure_agg.mask(u, u, neighbours=ring)
        got = {r["coord"]: r["total"] for r in secure_agg.unmask(masked).collect()}
        assert all(abs(got[c] - sum(0.1 * p - c for p in range(5))) < 1e-5 for c in range(3))
        assert masked.where(F.col("masked") < (1 << 40)).count() < 8
    with pytest.raises(ValueError):
        secure_agg.check(1 << 20, float(1 << 30))


def test_discrete_gaussian_moments():
    x = secure_agg.discrete_gaussian(3.0, 40_000, np.random.default_rng(0))
    assert abs(x.mean()) < 0.08 and abs(x.std() - 3.0) < 0.08


@pytest.mark.parametrize("w, z, expected", [(1e4, 0.5, 12.05), (1e4, 0.7, 4.10), (1e4, 1.0, 1.62), (1e5, 0.5, 4.74), (1e5, 0.7, 1.99), (1e5, 1.0, 0.91), (1e6, 0.5, 2.94), (1e6, 0.7, 1.44), (1e6, 1.0, 0.68)])
def test_accountant(w, z, expected):
    assert privacy.epsilon(100 / w, z, 100) == pytest.approx(expected, abs=0.01)


def test_accountant_properties():
    assert privacy.epsilon(0.01, 1, 10) < privacy.epsilon(0.01, 1, 100) < privacy.epsilon(0.02, 1, 100)
    assert privacy.rdp_at(1.0, 2.0, 8) == pytest.approx(8 / (2 * 4))
    z = privacy.calibrate(2.0, 0.01, 50)
    assert privacy.epsilon(0.01, z, 50) == pytest.approx(2.0, rel=1e-3)
    assert privacy.advanced(0.01, 0, 10_000, 1e-6)[0] < privacy.basic(0.01, 0, 10_000)[0]
    assert privacy.calibrate(math.inf, 0.1, 10) == 0.0


def test_ledger_refuses():
    book = privacy.Ledger(1.0)
    with pytest.raises(RuntimeError):
        for r in range(1000):
            book.charge(f"round {r}", 0.01, 0.7)
    assert book.spent() <= 1.0


def test_cohorts(spark):
    n = participants.cohort(participants.people(spark, 100_000), 0.01, 4).count()
    assert abs(n - 1000) < 5 * math.sqrt(1000)
    assert participants.cohort_fixed(participants.people(spark, 1000), 37, 1).count() == 37


def test_split_is_stratified(spark, small):
    rows = participants.split(labels.apply(order_trace(spark, small))).groupBy("y", "part").count().collect()
    n = {(r["y"], r["part"]): r["count"] for r in rows}
    assert n[1, "test"] == math.ceil(0.2 * (n[1, "test"] + n[1, "train"]))


def test_plans(spark, small):
    plan = features.features_long(order_trace(spark, small))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan
    assert "o_totalprice" not in plan and plan.count("hashpartitioning(script_id") >= 1
    q = participants.cohort(participants.people(spark, 1000), 0.1, 1)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in q
