"""The sweeps' runs under a budget."""

from __future__ import annotations

import numpy as np

import pytest
from pyspark.sql import functions as F

from tracefl import catalogue, experiments, participants, privacy, scaling


def test_statistics_are_noised_under_a_budget(spark, tiny, monkeypatch):
    case = experiments.prepare(spark, tiny)
    seen = {}
    monkeypatch.setattr(experiments, "sweep", lambda case, runs: seen.update(runs) or dict.fromkeys(runs, 0.0))
    try:
        out = experiments.by_budget(case, (10_000,), (1.0, float("inf")), 1, seeds=2)
    finally:
        case.done()
    one, two, free = (seen[f"full|10000|{k}"] for k in ("1.0|0", "1.0|1", "inf|0"))
    assert np.array_equal(free.mean, case.mean) and free.cfg.z == 0
    assert not np.allclose(one.mean, case.mean) and not np.allclose(one.scale, case.scale)
    assert not np.allclose(one.mean, two.mean)
    assert len(out) == 4


def test_cohorts_are_drawn_alike_and_cost_their_own_size(spark):
    """Poisson samples of all W: q * W of each statistic, independent of one another, few keys however large W is."""
    table, w, q = catalogue.table(spark), 1_000_000, 1e-4
    drawn = scaling.drawn_cohorts(table, scaling.ScaleConfig(w, q=q)).collect()
    n = catalogue.N_FEATURES
    keys = [("mu", f, r["participant_id"]) for r in drawn for f in r["in_mu"]] + [("var", f, r["participant_id"]) for r in drawn for f in r["in_var"]]
    assert len(keys) == len(set(keys)) and abs(len(keys) - 2 * n * q * w) < 6 * (2 * n * q * w) ** 0.5
    assert len(drawn) > 0.9 * len(keys)  # hardly anyone is in two of them, so no pool is shared
    assert {t for t, _, _ in keys} == {"mu", "var"} and all(0 <= p < w for _, _, p in keys)
    again = scaling.drawn_cohorts(table, scaling.ScaleConfig(w, q=q)).collect()
    assert {r["participant_id"] for r in drawn} == {r["participant_id"] for r in again}


def test_only_chosen_keys_are_summed(spark):
    """The chosen keys' statistics are those of all participants; nobody else's rows reach the join with values."""
    table = catalogue.table(spark)
    feats = spark.range(60).select(F.col("id").alias("script_id"), F.explode(F.sequence(F.lit(0), F.lit(9))).alias("feature_id")).withColumn("v", ((F.col("script_id") * 7 + F.col("feature_id")) % 5).cast("double"))
    shard = spark.range(200).select(F.col("id").alias("participant_id"), F.explode(F.sequence(F.lit(0), F.lit(3))).alias("k")).select("participant_id", ((F.col("participant_id") * 13 + F.col("k")) % 60).alias("script_id"))
    cfg = scaling.ScaleConfig(200, q=0.1)
    picks = scaling.cohorts(participants.people(spark, 200), table, cfg)
    whole = {(r["participant_id"], r["feature_id"]): r for r in scaling.local_stats(shard, feats, cfg).collect()}
    chosen = {r["participant_id"]: r for r in picks.collect()}
    got = {r["feature_id"]: r for r in scaling.fit(shard, feats, table, cfg).collect()}
    for f in range(10):
        for which, have in (("mu", "mean"), ("var", "var")):
            want = sum(whole[p, f][which] for p, r in chosen.items() if f in r[f"in_{which}"]) / 20
            assert got[f][have] == pytest.approx(want)


def test_system_noise_by_default_and_charges(spark, tiny):
    table = catalogue.table(spark)
    nobody = spark.createDataFrame([], "participant_id long, script_id long"), spark.createDataFrame([], "script_id long, feature_id int, v double")
    a, b = ([r["mean"] for r in scaling.fit(*nobody, table, scaling.ScaleConfig(100, z=1.0)).orderBy("feature_id").collect()] for _ in range(2))
    assert a != b and 0.5 < np.std(a) / 0.04 < 1.5
    case = experiments.prepare(spark, tiny)
    try:
        book = privacy.Ledger(10.0)
        experiments.private_scale(case, 1000, 0.1, 6.0, ledger=book)
        assert [(p[0], p[3]) for p in book.parts] == [("statistics", 2 * catalogue.N_FEATURES)]
        with pytest.raises(RuntimeError):
            experiments.private_scale(case, 1000, 0.1, 0.0, ledger=book)
    finally:
        case.done()
