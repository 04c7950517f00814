"""Work that runs share gives what each gives alone."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.conftest import TINY
from tracefl import catalogue, experiments, federated, model, scaling
from tracefl.features import pack


def test_hashed_cohorts_by_key(spark, monkeypatch):
    """The same as with every participant's list of features, without making those lists."""
    shard = spark.range(60).select((F.col("id") % 12).alias("participant_id"), F.col("id").alias("script_id"))
    feats = spark.range(600).select((F.col("id") % 60).alias("script_id"), (F.col("id") % 7).cast("int").alias("feature_id"), (F.col("id") % 5).cast("double").alias("v")).dropDuplicates(["script_id", "feature_id"])
    table = catalogue.table(spark)
    cfg = scaling.ScaleConfig(12, q=0.5)
    picks = scaling.cohorts(shard.select("participant_id").distinct(), table, cfg)
    picks = spark.createDataFrame(picks.collect(), picks.schema)
    of = lambda df: np.array([[r["mean"], r["var"]] for r in df.orderBy("feature_id").collect()])
    want = of(scaling.fit(shard, pack(feats), table, cfg, picks))
    monkeypatch.setattr(scaling, "cohorts", None)  # not called any more
    assert np.allclose(of(scaling.fit(shard, feats, table, cfg)), want) and np.allclose(of(scaling.fit(shard, pack(feats), table, cfg)), want)
    assert want.any()


@pytest.fixture
def case(spark):
    case = experiments.prepare(spark, TINY)
    yield case
    case.done()


def test_runs_that_are_shared(case, monkeypatch):
    """Seeds without effect cost one run; shares of limited participants cost one job a round, with the areas that each has alone."""
    made, train_many = [], federated.train_many

    def counted(runs, *args, **how):
        made.append(len(runs))
        return train_many(runs, *args, **how)

    monkeypatch.setattr(federated, "train_many", counted)
    got = experiments.by_participants(case, ws=(5,), sets=("native",), rounds=1, seeds=3)
    assert made == [1] and len(got) == 3 and len({a for *_, a in got}) == 1
    made.clear()
    both = experiments.by_limited(case, shares=(0.0, 0.8), w=200, rounds=1, sample=20, seeds=1)
    assert made == [2] and [s for s, *_ in both] == [0.0, 0.8]
    for share, _, _, area in both:
        alone = experiments.sweep(case, {"0": federated.run_of(experiments.base(200, rounds=1, seed="fl0"), case.mean, case.scale)}, experiments.limited(case, share))
        assert alone["0"] == pytest.approx(area)


def test_one_set_of_sums_for_all_noise(case):
    got = experiments.private_scales(case, 300, 0.05, {0.5, 2.0}, "scale3")
    for z in got:
        want = experiments.private_scale(case, 300, 0.05, z, seed="scale3", noise="seeded")
        assert np.allclose(got[z][0], want[0]) and np.allclose(got[z][1], want[1])
    assert not np.allclose(got[0.5][0], got[2.0][0])


def test_runs_of_one_cohort_share_its_shards(case, monkeypatch):
    """The cohort of a seed has its shards made once for all shares and budgets; scores come from one pass over the test part."""
    met, virtual = [], experiments.virtual

    def counted(case, urls=20):
        def shards(cohort):
            if "run" in cohort.columns:
                met.append({r["run"] for r in cohort.select("run").distinct().collect()})
            return virtual(case, urls)(cohort)

        return shards

    monkeypatch.setattr(experiments, "virtual", counted)
    experiments.by_limited(case, shares=(0.0, 0.5, 1.0), w=200, rounds=2, sample=20, seeds=2)
    assert met == [{"0.0|0", "0.0|1"}] * 2
    met.clear()
    runs = {f"{z}|{k}": federated.run_of(experiments.base(200, rounds=1, z=z, seed=f"fl{k}"), case.mean, case.scale) for z in (0.0, 1.0) for k in (0, 1)}
    got = experiments.sweep(case, runs)
    assert met == [{"0.0|0", "0.0|1"}]
    for n, r in runs.items():
        assert experiments.sweep(case, {n: r})[n] == pytest.approx(got[n])
    fits = {n: federated.Result(np.linspace(-1, 1, catalogue.N_FEATURES + 1) * (i + 1)) for i, n in enumerate(runs)}
    scores = experiments.scores(case, fits, runs)
    assert scores._jdf.queryExecution().optimizedPlan().toString().count("InMemoryRelation") == 1
    for n, r in runs.items():
        one = {x["script_id"]: x["score"] for x in model.score_packed(case.test, fits[n].theta, r.mean, r.scale).collect()}
        assert {x["script_id"]: x["score"] for x in scores.where(F.col("run") == n).collect()} == pytest.approx(one)


def test_statistics_of_several_draws_in_one_job(case, monkeypatch):
    """As from every draw's own shards and all of their rows, also where a domain's scripts come in several lists."""
    monkeypatch.setattr(experiments, "LISTED", 2)
    table = catalogue.table(case.spark)
    cfgs = {k: scaling.ScaleConfig(w, q=q, seed=k, **experiments.FLAG_CAPS) for k, w, q in (("a", 300, 0.05), ("b", 300, 0.05), ("c", 2000, 0.01))}
    want = {}
    for k, cfg in cfgs.items():
        picks = scaling.drawn_cohorts(table, cfg).cache()
        want[k] = {r["feature_id"]: (r["mean"], r["var"]) for r in scaling.fit(experiments.virtual(case)(picks.select("participant_id")), case.train, table, cfg, picks).collect()}
        picks.unpersist()
    monkeypatch.setattr(experiments, "virtual", None)  # no shards are made whole
    got = experiments._private_stats(case, cfgs)
    for k in cfgs:
        assert len(got[k]) == catalogue.N_FEATURES and any(v for v in want[k].values())
        for r in got[k]:
            assert (r["mean"], r["var"]) == pytest.approx(want[k][r["feature_id"]])
