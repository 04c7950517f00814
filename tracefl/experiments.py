"""The experiments on the order trace: one prepared case, and sweeps whose runs share their jobs."""

from __future__ import annotations

import functools
import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import catalogue, features, federated, labels, metrics, model, noniid, participants, scaling
from .carriers import order_trace
from .federated import Result, Run, TrainConfig, run_of
from .hashing import py_normal
from .privacy import BudgetPlan

FLAG_CAPS = {"flag_cap_mean": 0.5, "flag_cap_var": 0.25, "first_flag": catalogue.FIRST_FLAG}


@dataclass
class Case:
    """Everything the runs share; packed and bridge are kept in memory between rounds."""

    spark: SparkSession
    trace: DataFrame
    labelled: DataFrame
    train: DataFrame  # (script_id, y, idx, val)
    test: DataFrame
    bridge: DataFrame
    cdf: DataFrame
    mean: np.ndarray
    scale: np.ndarray

    def done(self) -> None:
        for df in (self.train, self.test, self.bridge, self.cdf):
            df.unpersist()


def prepare(spark: SparkSession, sf_dir: str) -> Case:
    trace = order_trace(spark, sf_dir)
    labelled = labels.apply(trace)
    parts = participants.split(labelled)
    packed = features.pack(features.features_long(trace)).join(parts, "script_id")
    train, test = (packed.where(F.col("part") == p).drop("part").cache() for p in ("train", "test"))
    bridge = participants.bridge(trace).join(train.select("script_id"), "script_id", "left_semi").cache()
    cdf = participants.zipf(participants.sites(trace)).cache()
    long = train.select("script_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("script_id", F.col("p.idx").alias("feature_id"), F.col("p.val").alias("v"))
    stats = scaling.global_stats(long, catalogue.table(spark), train.count()).collect()
    return Case(spark, trace, labelled, train, test, bridge, cdf, *federated.scale_vectors(stats, catalogue.N_FEATURES))


def virtual(case: Case, urls: int = 20) -> federated.Shards:
    """Shards of drawn domains, made for a round's cohort alone."""
    return lambda cohort: participants.draw(cohort, case.cdf, urls).join(case.bridge, "domain_id").select(*cohort.columns, "script_id").distinct()


def limited(case: Case, share: float | dict[str, float], urls: int = 20) -> federated.Shards:
    """Shards of which limited participants keep less; share: of them, for all runs or for each."""

    def shards(cohort: DataFrame) -> DataFrame:
        of = F.element_at(F.create_map(*[F.lit(x) for kv in share.items() for x in kv]), F.col("run")) if isinstance(share, dict) else share
        return participants.limit_knowledge(virtual(case, urls)(cohort), case.labelled, of)

    return shards


#: Scripts of a domain that travel in one list, roughly.
LISTED = 4096


def _chosen_sums(case: Case, picks: DataFrame, urls: int) -> DataFrame:
    """(draw, participant_id, feature_id, take_mu, take_var, n, s1, s2) of picks (draw, participant_id, in_mu, in_var).

    A participant's shard depends on no draw, so it is met once for all of them. Of its scripts only those with a chosen feature are rows; the others
    are counted in lists by domain, dealt by a hash of the script where a domain is large, so that a script of several domains counts once.
    """
    drawn = participants.draw(picks.select("participant_id").distinct(), case.cdf, urls)
    most = case.bridge.groupBy("domain_id").count().agg(F.max("count")).first()[0] or 0
    lists = case.bridge.groupBy("domain_id", F.pmod(F.xxhash64("script_id"), F.lit(most // LISTED + 1)).alias("part")).agg(F.collect_list("script_id").alias("scripts"))
    n = drawn.join(lists, "domain_id").groupBy("participant_id", "part").agg(F.size(F.array_distinct(F.flatten(F.collect_list("scripts")))).alias("n")).groupBy("participant_id").agg(F.sum("n").alias("n"))
    keys = picks.select("draw", "participant_id", "in_mu", "in_var", F.explode(F.array_union("in_mu", "in_var")).alias("feature_id"))
    keys = keys.select("draw", "participant_id", "feature_id", *[F.array_contains(f"in_{t}", F.col("feature_id")).alias(f"take_{t}") for t in ("mu", "var")])
    values = case.bridge.join(case.train.select("script_id", F.explode(F.arrays_zip("idx", "val")).alias("x")), "script_id").select("domain_id", "script_id", F.col("x.idx").alias("feature_id"), F.col("x.val").alias("v"))
    hit = keys.join(drawn, "participant_id").join(values, ["domain_id", "feature_id"]).select(*keys.columns, "script_id", "v").distinct()
    s = hit.groupBy(*keys.columns).agg(F.sum("v").alias("s1"), F.sum(F.col("v") * F.col("v")).alias("s2"))
    return s.join(n, "participant_id")


def _private_stats(case: Case, cfgs: dict[str, scaling.ScaleConfig], urls: int = 20) -> dict[str, list]:
    """For each draw its rows of scaling.fit. Each statistic of each feature has a Poisson cohort of all W; only participants in one are made, and their sums in one job for all draws."""
    table = catalogue.table(case.spark)
    whole = {k: c for k, c in cfgs.items() if c.q >= 1}
    out = {k: scaling.fit(virtual(case, urls)(participants.people(case.spark, c.participants)), case.train, table, c).collect() for k, c in whole.items()}
    some = {k: c for k, c in cfgs.items() if c.q < 1}
    if not some:
        return out
    picks = functools.reduce(DataFrame.unionAll, [scaling.drawn_cohorts(table, c).select(F.lit(k).alias("draw"), "participant_id", "in_mu", "in_var") for k, c in some.items()]).cache()  # q * W * 2F keys of each draw; lost blocks are drawn again alike
    sums = _chosen_sums(case, picks, urls).cache()  # those of the keys with values
    try:
        each = [scaling.fit(None, case.train, table, c, sums=sums.where(F.col("draw") == k)).withColumn("draw", F.lit(k)) for k, c in some.items()]
        for r in functools.reduce(DataFrame.unionAll, each).collect():  # 2F figures of each draw
            out.setdefault(r["draw"], []).append(r)
    finally:
        sums.unpersist()
        picks.unpersist()
    return out


def private_scale(case: Case, w: int, q: float, z: float, urls: int = 20, divisor: str = "stddev", ledger=None, **how) -> tuple[np.ndarray, np.ndarray]:
    """(mean, scale) from noised statistics. Charges the ledger 2F statistics."""
    if ledger is not None:
        ledger.charge("statistics", q, z, 2 * catalogue.N_FEATURES)
    cfg = scaling.ScaleConfig(w, q=q, z=z, divisor=divisor, **{**FLAG_CAPS, **how})
    return federated.scale_vectors(_private_stats(case, {"": cfg}, urls)[""], catalogue.N_FEATURES, divisor)


def private_scales(case: Case, w: int, q: float, zs: set[float], seed: str) -> dict[float, tuple[np.ndarray, np.ndarray]]:
    """private_scale with seeded noise for several z, for simulation."""
    return private_scales_of(case, {"": (w, q, zs, seed)})[""]


def private_scales_of(case: Case, draws: dict[str, tuple[int, float, set[float], str]]) -> dict[str, dict[float, tuple[np.ndarray, np.ndarray]]]:
    """private_scales of several (W, q, zs, seed) at once: the cohorts and their sums don't depend on z, so they are made once."""
    cfgs = {k: scaling.ScaleConfig(w, q=q, seed=seed, **FLAG_CAPS) for k, (w, q, _, seed) in draws.items()}
    stats = _private_stats(case, cfgs)
    return {k: {z: _noised(stats[k], cfg, z) for z in draws[k][2]} for k, cfg in cfgs.items()}


def _noised(stats: list, cfg: scaling.ScaleConfig, z: float) -> tuple[np.ndarray, np.ndarray]:
    """(mean, scale) with the seed's noise."""
    noised = []
    for r in stats:
        i = r["feature_id"]
        caps = (cfg.flag_cap_mean, cfg.flag_cap_var) if i >= cfg.first_flag else (cfg.cap_mean, cfg.cap_var)
        noised.append({"feature_id": i} | {name: r[name] + py_normal(cfg.seed, f"noise-{tag}", i) * (cap * z / (cfg.q * cfg.participants)) for name, tag, cap in zip(("mean", "var"), ("mu", "var"), caps, strict=True)})
    return federated.scale_vectors(noised, catalogue.N_FEATURES)


def scores(case: Case, results: dict[str, Result], runs: dict[str, Run]) -> DataFrame:
    """(run, script_id, y, score) on the test part, in one pass over it."""
    names = list(results)
    got = model.scores_packed(case.test, *[np.array(v) for v in zip(*[(results[n].theta, runs[n].mean, runs[n].scale) for n in names], strict=True)])
    name = F.array(*[F.lit(n) for n in names])
    return got.select("script_id", "y", F.posexplode("scores").alias("i", "score")).select(F.get(name, F.col("i")).alias("run"), "script_id", "y", "score")


def areas(case: Case, results: dict[str, Result], runs: dict[str, Run]) -> dict[str, float]:
    return {r["run"]: r["auprc"] for r in metrics.auprc(scores(case, results, runs), keys=("run",)).collect()}


def _same(name: str, run: Run) -> tuple:
    """Runs with equal keys have equal results: with everyone in each round and no noise the seed decides nothing."""
    seed = "" if run.cfg.q >= 1 and not run.cfg.z else run.cfg.seed
    return replace(run.cfg, seed=seed), run.mean.tobytes(), run.scale.tobytes(), run.keep.tobytes(), run.limit


def sweep(case: Case, runs: dict[str, Run], shards: federated.Shards | None = None, apart: bool | None = None) -> dict[str, float]:
    """Areas of simulated runs. Their noise is seeded so that they can be repeated; none of them is a release. Runs that are equal but for a seed without effect are made once, and runs with one cohort share its shards (unless shards of one's own may tell runs apart)."""
    apart = shards is not None if apart is None else apart
    first: dict[tuple, str] = {}
    of = {n: n if apart else first.setdefault(_same(n, r), n) for n, r in runs.items()}
    made = {n: r for n, r in runs.items() if of[n] == n}
    people = {w: participants.people(case.spark, w) for w in {r.cfg.participants for r in made.values()}}
    everyone = {n: people[r.cfg.participants] for n, r in made.items()}
    got = areas(case, federated.train_many(made, everyone, shards or virtual(case), case.train, noise=py_normal, apart=apart), made)
    return {n: got[of[n]] for n in runs}


def base(w: int, cohort: int = 100, **how) -> TrainConfig:
    return TrainConfig(catalogue.N_FEATURES, w, q=min(1.0, cohort / w), **how)


def by_participants(case: Case, ws: tuple[int, ...] = (1, 10, 100, 1000), sets: tuple[str, ...] = ("full", "lab", "extension", "native"), rounds: int = 4, seeds: int = 5) -> list[tuple]:
    """(set, W, seed, area) without noise, everyone in each round."""
    runs = {f"{s}|{w}|{k}": run_of(TrainConfig(catalogue.N_FEATURES, w, rounds=rounds, q=1.0, clip=math.inf, seed=f"fl{k}"), case.mean, case.scale, catalogue.feature_set(s)) for s in sets for w in ws for k in range(seeds)}
    return [(*_split(n), a) for n, a in sweep(case, runs).items()]


def _split(name: str) -> tuple:
    s, w, k = name.split("|")
    return s, float(w), int(k)


def by_budget(case: Case, ws: tuple[int, ...] = (10_000, 100_000, 1_000_000), eps: tuple[float, ...] = (1.0, 5.0, 10.0, math.inf), rounds: int = 6, sets: tuple[str, ...] = ("full",), seeds: int = 5) -> list[tuple]:
    """(set, W, epsilon, z, seed, area): 2F statistics and R rounds share the budget; means and variances are noised as well, anew for each seed. Without noise they are exact."""
    runs, zs = {}, {}
    cfgs = {w: base(w, rounds=rounds) for w in ws}
    resolved = {w: {e: BudgetPlan(e, catalogue.N_FEATURES, rounds, cfg.q).resolve() for e in eps} for w, cfg in cfgs.items()}
    noisy = {w: {z for z, _ in r.values() if z} for w, r in resolved.items()}
    draws = {f"{w}|{k}": (w, cfgs[w].q, noisy[w], f"scale{k}") for w in ws if noisy[w] for k in range(seeds)}
    scales = private_scales_of(case, draws) if draws else {}
    for w, cfg in cfgs.items():
        for k in range(seeds):
            for e, (z_scale, z_round) in resolved[w].items():
                zs[w, e] = z_round
                mean, scale = scales[f"{w}|{k}"][z_scale] if z_scale else (case.mean, case.scale)
                for s in sets:
                    runs[f"{s}|{w}|{e}|{k}"] = run_of(replace(cfg, z=z_round, seed=f"fl{k}"), mean, scale, catalogue.feature_set(s))
    out = []
    for n, a in sweep(case, runs).items():
        s, w, e, k = n.split("|")
        out.append((s, float(w), float(e), zs[int(w), float(e)], int(k), a))
    return out


def by_scaling(case: Case, sets: tuple[str, ...] = ("full", "native"), w: int = 10_000, rounds: int = 6, z: float = 0.0) -> list[tuple]:
    """(set, scaling, area): exact, divided by the variance, and none."""
    one, none = np.ones_like(case.scale), np.zeros_like(case.mean)
    kinds = {"stddev": (case.mean, case.scale), "variance": (case.mean, case.scale**2), "none": (none, one)}
    runs = {f"{s}|{k}": run_of(base(w, rounds=rounds, z=z), *v, catalogue.feature_set(s)) for s in sets for k, v in kinds.items()}
    return [(*n.split("|"), a) for n, a in sweep(case, runs).items()]


def by_growth(case: Case, pool: list[int], step: int, most: int, w: int = 10_000, rounds: int = 5, z: float = 0.0) -> list[tuple]:
    """(k, area) of the native set with the next k features of the pool."""
    native = catalogue.feature_set("native")
    pool = [i for i in pool if i not in set(native)]
    runs = {str(k): run_of(base(w, rounds=rounds, z=z), case.mean, case.scale, sorted([*native, *pool[:k]])) for k in range(0, most + 1, step)}
    return sorted((int(n), a) for n, a in sweep(case, runs).items())


def by_limited(case: Case, shares: tuple[float, ...] = (0.0, 0.2, 0.4, 0.5, 0.6, 0.8, 1.0), w: int = 10_000, rounds: int = 5, sample: int = 100, seeds: int = 5) -> list[tuple]:
    """(share of limited participants, seed, score of unlikeness over positives with 1 at share 0, area)."""
    few = participants.people(case.spark, sample)
    case = replace(case, labelled=case.labelled.cache())
    try:
        known = lambda cohort: participants.known_until(virtual(case)(cohort), case.labelled)
        each = known(few).withColumn("limit", F.explode(F.array(*[F.lit(float(s)) for s in shares]))).where("until >= limit")
        spread = {r["limit"]: r["spread"] for r in noniid.spread(each, case.labelled, positives=True, keys=("limit",)).collect()}
        of = {f"{s}|{k}": s for s in shares for k in range(seeds)}
        runs = {n: replace(run_of(base(w, rounds=rounds, seed=f"fl{n.split('|')[1]}"), case.mean, case.scale), limit=s) for n, s in of.items()}
        got = sweep(case, runs, known, apart=False)
    finally:
        case.labelled.unpersist()
    first, unlike = None, {}
    for s in shares:
        d = spread.get(float(s))
        first = first or d
        unlike[s] = d / first
    return [(of[n], int(n.split("|")[1]), unlike[of[n]], a) for n, a in got.items()]


def poison(case: Case, factor: float, share: float, clip: float = 1.0, w: int = 200) -> dict[str, float]:
    """How far attackers who send their update times -factor move one round's model, with and without the clip; and the clip's bound."""
    shards = virtual(case)
    rows = shards(participants.people(case.spark, w).withColumn("run", F.lit("r"))).join(case.train, "script_id")
    run = run_of(TrainConfig(catalogue.N_FEATURES, w, clip=math.inf), case.mean, case.scale)
    got = federated.updates(rows, {"r": run}, {"r": np.zeros(catalogue.N_FEATURES + 1)}, 1).select("participant_id", "delta").collect()
    bad = {p for p in range(w) if p < share * w}
    honest = np.array([r["delta"] for r in got])
    sent = np.array([np.array(r["delta"]) * (-factor if r["participant_id"] in bad else 1.0) for r in got])
    cap = lambda m: m * np.minimum(1, clip / np.maximum(np.linalg.norm(m, axis=1), 1e-12))[:, None]
    return {"free": float(np.linalg.norm((sent - honest).sum(axis=0)) / w), "clipped": float(np.linalg.norm((cap(sent) - cap(honest)).sum(axis=0)) / w), "bound": 2 * len(bad) * clip / w}
