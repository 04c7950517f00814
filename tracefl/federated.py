"""Private federated averaging and its variants: rounds of local updates, clipped to a ball, summed and noised once.

A round is one job: cohort by hash, shards of the cohort alone, packed features, one local optimisation per
participant in an Arrow group, and sums that leave each partition as one vector. Noise is drawn on the driver after the sum,
never in a task that may run twice; only the local placement draws in tasks, from keys. Independent runs (`run_id`) share the job.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable
from dataclasses import dataclass, field, replace  # noqa: F401

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import optim
from .hashing import py_normal, uniform


@dataclass(frozen=True)
class TrainConfig:
    features: int
    participants: int
    rounds: int = 20
    q: float = 1.0
    z: float = 0.0
    clip: float = 1.0  # inf: none
    epochs: int = 1
    optimiser: str = "lbfgs"  # or "gradient", "sgd"
    iters: int = 5
    history: int = 10
    lr: float = 0.5
    l2: float = 1e-3
    clip_when: str = "epoch"  # or "final"
    placement: str = "central"  # or "local", "distributed"
    unit: str = "participant"  # or "record": each row's gradient is clipped
    denominator: str = "expected"  # qW, or "realised": the cohort's size
    weights: str = "equal"  # or "rows"
    seed: str = "fl"
    tol: float = 0.0  # stop when the model moves less, relative to its norm


@dataclass
class Result:
    theta: np.ndarray
    history: list[dict] = field(default_factory=list)


Shards = Callable[[DataFrame], DataFrame]


def scale_vectors(stats: list, features: int, divisor: str = "stddev", floor: float = 0.02) -> tuple[np.ndarray, np.ndarray]:
    """(mean, scale) by feature id, from collected rows of at most F features."""
    mean, scale = np.zeros(features), np.ones(features)
    for r in stats:
        v = max(r["var"], floor)
        mean[r["feature_id"]], scale[r["feature_id"]] = r["mean"], math.sqrt(v) if divisor == "stddev" else v
    return mean, scale


def _dense(idx: pa.ListArray, val: pa.ListArray, features: int) -> np.ndarray:
    at = np.asarray(idx.offsets)
    x = np.zeros((len(idx), features))
    rows = np.repeat(np.arange(len(idx)), np.diff(at))
    x[rows, idx.values.to_numpy()[at[0] : at[-1]]] = val.values.to_numpy()[at[0] : at[-1]]
    return x


def local_update(x: np.ndarray, y: np.ndarray, theta: np.ndarray, cfg: TrainConfig) -> tuple[np.ndarray, float, bool]:
    """(difference to the start model, norm of the first unclipped difference, whether any was clipped)."""
    w, first, clipped = theta.copy(), 0.0, False
    for epoch in range(cfg.epochs):
        if cfg.unit == "record":
            z = optim.sigmoid(x @ w[:-1] + w[-1]) - y
            g = np.column_stack([x * z[:, None], z])
            norm = np.linalg.norm(g, axis=1)
            g = g * np.minimum(1, cfg.clip / np.maximum(norm, 1e-12))[:, None]
            w = w - cfg.lr * g.mean(axis=0)
        else:
            fun = optim.logistic(x, y, cfg.l2)
            if cfg.optimiser == "lbfgs":
                w = optim.lbfgs(fun, w, cfg.history, cfg.iters)
            elif cfg.optimiser == "gradient":
                w = optim.gradient_steps(fun, w, cfg.lr, 1)
            else:
                w = optim.sgd(x, y, w, cfg.lr, l2=cfg.l2)
        delta = w - theta
        norm = float(np.linalg.norm(delta))
        first = norm if epoch == 0 else first
        if cfg.unit == "participant" and norm > cfg.clip and (cfg.clip_when == "epoch" or epoch == cfg.epochs - 1):
            clipped = True
            w = theta + optim.project(delta, cfg.clip)
    return w - theta, first, clipped


@dataclass(frozen=True)
class Run:
    """One training: its configuration, the features it uses and how they are scaled."""

    cfg: TrainConfig
    mean: np.ndarray
    scale: np.ndarray
    keep: np.ndarray
    limit: float = 0.0  # of rows that say `until`, those with less aren't this run's

    @property
    def at(self) -> np.ndarray:
        """The trained coordinates; the bias is the last."""
        return np.append(self.keep, self.cfg.features)


def run_of(cfg: TrainConfig, mean: np.ndarray | None = None, scale: np.ndarray | None = None, keep: list[int] | None = None) -> Run:
    return Run(cfg, np.zeros(cfg.features) if mean is None else mean, np.ones(cfg.features) if scale is None else scale, np.arange(cfg.features) if keep is None else np.asarray(sorted(keep)))


def updates(rows: DataFrame, runs: dict[str, Run], theta: dict[str, np.ndarray], round_: int, shared: dict[str, list[str]] | None = None) -> DataFrame:
    """rows (run, participant_id, y, idx, val): (run, participant_id, delta over all coordinates, norm, clipped, n).

    shared: the runs that a run's rows stand for, where they have one cohort; a row with `until` is a run's up to its limit. Who has no row left has no update.
    """
    until = ["until"] if "until" in rows.columns else []

    def local(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        lead, who = key[0].as_py(), key[1].as_py()
        table = table.combine_chunks()
        names = [lead] if shared is None else shared[lead]
        dense, truth = _dense(table["idx"].chunk(0), table["val"].chunk(0), runs[names[0]].cfg.features), table["y"].to_numpy().astype(float)
        out = []
        for name in names:
            run = runs[name]
            cfg, at, x, y = run.cfg, run.at, dense, truth
            if until:
                mine = table["until"].to_numpy() >= run.limit
                x, y = x[mine], y[mine]
            if not len(y):
                continue
            x = ((x - run.mean) / run.scale)[:, run.keep]
            got, norm, clipped = local_update(x, y, theta[name][at], cfg)
            if cfg.placement != "central" and cfg.z:
                # alone, or a share: the expected cohort's shares add up to the server's noise
                share = 1.0 if cfg.placement == "local" else 1 / math.sqrt(max(1.0, cfg.q * cfg.participants))
                got = got + np.array([share * cfg.z * cfg.clip * py_normal(cfg.seed, cfg.placement, round_, who, c) for c in at])
            delta = np.zeros(cfg.features + 1)
            delta[at] = got
            out.append((name, who, delta, norm, clipped, len(y)))
        name, who_, delta, norm, clipped, n = zip(*out, strict=True) if out else [()] * 6
        return pa.table({"run": pa.array(name, pa.string()), "participant_id": pa.array(who_, pa.int64()), "delta": pa.array(delta, pa.list_(pa.float64())), "norm": pa.array(norm, pa.float64()), "clipped": pa.array(clipped, pa.bool_()), "n": pa.array(n, pa.int64())})

    return rows.select("run", "participant_id", "y", "idx", "val", *until).groupBy("run", "participant_id").applyInArrow(local, "run string, participant_id long, delta array<double>, norm double, clipped boolean, n long")


def vector_sums(deltas: DataFrame) -> dict[str, tuple[np.ndarray, dict]]:
    """For each run the sum of its vectors and counts: a row from each partition, then from each of about sqrt(partitions), to the driver."""

    def partial(batches):
        total: dict[str, list] = {}
        for b in batches:
            if not b.num_rows:
                continue
            flat = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
            name = np.asarray(b.column(0).to_pylist())
            rest = [b.column(i).to_numpy() for i in range(2, 6)]
            for r in set(name.tolist()):
                mine = name == r
                new = [flat[mine].sum(axis=0), *[v[mine].sum() for v in rest]]
                total[r] = [x + y for x, y in zip(total[r], new, strict=True)] if r in total else new
        for r, (vector, k, clipped, norms, n) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([r]), pa.array([vector.tolist()], pa.list_(pa.float64())), *[pa.array([v], t) for v, t in ((int(k), pa.int64()), (int(clipped), pa.int64()), (float(norms), pa.float64()), (int(n), pa.int64()))]], ["run", "delta", "k", "clipped", "norms", "rows"])

    schema = "run string, delta array<double>, k long, clipped long, norms double, rows long"
    first = deltas.select("run", "delta", F.lit(1).cast("long").alias("k"), F.col("clipped").cast("long").alias("clipped"), F.col("norm").alias("norms"), F.col("n").alias("rows")).mapInArrow(partial, schema)
    width = max(1, math.isqrt(int(deltas.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    out: dict[str, tuple[np.ndarray, dict]] = {}
    for r in first.repartition(width).mapInArrow(partial, schema).collect():  # runs by sqrt(partitions) rows
        vector, seen = out.get(r["run"], (0.0, dict.fromkeys(("k", "clipped", "norms", "rows"), 0)))
        out[r["run"]] = (vector + np.array(r["delta"]), {k: seen[k] + r[k] for k in seen})
    return out


def _groups(live: dict[str, Run], everyone: dict[str, DataFrame], round_: int, apart: bool) -> tuple[DataFrame, dict[str, list[str]]]:
    """The round's (run, participant_id), and the runs that share the rows of each run in it. A cohort is drawn once for all runs that have it, and the Poisson cohorts of one table of participants in one pass."""
    from .participants import cohort_fixed, in_cohort

    alike: dict[tuple, list[str]] = {}
    for name, r in live.items():
        cfg = r.cfg
        fixed = max(1, round(cfg.q * cfg.participants)) if cfg.denominator == "realised" and cfg.q < 1 else 0
        alike.setdefault((id(everyone[name]), fixed, cfg.q, "" if cfg.q >= 1 else cfg.seed, cfg.features), []).append(name)
    shared = {n: [n] for n in live} if apart else {names[0]: names for names in alike.values()}
    parts, poisson = [], {}
    for (table, fixed, q, seed, _), names in alike.items():
        own = F.array(*[F.lit(n) for n in names if n in shared])
        if fixed:
            parts.append(cohort_fixed(everyone[names[0]], fixed, round_, seed).select(F.explode(own).alias("run"), "participant_id"))
        else:
            poisson.setdefault(table, (everyone[names[0]], []))[1].append(own if q >= 1 else F.when(in_cohort(q, round_, seed), own))
    for people, picks in poisson.values():
        parts.append(people.select(F.explode(F.flatten(F.array_compact(F.array(*picks)))).alias("run"), "participant_id"))
    return functools.reduce(DataFrame.unionAll, parts), shared


def train_many(runs: dict[str, Run], everyone: dict[str, DataFrame], shards: Shards, packed: DataFrame, theta0: np.ndarray | None = None, ledger=None, noise: Callable[..., float] | None = None, apart: bool = True) -> dict[str, Result]:
    """Independent runs, one job for each round of all of them. everyone: each run's participants; shards maps (run, participant_id) to (run, participant_id, script_id).

    The server's noise is the operating system's; a function of keys (`py_normal`) may stand for it in tests and simulation. The local and the
    distributed placement are simulations: participants' noise is drawn from keys, so that a task may run twice. apart: shards may tell runs
    apart; else runs with one cohort share its rows, and shards meets the first of them.
    """
    from .privacy import SystemNoise

    noise = noise or SystemNoise().normal
    strange = {r.cfg.placement for r in runs.values()} - {"central", "local", "distributed"}
    if strange:
        raise ValueError(f"no placement {strange}")
    out = {name: Result(np.zeros(r.cfg.features + 1) if theta0 is None else theta0.copy()) for name, r in runs.items()}
    live = dict(runs)
    for round_ in range(1, max(r.cfg.rounds for r in runs.values()) + 1):
        live = {n: r for n, r in live.items() if round_ <= r.cfg.rounds}
        if not live:
            break
        groups, shared = _groups(live, everyone, round_, apart)
        rows = shards(groups).join(packed, "script_id")
        deltas = updates(rows, live, {n: out[n].theta for n in live}, round_, shared)
        if any(r.cfg.weights == "rows" for r in live.values()):
            by_rows = [n for n, r in live.items() if r.cfg.weights == "rows"]
            deltas = deltas.withColumn("delta", F.when(F.col("run").isin(by_rows), F.transform("delta", lambda v: v * F.col("n"))).otherwise(F.col("delta")))
        sums = vector_sums(deltas)
        for name, r in list(live.items()):
            cfg, at = r.cfg, r.at
            total, seen = sums.get(name, (np.zeros(cfg.features + 1), dict.fromkeys(("k", "clipped", "norms", "rows"), 0)))
            below = max(seen["rows"], 1) if cfg.weights == "rows" else (cfg.q * cfg.participants if cfg.denominator == "expected" else max(seen["k"], 1))
            total = total / below
            if cfg.z and cfg.placement == "central":
                sigma = cfg.z * cfg.clip / (cfg.q * cfg.participants)
                total[at] += sigma * np.array([noise(cfg.seed, "round", round_, c) for c in at])
            if ledger is not None:
                ledger.charge(f"{name} round {round_}", cfg.q, cfg.z)
            out[name].theta = out[name].theta + total
            moved = float(np.linalg.norm(total)) / max(1e-12, float(np.linalg.norm(out[name].theta)))
            out[name].history.append({"round": round_, "cohort": seen["k"], "clipped_share": seen["clipped"] / max(1, seen["k"]), "mean_norm": seen["norms"] / max(1, seen["k"]), "moved": moved, "theta": out[name].theta.tolist()})
            if cfg.tol and moved < cfg.tol:
                live.pop(name)
    return out


def train(everyone: DataFrame, shards: Shards, packed: DataFrame, cfg: TrainConfig, mean: np.ndarray | None = None, scale: np.ndarray | None = None, keep: list[int] | None = None, **how) -> Result:
    """R rounds of one run. packed: (script_id, y, idx, val) of the training scripts."""
    return train_many({"run": run_of(cfg, mean, scale, keep)}, {"run": everyone}, shards, packed, **how)["run"]


def vector_sum(deltas: DataFrame, size: int) -> tuple[np.ndarray, dict]:
    """Sum of (delta, norm, clipped, n) rows of one run."""
    got = vector_sums(deltas.select(F.lit("one").alias("run"), "delta", "norm", "clipped", "n"))
    return got.get("one", (np.zeros(size), {}))


def fedavg(everyone: DataFrame, shards: Shards, packed: DataFrame, cfg: TrainConfig, **how) -> Result:
    """Plain averaging over a fixed cohort: no clip, no noise."""
    return train(everyone, shards, packed, replace(cfg, z=0.0, clip=math.inf, denominator="realised"), **how)


def refresh(theta: np.ndarray, everyone: DataFrame, shards: Shards, new_packed: DataFrame, cfg: TrainConfig, **how) -> Result:
    """Further rounds from the last model on a new window of scripts."""
    return train(everyone, shards, new_packed, cfg, theta0=theta, **how)


def gradient_round(shard: DataFrame, feats: DataFrame, labels: DataFrame, theta: DataFrame, participants: int, q: float, z: float, clip: float, lr: float, round_: int, seed: str = "sql") -> DataFrame:
    """One round with one full-gradient epoch, all in DataFrame operations: (coord, w) from theta (coord, w); the bias is coord -1.

    Every participant of the cohort has a row for the bias, so clipping and sums need no special case.
    """
    from .hashing import normal

    mine = shard.where(uniform(seed, F.lit(round_), F.col("participant_id")) < q) if q < 1 else shard
    bias = theta.where("coord = -1").select(F.col("w").alias("b"))
    margin = feats.join(F.broadcast(theta.where("coord >= 0")), feats["feature_id"] == theta["coord"]).groupBy("script_id").agg(F.sum(F.col("v") * F.col("w")).alias("m"))
    resid = labels.select("script_id", "y").join(margin, "script_id", "left").crossJoin(F.broadcast(bias)).select("script_id", (1 / (1 + F.exp(-(F.coalesce("m", F.lit(0.0)) + F.col("b")))) - F.col("y")).alias("r"))
    own = mine.join(resid, "script_id")
    n = own.groupBy("participant_id").agg(F.count("*").alias("n"), F.sum("r").alias("s"))
    grad = own.join(feats, "script_id").groupBy("participant_id", F.col("feature_id").alias("coord")).agg(F.sum(F.col("r") * F.col("v")).alias("g"))
    grad = grad.unionByName(n.select("participant_id", F.lit(-1).alias("coord"), F.col("s").alias("g"))).join(n.select("participant_id", "n"), "participant_id").select("participant_id", "coord", (-lr * F.col("g") / F.col("n")).alias("d"))
    norm = grad.groupBy("participant_id").agg(F.sqrt(F.sum(F.col("d") * F.col("d"))).alias("norm"))
    factor = F.when(F.col("norm") > clip, clip / F.col("norm")).otherwise(1.0)
    total = grad.join(norm, "participant_id").groupBy("coord").agg((F.sum(F.col("d") * factor) / (q * participants)).alias("t"))
    noise = normal(seed, "noise", F.lit(round_), F.col("coord")) * (z * clip / (q * participants)) if z else F.lit(0.0)
    return theta.join(total, "coord", "left").select("coord", (F.col("w") + F.coalesce("t", F.lit(0.0)) + noise).alias("w"))


def sql_gradient_round(prev: str, name: str, participants: int, q: float, z: float, clip: float, lr: float, round_: int, seed: str = "sql") -> str:
    """DuckDB CTEs of gradient_round over shard, feats, labelled and the model `prev`."""
    from .hashing import sql_normal, sql_uniform

    noise = f"{sql_normal(repr(seed), repr('noise'), str(round_), 't.coord')} * {z * clip / (q * participants)!r}" if z else "0.0"
    where = f"WHERE {sql_uniform(repr(seed), str(round_), 'participant_id')} < {q}" if q < 1 else ""
    p = name
    return f"""{p}_margin AS (SELECT script_id, sum(v * w) AS m FROM feats JOIN {prev} ON feature_id = coord GROUP BY script_id),
{p}_resid AS (SELECT l.script_id, 1 / (1 + exp(-(coalesce(m, 0) + (SELECT w FROM {prev} WHERE coord = -1)))) - y AS r FROM labelled l LEFT JOIN {p}_margin USING (script_id)),
{p}_own AS (SELECT participant_id, script_id, r FROM (SELECT * FROM shard {where}) JOIN {p}_resid USING (script_id)),
{p}_n AS (SELECT participant_id, count(*) AS n, sum(r) AS s FROM {p}_own GROUP BY 1),
{p}_grad AS (SELECT participant_id, coord, -{lr} * g / n AS d FROM (
   SELECT participant_id, feature_id AS coord, sum(r * v) AS g FROM {p}_own JOIN feats USING (script_id) GROUP BY 1, 2
   UNION ALL SELECT participant_id, -1, s FROM {p}_n) JOIN {p}_n USING (participant_id)),
{p}_norm AS (SELECT participant_id, sqrt(sum(d * d)) AS norm FROM {p}_grad GROUP BY 1),
{p}_total AS (SELECT coord, sum(d * CASE WHEN norm > {clip} THEN {clip} / norm ELSE 1.0 END) / {q * participants!r} AS t FROM {p}_grad JOIN {p}_norm USING (participant_id) GROUP BY 1),
{p} AS (SELECT t.coord, t.w + coalesce(x.t, 0.0) + {noise} AS w FROM {prev} t LEFT JOIN {p}_total x USING (coord))"""
