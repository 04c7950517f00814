"""Private federated scaling: noised means and variances of features from participants' capped local statistics.

Sparse throughout: zeros enter through a participant's row count alone. A feature's cohort of each statistic is a Poisson
sample of all participants, independent of every other's. Cohorts are made first, from keys; only the chosen participants' rows
are counted, and only the features they were chosen for are summed. ``drawn_cohorts`` costs as many keys as it draws; ``cohorts`` tests a hash of
each key and can be repeated in SQL.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .features import pack
from .hashing import normal, uniform
from .privacy import SystemNoise

CHUNK = 1 << 16


@dataclass(frozen=True)
class ScaleConfig:
    participants: int
    q: float = 1.0
    z: float = 0.0
    cap_mean: float = 4.0
    cap_var: float = 100.0
    flag_cap_mean: float | None = None  # caps of features with feature_id >= first_flag, whose bounds are known without data
    flag_cap_var: float | None = None
    first_flag: int = 1 << 30
    clip: str = "upper"  # as printed: assumes statistics >= 0; "both" for signed inputs
    pooling: str = "mean_of_local"  # or "moments": mean of local squares less the squared mean
    divisor: str = "stddev"  # or "variance"
    min_scale: float = 0.02
    seed: str = "scale"
    noise: str = "system"  # or "seeded": a function of keys, for tests and simulation; whoever knows the seed can take it away
    off: bool = False


def _cap(c: Column, cap: Column, how: str) -> Column:
    return F.least(c, cap) if how == "upper" else F.greatest(F.least(c, cap), -cap)


def _caps(cfg: ScaleConfig, which: str) -> Column:
    main, flag = (cfg.cap_mean, cfg.flag_cap_mean) if which == "mu" else (cfg.cap_var, cfg.flag_cap_var)
    return F.lit(float(main)) if flag is None else F.when(F.col("feature_id") >= cfg.first_flag, F.lit(float(flag))).otherwise(F.lit(float(main)))


def local_sums(shard: DataFrame, feats: DataFrame) -> DataFrame:
    """(participant_id, feature_id, n, s1, s2): n counts all of the participant's rows."""
    n = shard.groupBy("participant_id").agg(F.count("*").alias("n"))
    s = shard.join(feats, "script_id").groupBy("participant_id", "feature_id").agg(F.sum("v").alias("s1"), F.sum(F.col("v") * F.col("v")).alias("s2"))
    return s.join(n, "participant_id")


def _stats(s: DataFrame, cfg: ScaleConfig, *more: str) -> DataFrame:
    var = F.when(F.col("n") > 1, F.greatest((F.col("s2") - F.col("s1") * F.col("s1") / F.col("n")) / (F.col("n") - 1), F.lit(0.0))).otherwise(0.0)
    return s.select("participant_id", "feature_id", _cap(F.col("s1") / F.col("n"), _caps(cfg, "mu"), cfg.clip).alias("mu"), _cap(var, _caps(cfg, "var"), cfg.clip).alias("var"), _cap(F.col("s2") / F.col("n"), _caps(cfg, "var"), cfg.clip).alias("raw2"), *more)


def local_stats(shard: DataFrame, feats: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """(participant_id, feature_id, mu, var, raw2), capped. A single row has variance 0."""
    return _stats(local_sums(shard, feats), cfg)


def cohorts(people: DataFrame, catalogue: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """(participant_id, in_mu, in_var): the features whose mean's and variance's cohort a participant is in, by hashes. Who is in none is left out."""
    ids = F.array(*[F.lit(r[0]) for r in catalogue.select("feature_id").collect()])  # as many as the catalogue has, whatever the data
    pick = lambda tag: F.filter(ids, lambda f: uniform(cfg.seed, tag, f, F.col("participant_id")) < cfg.q)
    return people.select("participant_id", pick("mu").alias("in_mu"), pick("var").alias("in_var")).where("size(in_mu) + size(in_var) > 0")


def drawn_cohorts(catalogue: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """The same for participants 0 to W - 1, by draws: of each chunk of participants a binomial number, at distinct places. Costs q * W, not W, for each statistic."""
    w, q, seed = cfg.participants, cfg.q, cfg.seed
    chunks = F.sequence(F.lit(0), F.lit(math.ceil(w / CHUNK) - 1))
    keys = catalogue.select("feature_id", F.explode(F.array(F.lit("mu"), F.lit("var"))).alias("tag")).select("feature_id", "tag", F.explode(chunks).alias("chunk"))

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for feature, tag, chunk in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                rng = np.random.default_rng(int.from_bytes(hashlib.md5(f"{seed}|{tag}|{feature}|{chunk}".encode()).digest()))
                n = min(CHUNK, w - chunk * CHUNK)
                who = chunk * CHUNK + rng.choice(n, rng.binomial(n, q), replace=False)
                yield pa.RecordBatch.from_arrays([pa.array(who, pa.int64()), pa.array([feature] * len(who), batch.column(0).type), pa.array([tag] * len(who), pa.string())], ["participant_id", "feature_id", "tag"])

    kind = catalogue.schema["feature_id"].dataType.simpleString()
    drawn = keys.repartition("feature_id", "tag", "chunk").mapInArrow(draw, f"participant_id long, feature_id {kind}, tag string")
    of = lambda tag: F.collect_list(F.when(F.col("tag") == tag, F.col("feature_id")))
    return drawn.groupBy("participant_id").agg(of("mu").alias("in_mu"), of("var").alias("in_var"))


def chosen_stats(shard: DataFrame, packed: DataFrame, picks: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """local_stats of the chosen (participant, feature) keys alone, with take_mu and take_var. packed: (script_id, idx, val)."""
    own = shard.select("participant_id", "script_id").join(picks, "participant_id")
    n = own.groupBy("participant_id").agg(F.count("*").alias("n"))
    either = lambda f: F.array_contains("in_mu", f) | F.array_contains("in_var", f)
    hit = own.join(packed.select("script_id", "idx", "val"), "script_id").select("participant_id", "in_mu", "in_var", F.explode(F.filter(F.arrays_zip("idx", "val"), lambda x: either(x["idx"]))).alias("x"))
    hit = hit.select("participant_id", F.col("x.idx").alias("feature_id"), F.col("x.val").alias("v"), F.array_contains("in_mu", F.col("x.idx")).alias("take_mu"), F.array_contains("in_var", F.col("x.idx")).alias("take_var"))
    s = hit.groupBy("participant_id", "feature_id", "take_mu", "take_var").agg(F.sum("v").alias("s1"), F.sum(F.col("v") * F.col("v")).alias("s2"))
    return _stats(s.join(n, "participant_id"), cfg, "take_mu", "take_var")


def _noise(catalogue: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """(feature_id, g_mu, g_var): a standard normal for each statistic."""
    if cfg.noise == "seeded":
        return catalogue.select("feature_id", *[normal(cfg.seed, f"noise-{t}", F.col("feature_id")).alias(f"g_{t}") for t in ("mu", "var")])
    if cfg.noise != "system":
        raise ValueError(f"no noise of kind {cfg.noise}")
    g = SystemNoise().normal
    rows = [(r[0], g(), g()) for r in catalogue.select("feature_id").collect()]  # drawn once, on the driver: a task that runs twice would draw twice
    kind = catalogue.schema["feature_id"].dataType.simpleString()
    return catalogue.sparkSession.createDataFrame(rows, f"feature_id {kind}, g_mu double, g_var double")


def _long(packed: DataFrame) -> DataFrame:
    return packed.select("script_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("script_id", F.col("p.idx").alias("feature_id"), F.col("p.val").alias("v"))


def fit(shard: DataFrame, feats: DataFrame, catalogue: DataFrame, cfg: ScaleConfig, picks: DataFrame | None = None, sums: DataFrame | None = None) -> DataFrame:
    """(feature_id, mean, var) for every feature of the catalogue, also for those that nobody has: their rows are noise alone.

    feats: (script_id, feature_id, v), or packed (script_id, idx, val). picks: the cohorts, where they were made before the shards. sums: those
    of the chosen keys (participant_id, feature_id, take_mu, take_var, n, s1, s2), where they were made before.
    """
    second = "var" if cfg.pooling == "mean_of_local" else "raw2"
    packed = "idx" in feats.columns
    if cfg.q < 1:
        if sums is not None:
            loc = _stats(sums, cfg, "take_mu", "take_var")
        elif picks is None:  # by hashes of the keys that have values: the others of `cohorts` add nothing
            take = lambda tag: uniform(cfg.seed, tag, F.col("feature_id"), F.col("participant_id")) < cfg.q
            loc = local_stats(shard, _long(feats) if packed else feats, cfg).withColumns({"take_mu": take("mu"), "take_var": take("var")})
        else:
            loc = chosen_stats(shard, feats if packed else pack(feats), picks, cfg)
        mu, var = F.when(F.col("take_mu"), F.col("mu")), F.when(F.col("take_var"), F.col(second))
    else:
        loc, mu, var = local_stats(shard, _long(feats) if packed else feats, cfg), F.col("mu"), F.col(second)
    sums = loc.groupBy("feature_id").agg(F.sum(mu).alias("a"), F.sum(var).alias("b"))
    qw = cfg.q * cfg.participants
    out = catalogue.select("feature_id").join(sums, "feature_id", "left")
    noise = lambda which: F.lit(0.0)
    if cfg.z:
        out = out.join(_noise(catalogue, cfg), "feature_id")
        noise = lambda which: F.col(f"g_{which}") * (_caps(cfg, which) * cfg.z / qw)
    out = out.select("feature_id", (F.coalesce("a", F.lit(0.0)) / qw + noise("mu")).alias("mean"), (F.coalesce("b", F.lit(0.0)) / qw + noise("var")).alias("var"))
    return out if cfg.pooling == "mean_of_local" else out.withColumn("var", F.col("var") - F.col("mean") * F.col("mean"))


def global_stats(feats: DataFrame, catalogue: DataFrame, n: int | Column) -> DataFrame:
    """Centralised exact mean and sample variance over n scripts, zeros included."""
    n = F.lit(n) if isinstance(n, int) else n
    s = feats.groupBy("feature_id").agg(F.sum("v").alias("s1"), F.sum(F.col("v") * F.col("v")).alias("s2"))
    s = catalogue.select("feature_id").join(s, "feature_id", "left").select("feature_id", F.coalesce("s1", F.lit(0.0)).alias("s1"), F.coalesce("s2", F.lit(0.0)).alias("s2"))
    return s.select("feature_id", (F.col("s1") / n).alias("mean"), ((F.col("s2") - F.col("s1") * F.col("s1") / n) / (n - 1)).alias("var"))


def scale_of(var: Column, cfg: ScaleConfig) -> Column:
    """The divisor. Only the square root gives unit variance; the variance itself is the printed form. The floor is post-processing."""
    v = F.greatest(var, F.lit(cfg.min_scale))
    return F.sqrt(v) if cfg.divisor == "stddev" else v


def transform(feats: DataFrame, stats: DataFrame, cfg: ScaleConfig) -> DataFrame:
    """Scaled values of stored features; the zeros' value -mean / scale is left implicit (see ``lazy_offset``)."""
    if cfg.off:
        return feats
    s = stats.select("feature_id", "mean", scale_of(F.col("var"), cfg).alias("scale"))
    return feats.join(F.broadcast(s), "feature_id").select("script_id", "feature_id", ((F.col("v") - F.col("mean")) / F.col("scale")).alias("v"))


def error_report(private: DataFrame, exact: DataFrame) -> DataFrame:
    j = private.alias("p").join(exact.alias("e"), "feature_id")
    return j.agg(F.avg(F.col("p.mean") - F.col("e.mean")).alias("mean_bias"), F.sqrt(F.avg(F.pow(F.col("p.mean") - F.col("e.mean"), 2))).alias("mean_rmse"), F.avg(F.col("p.var") - F.col("e.var")).alias("var_bias"), F.sqrt(F.avg(F.pow(F.col("p.var") - F.col("e.var"), 2))).alias("var_rmse"))
