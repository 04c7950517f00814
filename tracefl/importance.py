"""Which features carry a model, and how few suffice."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def rank(theta: DataFrame) -> DataFrame:
    """(feature_id, weight, rank) by absolute weight; theta has F rows, so one window is enough."""
    t = theta.where("feature_id >= 0").withColumn("weight", F.abs("w"))
    return t.select("feature_id", "weight", F.dense_rank().over(Window.orderBy(F.desc("weight"))).alias("rank"))


def order(theta: np.ndarray) -> list[int]:
    return sorted(range(len(theta) - 1), key=lambda i: (-abs(theta[i]), i))


def growth(base: list[int], pool: list[int], step: int, most: int, run: Callable[[list[int]], float]) -> list[tuple[int, float]]:
    """(k, measure) of the base set with the next k features of the pool."""
    pool = [i for i in pool if i not in set(base)]
    return [(k, run(sorted([*base, *pool[:k]]))) for k in range(0, most + 1, step)]


def knee(curve: DataFrame, tolerance: float = 0.01) -> DataFrame:
    """The least k whose measure is within the tolerance of the best."""
    best = curve.agg(F.max("auprc").alias("best"))
    return curve.crossJoin(best).where(F.col("auprc") >= F.col("best") - tolerance).agg(F.min("k").alias("k"), F.first("best").alias("best"))


def composition(ids: DataFrame, catalogue: DataFrame) -> DataFrame:
    return catalogue.join(F.broadcast(ids), "feature_id", "left_semi").groupBy("kind").agg(F.count("*").alias("features"))


def association(counts: DataFrame, labelled: DataFrame) -> DataFrame:
    """(api, support, lift, pmi) of an API's use with a positive label."""
    use = counts.select("script_id", "api").join(labelled.select("script_id", "y"), "script_id").groupBy("api").agg(F.count("*").alias("n"), F.sum("y").alias("both"))
    total = labelled.agg(F.count("*").alias("scripts"), F.sum("y").alias("pos"))
    j = use.crossJoin(F.broadcast(total)).withColumn("lift", F.col("both") * F.col("scripts") / (F.col("n") * F.col("pos")))
    return j.select("api", F.col("both").cast("long").alias("support"), "lift", F.when(F.col("lift") > 0, F.log2("lift")).alias("pmi"))
