"""Measures: precision-recall areas, threshold measures, repeats, and costs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

CELLS = 4096


def pr_curve(scores: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(score, tp, n, precision, recall) for each distinct score, ties together.

    Scores are first grouped; running sums are taken within cells of the score's range and added to the totals
    of the cells above, so no window holds all scores. Scores lie in [0, 1].
    """
    k = list(keys)
    g = scores.groupBy(*k, "score").agg(F.sum("y").cast("long").alias("p"), F.count("*").alias("c")).withColumn("cell", F.floor(F.col("score") * CELLS).cast("int"))
    above = Window.partitionBy(*k).orderBy(F.desc("cell")).rowsBetween(Window.unboundedPreceding, -1)
    cells = g.groupBy(*k, "cell").agg(F.sum("p").alias("cp"), F.sum("c").alias("cc"))
    cells = cells.select(*k, "cell", F.coalesce(F.sum("cp").over(above), F.lit(0)).alias("p0"), F.coalesce(F.sum("cc").over(above), F.lit(0)).alias("c0"), F.sum("cp").over(Window.partitionBy(*k)).alias("total"))
    w = Window.partitionBy(*k, "cell").orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    r = g.join(cells, [*k, "cell"]).withColumn("tp", F.col("p0") + F.sum("p").over(w)).withColumn("n", F.col("c0") + F.sum("c").over(w))
    return r.select(*k, "score", "p", "tp", "n", "total", (F.col("tp") / F.col("n")).alias("precision"), (F.col("tp") / F.col("total")).alias("recall"))


def auprc(scores: DataFrame, how: str = "step", keys: tuple[str, ...] = (), bins: int = 1000) -> DataFrame:
    """Area under precision-recall: step (average precision), trapezoid, or binned (the step area over `bins` equal score bins)."""
    if how == "binned":
        scores = scores.withColumn("score", F.floor(F.col("score") * bins) / bins)
    curve = pr_curve(scores, keys)
    if how != "trapezoid":
        return curve.groupBy(*keys).agg(F.sum(F.col("p") / F.col("total") * F.col("precision")).alias("auprc"))
    # the point before has tp - p positives of n - c rows; at the first it is the curve's own precision
    w = Window.partitionBy(*keys).orderBy(F.desc("score"))
    c = curve.withColumn("before", F.coalesce(F.lag("precision").over(w), F.col("precision")))
    return c.groupBy(*keys).agg(F.sum(F.col("p") / F.col("total") * (F.col("precision") + F.col("before")) / 2).alias("auprc"))


def at_threshold(scores: DataFrame, t: float) -> DataFrame:
    hit = F.col("score") >= t
    c = scores.agg(F.count_if(hit & (F.col("y") == 1)).alias("tp"), F.count_if(hit & (F.col("y") == 0)).alias("fp"), F.count_if(~hit & (F.col("y") == 1)).alias("fn"), F.count_if(~hit & (F.col("y") == 0)).alias("tn"))
    p, r = F.col("tp") / F.greatest(F.col("tp") + F.col("fp"), F.lit(1)), F.col("tp") / F.greatest(F.col("tp") + F.col("fn"), F.lit(1))
    return c.select("*", p.alias("precision"), r.alias("recall"), (2 * F.col("tp") / F.greatest(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(1))).alias("f1"), (F.col("fp") / F.greatest(F.col("fp") + F.col("tn"), F.lit(1))).alias("fpr"))


def best_threshold(scores: DataFrame, precision: float) -> DataFrame:
    """The least score whose precision is still enough."""
    return pr_curve(scores).where(F.col("precision") >= precision).agg(F.min("score").alias("threshold"), F.max("recall").alias("recall"))


def repeats(runs: DataFrame, keys: list[str], value: str = "auprc") -> DataFrame:
    return runs.groupBy(*keys).agg(F.avg(value).alias("mean"), F.coalesce(F.stddev_samp(value), F.lit(0.0)).alias("std"), F.count("*").alias("runs"))


def within(mean_a: float, std_a: float, mean_b: float, std_b: float, k: float = 2) -> bool:
    """Comparable: the means differ by at most k of the larger deviation."""
    return abs(mean_a - mean_b) <= k * max(std_a, std_b)


def relative(new: float, old: float) -> float:
    """Change in percent of the old value."""
    return 100.0 * (new - old) / old


def footprint(features: int | Column, cohort: int = 100) -> dict[str, int] | dict[str, Column]:
    """Bytes of a model or update (8 for each weight and the bias), and of a round's traffic."""
    one = 8 * (features + 1)
    return {"model_bytes": one, "update_bytes": one, "round_bytes": 2 * one * cohort}


def api_entropy(trace: DataFrame) -> DataFrame:
    """Shannon entropy (bits) of each API's return values."""
    g = trace.groupBy("api", "ret").agg(F.sum("n_calls").alias("n"))
    p = F.col("n") / F.sum("n").over(Window.partitionBy("api"))
    return g.withColumn("p", p).groupBy("api").agg(F.sum(-F.col("p") * F.log2("p")).alias("entropy"))


def anonymity_sets(df: DataFrame, columns: list[str]) -> DataFrame:
    """(set_size, sets, rows): how many rows share a combination of attributes."""
    g = df.groupBy(F.sha2(F.concat_ws("|", *[F.col(c).cast("string") for c in columns]), 256).alias("h")).agg(F.count("*").alias("set_size"))
    return g.groupBy("set_size").agg(F.count("*").alias("sets"), F.sum("set_size").cast("long").alias("rows"))


def unique_signatures(features: DataFrame, bridge: DataFrame) -> DataFrame:
    """Scripts whose combination of APIs occurs on a single domain."""
    sig = features.groupBy("script_id").agg(F.sha2(F.concat_ws(",", F.array_sort(F.collect_set("api"))), 256).alias("signature"))
    d = sig.join(bridge, "script_id").groupBy("signature").agg(F.count_distinct("domain_id").alias("domains"))
    return sig.join(d.where("domains = 1"), "signature").agg(F.count_distinct("script_id").alias("scripts"), F.count_distinct("signature").alias("signatures"))
