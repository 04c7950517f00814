"""How unlike participants' data are: distances of their family histograms from the pooled one, relative to a reference assignment."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labels import FAMILIES


def histogram(shard: DataFrame, labelled: DataFrame, positives: bool = False, keys: tuple[str, ...] = ()) -> DataFrame:
    """(participant_id, family, c, share): families of a participant's scripts, with `none` for the others unless only positives count. A script of several families counts in each."""
    labelled = labelled.where("y = 1") if positives else labelled
    fam = F.array_compact(F.array(*[F.when(F.col(n), F.lit(n)) for n in FAMILIES]))
    rows = shard.join(labelled, "script_id").select(*keys, "participant_id", F.explode(F.when(F.size(fam) == 0, F.array(F.lit("none"))).otherwise(fam)).alias("family"))
    g = rows.groupBy(*keys, "participant_id", "family").agg(F.count("*").alias("c"))
    n = g.groupBy(*keys, "participant_id").agg(F.sum("c").alias("n"))
    return g.join(n, [*keys, "participant_id"]).select(*keys, "participant_id", "family", "c", (F.col("c") / F.col("n")).alias("share"))


def spread(shard: DataFrame, labelled: DataFrame, distance: str = "tv", positives: bool = False, keys: tuple[str, ...] = ()) -> DataFrame:
    """Mean over participants of the distance to the pooled histogram: tv (total variation), hellinger or js (Jensen-Shannon). keys: columns of the shard, few values, each with a row of its own."""
    h = histogram(shard, labelled, positives, keys)
    total = h.groupBy(*keys, "family").agg(F.sum("c").alias("c"))
    beside = lambda left, right: left.join(F.broadcast(right), list(keys)) if keys else left.crossJoin(F.broadcast(right))
    pooled = beside(total, total.groupBy(*keys).agg(F.sum("c").alias("n"))).select(*keys, "family", (F.col("c") / F.col("n")).alias("pool"))
    grid = beside(h.select(*keys, "participant_id").distinct(), pooled).join(h.select(*keys, "participant_id", "family", "share"), [*keys, "participant_id", "family"], "left")  # five families at most
    p, q = F.coalesce("share", F.lit(0.0)), F.col("pool")
    m = (p + q) / 2
    part = {"tv": F.abs(p - q) / 2, "hellinger": F.pow(F.sqrt(p) - F.sqrt(q), 2) / 2, "js": (F.when(p > 0, p * F.log2(p / m)).otherwise(0.0) + F.when(q > 0, q * F.log2(q / m)).otherwise(0.0)) / 2}[distance]
    each = grid.groupBy(*keys, "participant_id").agg(F.sum(part).alias("d"))
    return each.groupBy(*keys).agg(F.avg(F.sqrt("d") if distance != "tv" else F.col("d")).alias("spread"))
