"""Distributed noise placement: fixed-point updates, masks that cancel in pairs, modular sums, discrete Gaussian shares. A simulation."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SCALE_BITS, MODULUS_BITS = 20, 60


def check(cohort: int, clip: float) -> None:
    """The sum of a cohort must fit in half of the modulus."""
    if cohort * clip * 2**SCALE_BITS >= 2 ** (MODULUS_BITS - 1):
        raise ValueError("the cohort's sum would wrap around the modulus")


def encode(values, scale_bits: int = SCALE_BITS):
    """Fixed point by rounding half up, as a column."""
    return F.round(values * float(1 << scale_bits)).cast("long")


def pair_mask(a, b, coord, seed: str = "mask"):
    """60 bits shared by a pair."""
    text = F.concat_ws("|", F.lit(seed), a.cast("string"), b.cast("string"), coord.cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def mask(updates: DataFrame, cohort: DataFrame, seed: str = "mask", neighbours: int | None = None, ring_size: int = 64) -> DataFrame:
    """updates (participant_id, coord, delta): masked fixed-point values.

    Each participant adds the mask of every pair where it is the lesser and subtracts it where it is the greater.
    neighbours: so many partners on each side in a ring of about ring_size participants, dealt to rings by a hash, instead of all pairs.
    """
    people = cohort.select("participant_id").distinct()
    if neighbours is None:
        pairs = people.alias("a").join(people.alias("b"), F.col("a.participant_id") < F.col("b.participant_id")).select(F.col("a.participant_id").alias("lo"), F.col("b.participant_id").alias("hi"))
    else:
        from pyspark.sql import Window

        rings = max(1, people.count() // ring_size)
        own = Window.partitionBy("ring")
        ring = people.withColumn("ring", F.pmod(F.xxhash64("participant_id"), F.lit(rings)))
        ring = ring.withColumn("i", F.row_number().over(own.orderBy("participant_id")) - 1).withColumn("n", F.count("*").over(own))
        step = ring.withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(neighbours)))).withColumn("to", (F.col("i") + F.col("j")) % F.col("n"))
        pairs = step.alias("x").join(ring.alias("y"), (F.col("x.ring") == F.col("y.ring")) & (F.col("x.to") == F.col("y.i"))).select(F.least("x.participant_id", "y.participant_id").alias("lo"), F.greatest("x.participant_id", "y.participant_id").alias("hi")).where("lo < hi").distinct()
    coords = updates.select("coord").distinct()
    m = pairs.crossJoin(coords).withColumn("m", pair_mask(F.col("lo"), F.col("hi"), F.col("coord"), seed))
    own = m.select(F.col("lo").alias("participant_id"), "coord", F.col("m").alias("s")).unionAll(m.select(F.col("hi"), "coord", -F.col("m")))
    total = own.groupBy("participant_id", "coord").agg(F.sum(F.col("s").cast("decimal(38,0)")).alias("s"))
    modulus = F.lit(1 << MODULUS_BITS).cast("decimal(38,0)")
    j = updates.join(total, ["participant_id", "coord"], "left")
    value = encode(F.col("delta")).cast("decimal(38,0)") + F.coalesce("s", F.lit(0).cast("decimal(38,0)"))
    return j.select("participant_id", "coord", F.pmod(value, modulus).cast("long").alias("masked"))


def unmask(masked: DataFrame) -> DataFrame:
    """(coord, total): the modular sum, which is all that the server sees, centred and decoded."""
    modulus, half = 1 << MODULUS_BITS, 1 << (MODULUS_BITS - 1)
    s = masked.groupBy("coord").agg(F.pmod(F.sum(F.col("masked").cast("decimal(38,0)")), F.lit(modulus).cast("decimal(38,0)")).cast("long").alias("s"))
    return s.select("coord", (F.when(F.col("s") >= half, F.col("s") - modulus).otherwise(F.col("s")) / float(1 << SCALE_BITS)).alias("total"))


def discrete_gaussian(sigma: float, size: int, rng: np.random.Generator) -> np.ndarray:
    """Integers with mass proportional to exp(-x^2 / 2 sigma^2), by rejection from a two-sided geometric."""
    t = math.floor(sigma) + 1
    out: list[np.ndarray] = []
    have = 0
    while have < size:
        n = 2 * (size - have) + 16
        y = rng.geometric(1 - math.exp(-1 / t), n) - 1
        sign = rng.integers(0, 2, n)
        ok = ~((y == 0) & (sign == 1))
        x = np.where(sign == 1, -y, y)
        ok &= rng.random(n) < np.exp(-((np.abs(x) - sigma * sigma / t) ** 2) / (2 * sigma * sigma))
        out.append(x[ok])
        have += int(ok.sum())
    return np.concatenate(out)[:size]
