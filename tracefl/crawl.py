"""Crawls compared: who sees which scripts, how visits end, and what an extension costs a page."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hashing import uniform
from .labels import FAMILIES

#: Share of (script, domain) pairs that each kind of crawl gets to see.
REACH = {"manual": 1.0, "basic": 0.25, "stealth": 0.2}


def hits(bridge: DataFrame, labelled: DataFrame, reach: dict[str, float] | None = None) -> DataFrame:
    """(crawler, script_id, family): positives that a crawl meets on at least one domain."""
    reach = reach or REACH
    who = F.explode(F.array_compact(F.array(*[F.when(uniform("crawl", F.lit(c), F.col("script_id"), F.col("domain_id")) < p, F.lit(c)) for c, p in reach.items()])))
    seen = bridge.join(labelled.where("y = 1"), "script_id").withColumn("crawler", who)
    fam = F.explode(F.array_compact(F.array(*[F.when(F.col(n), F.lit(n)) for n in FAMILIES])))
    return seen.select("crawler", "script_id", fam.alias("family")).distinct()


def coverage(found: DataFrame) -> DataFrame:
    """(crawler, family, scripts), with family null for the distinct total."""
    return found.rollup("crawler", "family").agg(F.count_distinct("script_id").alias("scripts")).where("crawler is not null")


def lift(found: DataFrame, manual: str = "manual", other: str = "basic") -> DataFrame:
    """Relative increase and plain ratio of the distinct totals."""
    t = found.agg(F.count_distinct(F.when(F.col("crawler") == manual, F.col("script_id"))).alias("a"), F.count_distinct(F.when(F.col("crawler") == other, F.col("script_id"))).alias("b"))
    return t.select(((F.col("a") - F.col("b")) / F.col("b")).alias("increase"), (F.col("a") / F.col("b")).alias("ratio"))


def visits(sites: DataFrame, seed: str = "visit") -> DataFrame:
    """(domain_id, status): outcomes by hash, with the published shares of failures and of their causes."""
    u = uniform(seed, F.col("domain_id"))
    return sites.select("domain_id", F.when(u < 0.915, "ok").when(u < 0.915 + 0.085 * 0.643, "http 403").otherwise("other failure").alias("status"))


def outcomes(visited: DataFrame) -> DataFrame:
    return visited.agg(F.count("*").alias("attempted"), (F.count_if(F.col("status") == "ok") / F.count("*")).alias("loaded"), (F.count_if(F.col("status") == "http 403") / F.greatest(F.count_if(F.col("status") != "ok"), F.lit(1))).alias("forbidden_share"))


def overhead(pairs: DataFrame) -> DataFrame:
    """Mean and greatest drop of a page's score (page_id, base, with_ext)."""
    d = F.col("base") - F.col("with_ext")
    return pairs.agg(F.avg(d).alias("mean_drop"), F.max(d).alias("max_drop"))


def trend(labelled: DataFrame, when: DataFrame) -> DataFrame:
    """(period, scripts, positives, per_100k); when: (script_id, ts)."""
    return labelled.join(when, "script_id").groupBy(F.date_trunc("year", "ts").cast("timestamp_ntz").alias("period")).agg(F.count_distinct("script_id").alias("scripts"), F.count_distinct(F.when(F.col("y") == 1, F.col("script_id"))).alias("positives"))
