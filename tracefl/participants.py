"""Participants, their shards of scripts, cohorts and splits: functions of hashes, so nothing needs to be stored or repeated."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .hashing import uniform


def split(labelled: DataFrame, frac: float = 0.2, stratify: bool = True, seed: str = "split") -> DataFrame:
    """script_id, y, part. Stratified: of each class the ceil(frac * n) scripts of least hash are the test part; else each by its own hash."""
    u = uniform(seed, F.col("script_id"))
    if not stratify:
        return labelled.select("script_id", "y", F.when(u < frac, "test").otherwise("train").alias("part"))
    # each class' cut is the hash of its ceil(frac * n)-th script; the rank is found within hash ranges, so no window holds a class
    r = labelled.select("script_id", "y", u.alias("u"), F.floor(u * 1024).cast("int").alias("cell"))
    cells = r.groupBy("y", "cell").agg(F.count("*").alias("n"))
    w = Window.partitionBy("y").orderBy("cell")
    cells = cells.withColumn("before", F.sum("n").over(w) - F.col("n")).withColumn("quota", F.ceil(F.sum("n").over(Window.partitionBy("y")) * frac))
    ranked = r.join(F.broadcast(cells.drop("n")), ["y", "cell"])  # two classes of 1,024 cells
    rank = F.col("before") + F.row_number().over(Window.partitionBy("y", "cell").orderBy("u", "script_id"))
    return ranked.select("script_id", "y", F.when(rank <= F.col("quota"), "test").otherwise("train").alias("part"))


def sites(trace: DataFrame) -> DataFrame:
    """(domain_id, n_scripts, rank, rank_bucket): domains by their scripts, and the bucket by powers of ten."""
    s = trace.groupBy("domain_id").agg(F.count_distinct("script_id").alias("n_scripts"))
    s = s.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n_scripts"), "domain_id")))
    return s.withColumn("rank_bucket", F.pow(F.lit(10), F.ceil(F.log10("rank"))).cast("long"))


def crawl_frame(ranked: DataFrame, top: int, extra: int, lo: int, hi: int, seed: str = "frame") -> DataFrame:
    """The top sites, and `extra` others drawn from the ranks above lo up to hi."""
    tail = ranked.where((F.col("rank") > lo) & (F.col("rank") <= hi)).orderBy(uniform(seed, F.col("domain_id")), "domain_id").limit(extra)
    return ranked.where(F.col("rank") <= top).withColumn("stratum", F.lit("top")).unionByName(tail.withColumn("stratum", F.lit("tail")))


def zipf(ranked: DataFrame, s: float = 1.0) -> DataFrame:
    """Mass rank**-s over its sum, and the interval [lo, hi) of each domain."""
    w = Window.orderBy("rank")
    m = ranked.select("domain_id", "rank", F.pow(F.col("rank").cast("double"), F.lit(-s)).alias("m"))
    total = F.sum("m").over(Window.partitionBy())
    c = F.sum("m").over(w)
    return m.select("domain_id", "rank", (F.col("m") / total).alias("mass"), ((c - F.col("m")) / total).alias("lo"), (c / total).alias("hi"))


CELLS = 4096


def draw(people: DataFrame, cdf: DataFrame, urls: int, seed: str = "draw") -> DataFrame:
    """(participant_id, domain_id): distinct domains of `urls` draws with replacement.

    The range join u in [lo, hi) as an equi-join: an interval is listed in each of the cells that it meets.
    """
    d = people.select("*", F.explode(F.sequence(F.lit(1), F.lit(urls))).alias("i")).withColumn("u", uniform(seed, F.col("participant_id"), F.col("i"))).withColumn("cell", F.floor(F.col("u") * CELLS).cast("int"))
    celled = cdf.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") * CELLS).cast("int"), F.least(F.floor(F.col("hi") * CELLS), F.lit(CELLS - 1)).cast("int"))))
    return d.join(celled, "cell").where("u >= lo and u < hi").select(*people.columns, "domain_id").distinct()


def draw_without(people: DataFrame, cdf: DataFrame, urls: int, seed: str = "gumbel") -> DataFrame:
    """Without replacement: the domains of the greatest log mass + Gumbel. Every participant meets every domain, so for small tables."""
    g = F.log("mass") - F.log(-F.log(uniform(seed, F.col("participant_id"), F.col("domain_id"))))
    w = Window.partitionBy("participant_id").orderBy(F.desc("g"), "domain_id")
    return people.crossJoin(F.broadcast(cdf)).withColumn("g", g).withColumn("r", F.row_number().over(w)).where(F.col("r") <= urls).select("participant_id", "domain_id")


def people(spark: SparkSession, w: int) -> DataFrame:
    return spark.range(w).select(F.col("id").alias("participant_id"))


def in_cohort(q: float, round_: int, seed: str = "cohort") -> Column:
    return uniform(seed, F.lit(round_), F.col("participant_id")) < q


def cohort(everyone: DataFrame, q: float, round_: int, seed: str = "cohort") -> DataFrame:
    """Poisson sample: each participant by its own hash, before anything is joined."""
    return everyone if q >= 1 else everyone.where(in_cohort(q, round_, seed))


def cohort_fixed(everyone: DataFrame, size: int, round_: int, seed: str = "cohort") -> DataFrame:
    return everyone.orderBy(uniform(seed, F.lit(round_), F.col("participant_id")), "participant_id").limit(size)


def shards(drawn: DataFrame, bridge: DataFrame, train: DataFrame) -> DataFrame:
    """(participant_id, script_id): the training scripts on a participant's domains. bridge: (domain_id, script_id)."""
    return drawn.join(bridge.join(train.select("script_id"), "script_id", "left_semi"), "domain_id").select(*[c for c in drawn.columns if c != "domain_id"], "script_id").distinct()


def bridge(trace: DataFrame) -> DataFrame:
    return trace.select("domain_id", "script_id").distinct()


def natural(orders: DataFrame, train: DataFrame) -> DataFrame:
    """The customer of an order as the participant that sees its script."""
    return orders.select(F.col("o_custkey").alias("participant_id"), F.col("o_orderkey").alias("script_id")).join(train.select("script_id"), "script_id", "left_semi")


def describe(shard: DataFrame, labelled: DataFrame) -> DataFrame:
    """Participants, rows and positives for each, in one row."""
    per = shard.join(labelled.select("script_id", "y"), "script_id").groupBy("participant_id").agg(F.count("*").alias("n"), F.sum("y").alias("p"))
    return per.agg(F.count("*").alias("participants"), F.min("n").alias("least"), F.max("n").alias("most"), F.sum("n").cast("long").alias("rows"), F.sum("p").cast("long").alias("positives"), F.count_if(F.col("p") == 0).alias("without_positives"))


def _foreign(seed: str) -> Column:
    """Whether a script has a family that isn't the one assigned to the participant by hash."""
    names = ("canvas", "canvas_font", "webrtc", "audio")
    mine = F.floor(uniform(f"{seed}-family", F.col("participant_id")) * len(names)).cast("int")
    foreign = F.lit(False)
    for i, n in enumerate(names):
        foreign = foreign | (F.col(n) & (mine != i))
    return foreign


def limit_knowledge(shard: DataFrame, labelled: DataFrame, share: float | Column, seed: str = "limited") -> DataFrame:
    """At the rate `share`, participants keep only positives all of whose families are the one assigned to them by hash."""
    limited = uniform(seed, F.col("participant_id")) < share
    return shard.join(labelled, "script_id").where(~(limited & _foreign(seed))).select(*shard.columns)


def known_until(shard: DataFrame, labelled: DataFrame, seed: str = "limited") -> DataFrame:
    """The shard with `until`: limit_knowledge keeps a row for every share up to that."""
    return shard.join(labelled, "script_id").select(*shard.columns, F.when(_foreign(seed), uniform(seed, F.col("participant_id"))).otherwise(1.0).alias("until"))
