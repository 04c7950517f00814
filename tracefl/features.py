"""Features of scripts from traces: call counts, custom features, packed vectors, and probes of the catalogue."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .catalogue import AUDIO, FIRST_FLAG, FIRST_PATTERN, NAMED, RETURNS

N_NAMED = len(NAMED)


def call_counts(trace: DataFrame) -> DataFrame:
    """(script_id, api, n): a partial and a final sum over one exchange."""
    return trace.groupBy("script_id", "api").agg(F.sum("n_calls").cast("long").alias("n"))


def call_counts_wide(trace: DataFrame, apis: tuple[str, ...]) -> DataFrame:
    return trace.groupBy("script_id").agg(*[F.coalesce(F.sum(F.when(F.col("api") == a, F.col("n_calls"))), F.lit(0)).cast("long").alias(f"n_{a}") for a in apis])


@dataclass(frozen=True)
class Custom:
    """A feature of a script from its accesses; `default` is its value when the API is never called (none: not admissible)."""

    name: str
    column: Column
    default: float | None = 0.0

    @staticmethod
    def returns(api: str, value: str) -> Custom:
        return Custom(f"{api} returns {value}", F.max(F.when((F.col("api") == api) & (F.col("ret") == value), 1).otherwise(0)))

    @staticmethod
    def arg(api: str, which: str, value: object) -> Custom:
        return Custom(f"{api} {which} is {value}", F.max(F.when((F.col("api") == api) & (F.col(which) == F.lit(value)), 1).otherwise(0)))

    @staticmethod
    def arg_kind(api: str, which: str, pattern: str) -> Custom:
        return Custom(f"{api} {which} like {pattern}", F.max(F.when((F.col("api") == api) & F.col(which).cast("string").rlike(pattern), 1).otherwise(0)))

    @staticmethod
    def arg_length(api: str, which: str) -> Custom:
        return Custom(f"{api} length of {which}", F.max(F.when(F.col("api") == api, F.length(F.col(which).cast("string")))), None)

    @staticmethod
    def arg_distinct(api: str, which: str, exact: bool = True) -> Custom:
        c = F.when(F.col("api") == api, F.col(which))
        return Custom(f"{api} distinct {which}", F.count_distinct(c) if exact else F.approx_count_distinct(c))


def customs(trace: DataFrame, wanted: list[Custom]) -> DataFrame:
    """One column for each custom feature, all from one pass over a script's accesses."""
    return trace.groupBy("script_id").agg(*[(c.column if c.default is None else F.coalesce(c.column, F.lit(c.default))).cast("long").alias(c.name) for c in wanted])


def admissible(catalogue: DataFrame) -> DataFrame:
    """Features that have a value when their API is never called."""
    return catalogue.where("default_value is not null")


def unique_scripts(docs: DataFrame) -> DataFrame:
    """One script for each content, the one of the least id, with the number of its copies."""
    return docs.groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("content")).agg(F.min("doc_id").alias("script_id"), F.count("*").alias("copies"))


def evidence(trace: DataFrame) -> DataFrame:
    """Per script, the calls of each named API and the distinct fonts set: what rules and patterns need, in one aggregate."""
    sums = [F.coalesce(F.sum(F.when(F.col("api_id") == i, F.col("n_calls"))), F.lit(0)).cast("long").alias(f"n_{a}") for i, a in enumerate(NAMED)]
    fonts = F.coalesce(F.max(F.when(F.col("api_id") == NAMED.index("font"), F.col("n_calls"))), F.lit(0)).cast("long").alias("fonts")
    members = F.size(F.collect_set(F.when(F.col("api").isin(*AUDIO), F.col("api")))).cast("long").alias("audio_members")
    return trace.groupBy("script_id").agg(*sums, fonts, members)


def patterns() -> list[Column]:
    """The pattern features in the order of the catalogue, as 0/1 columns over `evidence`."""
    n = lambda *apis: sum((F.col(f"n_{a}") for a in apis), F.lit(0)) > 0
    text, style, export = n("fillText", "strokeText"), n("fillStyle", "strokeStyle"), n("toDataURL")
    out = [text & style, text & export, style & export, F.col("fonts") > 20, F.col("n_measureText") > 20, n("createDataChannel", "createOffer"), n("onicecandidate", "localDescription"), n("save", "restore", "addEventListener"), n("font") & n("measureText")]
    return [c.cast("int") for c in out]


def features_long(trace: DataFrame) -> DataFrame:
    """(script_id, feature_id, v), zeros left out: counts, return flags and patterns over one exchange on the script."""
    t = trace.select("script_id", "api", "api_id", "n_calls", "ret").repartition("script_id")
    counts = t.groupBy("script_id", F.col("api_id").alias("feature_id")).agg(F.sum("n_calls").cast("double").alias("v"))
    ret = F.array_position(F.array(*[F.lit(r) for r in RETURNS]), F.col("ret")) - 1
    flags = t.where((F.col("api_id") < N_NAMED) & (ret >= 0)).select("script_id", (FIRST_FLAG + F.col("api_id") * len(RETURNS) + ret).cast("int").alias("feature_id")).distinct().withColumn("v", F.lit(1.0))
    found = F.filter(F.array(*[F.when(c == 1, F.lit(FIRST_PATTERN + i)) for i, c in enumerate(patterns())]), lambda x: x.isNotNull())
    conj = evidence(t).select("script_id", F.explode(found).alias("feature_id")).withColumn("v", F.lit(1.0))
    return counts.unionByName(flags).unionByName(conj)


def pack(long: DataFrame) -> DataFrame:
    """(script_id, idx, val): sorted sparse vectors."""
    p = long.groupBy("script_id").agg(F.array_sort(F.collect_list(F.struct("feature_id", "v"))).alias("p"))
    return p.select("script_id", F.col("p.feature_id").alias("idx"), F.col("p.v").alias("val"))


def discover_apis(trace: DataFrame, known: DataFrame) -> DataFrame:
    """APIs that are seen but not in an older list."""
    return trace.select("api").distinct().join(known, "api", "left_anti")


def extraction_cost(trace: DataFrame, ids: list[int]) -> DataFrame:
    """Calls and argument bytes that a set's counts need on the device."""
    mine = F.col("api_id").isin(*[i for i in ids if i < FIRST_FLAG])
    bytes_ = F.octet_length(F.concat_ws(",", F.col("arg1").cast("string"), F.col("arg2").cast("string"), F.col("ret"))) * F.col("n_calls")
    return trace.where(mine).agg(F.sum("n_calls").cast("long").alias("calls"), F.sum(bytes_).cast("long").alias("bytes"))
