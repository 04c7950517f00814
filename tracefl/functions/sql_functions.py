"""User functions for SQL: Arrow functions, a table function for draws, and SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..carriers import order_trace, read
from ..hashing import py_uniform
from ..registry import query


@F.pandas_udf(T.DoubleType())
def sigmoid_score(z: pd.Series) -> pd.Series:
    return 1 / (1 + np.exp(-z))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def clip_vector(v: pd.Series, radius: pd.Series) -> pd.Series:
    def one(x, s):
        x = np.asarray(x, float)
        n = np.linalg.norm(x)
        return (x if n <= s or n == 0 else x * (s / n)).tolist()

    return pd.Series([one(x, s) for x, s in zip(v, radius, strict=True)])


@F.pandas_udf(T.DoubleType())
def auprc_agg(score: pd.Series, y: pd.Series) -> float:
    """Average precision of a group of bounded size (a run's test part); ``metrics.auprc`` has no such bound."""
    g = pd.DataFrame({"s": score, "y": y}).groupby("s")["y"].agg(["sum", "count"]).sort_index(ascending=False)
    tp, n = g["sum"].cumsum(), g["count"].cumsum()
    return float((g["sum"] / max(g["sum"].sum(), 1) * tp / n).sum())


@F.udtf(returnType=T.StructType([T.StructField("participant_id", T.LongType()), T.StructField("i", T.IntegerType()), T.StructField("u", T.DoubleType())]))
class DrawUrls:
    def eval(self, participant_id: int, urls: int) -> Iterator[tuple[int, int, float]]:
        for i in range(1, urls + 1):
            yield participant_id, i, py_uniform("draw", participant_id, i)


def register(spark: SparkSession) -> None:
    spark.udf.register("sigmoid_score", sigmoid_score)
    spark.udf.register("clip_vector", clip_vector)
    spark.udf.register("auprc_agg", auprc_agg)
    spark.udtf.register("draw_urls", DrawUrls)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION zipf_mass(r DOUBLE, s DOUBLE) RETURNS DOUBLE RETURN pow(r, -s)")


@query("udf_sigmoid_score", "SELECT l_orderkey, l_linenumber, round(1 / (1 + exp(-(l_quantity - 25) / 10)), 6) AS p FROM lineitem")
def udf_sigmoid_score(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(sigmoid_score((F.col("l_quantity") - 25) / 10), 6).alias("p"))


@query("udf_clip_vector", "SELECT vec_id, round(least(2.0, sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)))), 4) AS norm FROM embeddings")
def udf_clip_vector(spark: SparkSession, d: str) -> DataFrame:
    c = read(spark, d, "embeddings").select("vec_id", clip_vector(F.col("embedding").cast("array<double>"), F.lit(2.0)).alias("v"))
    return c.select("vec_id", F.round(F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)), 4).alias("norm"))


@query("udf_auprc_agg", "WITH c AS (SELECT c_nationkey, s, sum(y) AS p, count(*) AS c FROM (SELECT c_nationkey, round(c_acctbal / 1000) AS s, CAST(c_mktsegment = 'BUILDING' AS INT) AS y FROM customer) GROUP BY ALL) SELECT c_nationkey, round(sum(p / total * tp / n), 6) AS auprc FROM (SELECT c_nationkey, p, sum(p) OVER w AS tp, sum(c) OVER w AS n, greatest(sum(p) OVER (PARTITION BY c_nationkey), 1) AS total FROM c WINDOW w AS (PARTITION BY c_nationkey ORDER BY s DESC)) GROUP BY 1")
def udf_auprc_agg(spark: SparkSession, d: str) -> DataFrame:
    c = read(spark, d, "customer").select("c_nationkey", F.round(F.col("c_acctbal") / 1000).alias("s"), (F.col("c_mktsegment") == "BUILDING").cast("int").alias("y"))
    return c.groupBy("c_nationkey").agg(F.round(auprc_agg("s", "y"), 6).alias("auprc"))


@query("udtf_draw_urls", "SELECT c_custkey AS participant_id, CAST(i AS INT) AS i, (CAST('0x' || substr(md5(concat_ws('|', 'draw', c_custkey, i)), 1, 8) AS BIGINT) + 0.5) / 4294967296.0 AS u FROM customer, range(1, 6) r(i) WHERE c_custkey <= 100")
def udtf_draw_urls(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    read(spark, d, "customer").where("c_custkey <= 100").createOrReplaceTempView("tf_people")
    return spark.sql("SELECT t.participant_id, t.i, t.u FROM tf_people, LATERAL draw_urls(c_custkey, 5) t")


@query("sqlf_zipf_mass", "SELECT range + 1 AS r, round(pow(range + 1, -1.0), 6) AS m FROM range(100)")
def sqlf_zipf_mass(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    return spark.sql("SELECT id + 1 AS r, round(zipf_mass(CAST(id + 1 AS DOUBLE), 1.0), 6) AS m FROM range(100)")


@query("src_catalog_view", "SELECT CAST(sum(l_quantity) AS BIGINT) AS calls FROM lineitem WHERE l_quantity > 10")
def src_catalog_view(spark: SparkSession, d: str) -> DataFrame:
    order_trace(spark, d).createOrReplaceTempView("tf_trace")
    return spark.sql("SELECT sum(n_calls) AS calls FROM tf_trace WHERE n_calls > :least", args={"least": 10})
