"""Logistic scores over sparse features, with scaling folded into the weights so that zeros stay implicit."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def weights(spark: SparkSession, theta: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> tuple[DataFrame, float]:
    """(feature_id, w) over raw values, and the offset: sum w (v - mean) / scale + b = sum (w / scale) v + (b - sum w mean / scale)."""
    w = theta[:-1] / scale
    rows = [(int(i), float(v)) for i, v in enumerate(w) if v]
    return spark.createDataFrame(rows or [(-2, 0.0)], "feature_id int, w double"), float(theta[-1] - (theta[:-1] * mean / scale).sum())


def sigmoid(z: Column) -> Column:
    return 1 / (1 + F.exp(-z))


def score(feats: DataFrame, scripts: DataFrame, w: DataFrame, offset: float) -> DataFrame:
    """(script_id, y, score). w has at most F rows, a fixed size, so it may be broadcast."""
    m = feats.join(F.broadcast(w), "feature_id").groupBy("script_id").agg(F.sum(F.col("v") * F.col("w")).alias("m"))
    return scripts.select("script_id", "y").join(m, "script_id", "left").select("script_id", "y", sigmoid(F.coalesce("m", F.lit(0.0)) + F.lit(offset)).alias("score"))


def score_packed(packed: DataFrame, theta: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> DataFrame:
    """The same over packed vectors, without a shuffle."""
    w = theta[:-1] / scale
    offset = float(theta[-1] - (theta[:-1] * mean / scale).sum())
    lit = F.array(*[F.lit(float(x)) for x in w])
    dot = F.aggregate(F.zip_with("idx", "val", lambda i, v: F.get(lit, i) * v), F.lit(0.0), lambda a, x: a + x)
    return packed.select("script_id", "y", sigmoid(dot + F.lit(offset)).alias("score"))


def scores_packed(packed: DataFrame, theta: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> DataFrame:
    """(script_id, y, scores): score_packed of many models, a row of theta, mean and scale each, in one pass."""
    w = (theta[:, :-1] / scale).T
    offset = theta[:, -1] - (theta[:, :-1] * mean / scale).sum(axis=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1 << 12):
                part = batch.slice(at, 1 << 12)
                n = len(idx := part.column(2))
                size = np.diff(np.asarray(idx.offsets))
                z = np.zeros((n, len(offset)))
                if size.any():
                    start = (np.cumsum(size) - size)[size > 0]
                    z[size > 0] = np.add.reduceat(w[idx.flatten().to_numpy()] * part.column(3).flatten().to_numpy()[:, None], start, axis=0)
                z = 1 / (1 + np.exp(-(z + offset)))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * len(offset), pa.int32()), pa.array(z.ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), lists], ["script_id", "y", "scores"])

    kind = packed.schema
    return packed.select("script_id", "y", "idx", "val").mapInArrow(run, f"script_id {kind['script_id'].dataType.simpleString()}, y {kind['y'].dataType.simpleString()}, scores array<double>")


def classify(scores: DataFrame, threshold: float) -> DataFrame:
    return scores.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def log_loss(scores: DataFrame) -> DataFrame:
    p = F.greatest(F.least(F.col("score"), F.lit(1 - 1e-12)), F.lit(1e-12))
    return scores.agg(F.avg(-(F.col("y") * F.ln(p) + (1 - F.col("y")) * F.ln(1 - p))).alias("log_loss"))
