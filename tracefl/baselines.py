"""What the federated detector is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import optim
from .federated import TrainConfig, _dense, vector_sum
from .hashing import uniform


def centralised(packed: DataFrame, features: int, mean: np.ndarray, scale: np.ndarray, keep: list[int] | None = None, l2: float = 1e-3, iters: int = 40) -> np.ndarray:
    """Distributed L-BFGS over all scripts: each step is one pass that sums losses and gradients by partition."""
    keep_ = np.arange(features) if keep is None else np.asarray(sorted(keep))
    at = np.append(keep_, features)
    rows = packed.select("y", "idx", "val").cache()
    n = rows.count()

    def fun(theta: np.ndarray) -> tuple[float, np.ndarray]:
        def part(batches):
            for b in batches:
                if b.num_rows:
                    x = ((_dense(b.column(1), b.column(2), features) - mean) / scale)[:, keep_]
                    y = b.column(0).to_numpy().astype(float)
                    f, g = optim.logistic(x, y)(theta)
                    yield pa.RecordBatch.from_arrays([pa.array([[*(g * len(y)), f * len(y)]], pa.list_(pa.float64())), pa.array([0.0]), pa.array([False]), pa.array([len(y)], pa.int64())], ["delta", "norm", "clipped", "n"])

        total, _ = vector_sum(rows.mapInArrow(part, "delta array<double>, norm double, clipped boolean, n long"), len(at) + 1)
        g = total[:-1] / n
        g[:-1] += l2 * theta[:-1]
        return total[-1] / n + 0.5 * l2 * float(theta[:-1] @ theta[:-1]), g

    got = optim.lbfgs(fun, np.zeros(len(at)), 10, iters, 1e-6)
    rows.unpersist()
    theta = np.zeros(features + 1)
    theta[at] = got
    return theta


def local_only(shard: DataFrame, packed: DataFrame, test: DataFrame, cfg: TrainConfig, mean: np.ndarray, scale: np.ndarray, keep: list[int] | None = None, iters: int = 25) -> DataFrame:
    """(participant_id, y, score): each participant's own model on the whole test part. test is scored in blocks by the models' one matrix."""
    keep_ = np.arange(cfg.features) if keep is None else np.asarray(sorted(keep))

    def fit(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        x = ((_dense(table["idx"].chunk(0), table["val"].chunk(0), cfg.features) - mean) / scale)[:, keep_]
        w = optim.lbfgs(optim.logistic(x, table["y"].to_numpy().astype(float), cfg.l2), np.zeros(len(keep_) + 1), cfg.history, iters)
        return pa.table({"participant_id": [key[0].as_py()], "w": pa.array([w.tolist()], pa.list_(pa.float64()))})

    models = shard.join(packed, "script_id").select("participant_id", "y", "idx", "val").groupBy("participant_id").applyInArrow(fit, "participant_id long, w array<double>")
    own = [(r["participant_id"], np.array(r["w"])) for r in models.collect()]  # a stated, small sample of participants

    def score(batches):
        for b in batches:
            if b.num_rows:
                x = ((_dense(b.column(1), b.column(2), cfg.features) - mean) / scale)[:, keep_]
                for i, w in own:
                    yield pa.RecordBatch.from_arrays([pa.array([i] * b.num_rows, pa.int64()), b.column(0), pa.array(optim.sigmoid(x @ w[:-1] + w[-1]))], ["participant_id", "y", "score"])

    return test.select(F.col("y").cast("int").alias("y"), "idx", "val").mapInArrow(score, "participant_id long, y int, score double")


def rules_only(labelled: DataFrame, truth: DataFrame) -> DataFrame:
    """The rules as a detector against another truth (script_id, truth)."""
    j = labelled.select("script_id", "y").join(truth, "script_id")
    return j.agg(F.count_if((F.col("y") == 1) & (F.col("truth") == 1)).alias("tp"), F.count_if((F.col("y") == 1) & (F.col("truth") == 0)).alias("fp"), F.count_if((F.col("y") == 0) & (F.col("truth") == 1)).alias("fn"))


def blocklist(docs: DataFrame, known: DataFrame, n: int = 8) -> DataFrame:
    """(doc_id, item_id): documents that hold all words of a known passage in a row.

    An equi-join on runs of n words (of a shorter passage on all its words), never all pairs; where every run is met, the whole
    passage is looked for. Passages without words are in no document.
    """
    words = lambda c: F.filter(F.split(c, r"\s+"), lambda w: w != "")
    grams = lambda a, m: F.transform(F.sequence(F.lit(1), F.size(a) - m + 1), lambda i: F.concat_ws(" ", F.slice(a, i, m)))
    d = docs.select("doc_id", words(F.col("text")).alias("w"))
    k = known.select("item_id", words(F.col("text")).alias("w")).where(F.size("w") > 0).withColumn("m", F.least(F.size("w"), F.lit(n)))
    runs = k.select("item_id", "m", F.array_distinct(grams(F.col("w"), F.col("m"))).alias("g"))
    lengths = F.array(*[F.lit(r["m"]) for r in k.select("m").distinct().collect()] or [F.lit(n)])  # n lengths at most
    own = d.select("doc_id", "w", F.explode(lengths).alias("m")).where(F.size("w") >= F.col("m"))
    own = own.select("doc_id", F.explode(F.array_distinct(grams(F.col("w"), F.col("m")))).alias("g"))
    met = own.join(runs.select("item_id", F.size("g").alias("runs"), F.explode("g").alias("g")), "g").groupBy("doc_id", "item_id", "runs").agg(F.count_distinct("g").alias("n")).where("n = runs")
    whole = lambda df, key, to: df.select(key, F.concat(F.lit(" "), F.concat_ws(" ", "w"), F.lit(" ")).alias(to))
    held = met.select("doc_id", "item_id").join(whole(d, "doc_id", "t"), "doc_id").join(whole(k, "item_id", "p"), "item_id")
    return held.where(F.contains("t", "p")).select("doc_id", "item_id").distinct()


def prior_scorer(scripts: DataFrame, seed: str = "prior") -> DataFrame:
    """A hash as the score: its area is about the prevalence."""
    return scripts.select("script_id", "y", uniform(seed, F.col("script_id")).alias("score"))


def static_features(docs: DataFrame, buckets: int = 256, n: int = 2) -> DataFrame:
    """(script_id, feature_id, v): hashed token n-grams of the content, the alternative that obfuscation defeats."""
    tokens = F.filter(F.split(F.lower("text"), r"[^a-z0-9]+"), lambda w: w != "")
    pairs = F.transform(F.sequence(F.lit(1), F.greatest(F.size("t") - n + 1, F.lit(1))), lambda i: F.concat_ws(" ", F.slice("t", i, n)))
    g = docs.select(F.col("doc_id").alias("script_id"), tokens.alias("t")).where(F.size("t") > 0).select("script_id", F.explode(pairs).alias("g"))
    bucket = F.conv(F.substring(F.md5("g"), 1, 8), 16, 10).cast("long") % buckets
    return g.groupBy("script_id", bucket.cast("int").alias("feature_id")).agg(F.count("*").cast("double").alias("v"))


def shape_features(docs: DataFrame, buckets: int = 256) -> DataFrame:
    """(script_id, feature_id, v): counts of word shapes (runs of capitals, small letters and digits by one sign each), hashed."""
    shape = F.regexp_replace(F.regexp_replace(F.regexp_replace("w", r"\p{Lu}+", "A"), r"\p{Ll}+", "a"), r"[0-9]+", "9")
    words = docs.select(F.col("doc_id").alias("script_id"), F.explode(F.split("text", r"\s+")).alias("w")).where("w != ''")
    bucket = F.conv(F.substring(F.md5(shape), 1, 8), 16, 10).cast("long") % buckets
    return words.groupBy("script_id", bucket.cast("int").alias("feature_id")).agg(F.count("*").cast("double").alias("v"))


def fed_tree_histogram(shard: DataFrame, feats: DataFrame, labels: DataFrame, edges: tuple[float, ...] = (0.5, 5.0, 20.0, 60.0)) -> DataFrame:
    """(feature_id, edge, gain): Gini gain of the first split from histograms that participants would send (sums over shards)."""
    rows = shard.join(labels.select("script_id", "y"), "script_id")
    total = rows.agg(F.count("*").alias("n"), F.sum("y").alias("p"))
    above = rows.join(feats, "script_id").select("feature_id", "y", F.explode(F.array(*[F.when(F.col("v") > e, F.lit(e)) for e in edges])).alias("edge")).where("edge is not null")
    g = above.groupBy("feature_id", "edge").agg(F.count("*").alias("rn"), F.sum("y").alias("rp")).crossJoin(F.broadcast(total))
    gini = lambda p, n: F.when(n > 0, 2 * (p / n) * (1 - p / n)).otherwise(0.0)
    left_n, left_p = F.col("n") - F.col("rn"), F.col("p") - F.col("rp")
    gain = gini(F.col("p"), F.col("n")) - F.col("rn") / F.col("n") * gini(F.col("rp"), F.col("rn")) - left_n / F.col("n") * gini(left_p, left_n)
    return g.select("feature_id", "edge", gain.alias("gain"))


def library_models(packed: DataFrame, features: int):
    """The library's logistic regression, linear SVM and decision tree on the same vectors: {name: transform}."""
    from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression
    from pyspark.ml.functions import array_to_vector

    dense = F.transform(F.sequence(F.lit(0), F.lit(features - 1)), lambda i: F.coalesce(F.get("val", F.array_position("idx", i).cast("int") - 1), F.lit(0.0)))
    rows = packed.select("script_id", F.col("y").cast("double").alias("label"), array_to_vector(dense).alias("features"))
    return rows, {"logistic": LogisticRegression(regParam=1e-3, maxIter=50), "svm": LinearSVC(regParam=1e-3, maxIter=50), "tree": DecisionTreeClassifier(maxDepth=5)}
