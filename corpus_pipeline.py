"""A corpus pipeline of five stages over `documents`, each written as Parquet before the next reads it.

Defined results: null and empty texts are scored as the classifier's docstring says and, where they pass, are one
group of copies of which one row stays; rows that repeat a key share its fate; a text of under five words is one gram in the near stage; a null source is
a source of its own; empty tables give an empty table; extra columns go along
as far as the mix, and the last stage returns doc_id, source, n_tokens and the two digests.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracefl.llm import byte_bpe, compression, exact_dedup, jaccard_join, mixing
from tracefl.llm.common import shared_folder
from tracefl.llm.queries import incoming, quality_model, tokenizer


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score is 0.3 or more; fitted on the labelled rows of docs."""
    model = quality_model(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return compression.score(docs, model, into="__score").where("__score >= 0.3").select(*[f"`{c}`" for c in docs.columns])


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.dedup(docs, incoming())


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.dedup(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix's rows in the order of their output shards, each shard shuffled; a document that the mix takes twice has two rows."""
    return mixing.in_order(mixing.mix(docs, prefix="__mix_"), "__mix_").select(*[f"`{c}`" for c in docs.columns])


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return byte_bpe.encode(docs, *tokenizer(), keep=("doc_id", "source"), digest=True)


STAGES = [("quality classifier", quality_classifier), ("exact dedup", exact), ("n-gram Jaccard join", near), ("mixing sources", mixed), ("byte-level BPE", encoded)]

#: The classifier, the near duplicates and the tokenizer can't be said in SQL; tests/llm holds brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for i, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if i == len(STAGES) - 1:
            return out
        out.write.parquet(f"{folder}/{i}")
        docs = spark.read.parquet(f"{folder}/{i}")
    return docs
