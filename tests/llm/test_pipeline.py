"""The pipeline's stages: whole rows between them, decisions that take effect, and edge cases."""

from __future__ import annotations

import collections
import zlib

import pytest

import corpus_pipeline
from tracefl.llm import compression
from tracefl.llm.queries import quality_model

from .test_operators import WORD, exact_groups, jaccard_classes, none, odd, texts  # noqa: F401


def test_stages_against_brute_force(spark, tiny, tmp_path):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    frames = [docs]
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, frames[-1], tiny).write.parquet(f"{tmp_path}/{i}")
        frames.append(spark.read.parquet(f"{tmp_path}/{i}"))
    for f in frames[:-1]:
        assert f.columns == docs.columns
    rows = [texts(f) for f in frames[:-1]]
    model = quality_model(docs, spark.read.parquet(f"{tiny}/labels.parquet"))
    tools = compression._compressors(model.good, model.bad)
    score = lambda t: 1 / (1 + 2.718281828459045 ** -(model.slope * model.difference(t.encode(), *tools) + model.offset))
    assert sorted(rows[1]) == sorted((i, t) for i, t in rows[0] if score(t) >= 0.3)
    groups = exact_groups(rows[1])
    assert sorted(rows[2]) == sorted((i, t) for i, t in rows[1] if groups[i, t][0] == i)
    assert sorted(i for i, _ in rows[3]) == sorted(i for i, c, _ in jaccard_classes(rows[2]) if i == c)
    copies = collections.Counter(i for i, _ in rows[4])
    assert set(copies) <= {i for i, _ in rows[3]} and max(copies.values()) <= 2
    words = sum(len(WORD.findall(t)) for _, t in rows[3])
    assert sum(len(WORD.findall(t)) for _, t in rows[4]) == pytest.approx(1.5 * words, rel=0.1)
    assert frames[-1].count() == len(rows[4]) and frames[-1].where("n_tokens is null or decoded_sha256 is null").count() == 0


def test_run(spark, tiny):
    assert corpus_pipeline.run(spark, tiny).count() > 0


@pytest.mark.parametrize("which", ["odd", "none"])
def test_stages_on_edge_cases(spark, tiny, which, request):
    docs = request.getfixturevalue(which)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, tiny)
        given = texts(docs)
        rows = [(r["doc_id"], r["text"] if "text" in out.columns else None) for r in out.collect()]
        if name == "exact dedup":
            groups = exact_groups(given)
            assert collections.Counter(rows) == collections.Counter((i, t) for i, t in given if groups[i, t or ""][0] == i), name
        elif name == "n-gram Jaccard join":
            assert collections.Counter(i for i, _ in rows) == collections.Counter(i for i, c, _ in jaccard_classes(given) if i == c), name
        elif name == "mixing sources":
            assert set(rows) <= set(given) and max(collections.Counter(rows).values(), default=0) <= 2 * max(collections.Counter(given).values(), default=0), name
        elif name == "byte-level BPE":
            assert sorted(map(str, (i for i, _ in rows))) == sorted(map(str, (i for i, _ in given))), name
        if name != "byte-level BPE":
            assert out.columns == docs.columns
        if which == "none":
            assert out.count() == 0


def test_held_out_rows_are_never_learned(spark, tiny):
    from pyspark.sql import functions as F

    from tracefl.llm.queries import held_out

    ids = spark.read.parquet(f"{tiny}/labels.parquet").where(~held_out()).select(F.col("doc_id")).collect()
    assert all(zlib.crc32(str(r["doc_id"]).encode()) % 5 for r in ids)


def test_shared_folder_is_required_on_clusters():
    """Outside local mode a machine-local folder would lose tables with its machine."""
    from types import SimpleNamespace

    from tracefl.llm.common import shared_folder

    empty = SimpleNamespace(getCheckpointDir=lambda: SimpleNamespace(isEmpty=lambda: True))
    context = SimpleNamespace(_jsc=SimpleNamespace(sc=lambda: empty), getConf=lambda: {}, master="spark://host:7077")
    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        shared_folder(SimpleNamespace(sparkContext=context))


def test_long_sample_texts_are_cut_evenly(spark):
    """The labelled sample reaches the driver in bounded pieces, spread over the whole text."""
    from pyspark.sql import functions as F

    long = "".join(f"{i:08d}" for i in range(64 * 400))
    docs = spark.createDataFrame([(1, long), (2, "short text"), (3, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1), (2, 0), (3, 1)], "doc_id long, quality int")
    got = sorted(compression.sample(docs, labels, F.lit(True), text_chunks=10), key=lambda r: r[1])
    assert [(len(t), y) for t, y in got] == [(10, 0), (5120, 1)]
    pieces = [got[1][0][i : i + 512].decode() for i in range(0, 5120, 512)]
    assert all(p in long for p in pieces) and long.index(pieces[-1]) > 0.8 * len(long)
