"""Sparse suffix arrays: repeated passages across documents.

Of each text only the suffixes at content-selected positions are kept: minimisers of its word ``k``-grams, chosen
so that any run of ``least`` words has one among its first ``slack`` words. Two texts that share such a run
keep suffixes there that agree in their next ``least - slack`` words. The kept suffixes are sorted by (those words' hash,
document, position) over range partitions, which equal suffixes in any number may span, and each is compared with its
neighbour from another document. Neighbours' matches on one diagonal are merged to segments.

Segments are then extended left and right. The suffixes at a segment's ends (and all of a segment that is still shorter than
``least``) are extended together with all equal suffixes of other documents: the windows of ``least`` words that begin up to
``slack`` words before them are sorted and compared in the same way. A window that another document has is itself a
proof, and what lies further out belongs to another kept suffix; so the result is exact for every repeat of ``least`` words
or more, whichever documents were neighbours, at a cost in proportion to the text. Positions count words from 0.

Defined results: null, empty and short texts have no passages; repeats within one document don't count;
rows that share a key count as one document; null keys are not compared; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import neighbours, split_join, written
from .words import Block, blocks, grams, minimisers, prefix_sums, span_hashes

LEAST, SLACK, K = 50, 20, 8


def suffix_positions(b: Block, k: int, slack: int) -> np.ndarray:
    """Word positions in the block of the chosen suffixes."""
    at, h = grams(b, k)
    return at[minimisers(h, b.doc[at], slack)] if len(at) else at


def _suffixes(docs: DataFrame, text: str, key: str, least: int, slack: int, k: int) -> DataFrame:
    """(key, doc_id, pos): the kept suffixes that go on for least - slack words, and the hash of those."""
    m = least - slack

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in blocks(batch.column(1)):
                at = suffix_positions(b, k, slack)
                at = at[at + m <= b.first[b.doc[at] + 1]] if len(at) else at
                s = span_hashes(prefix_sums(b.hash), at, at + m)
                doc = b.doc[at]
                yield pa.RecordBatch.from_arrays([pa.array(s.view(np.int64)), batch.column(0).take(pa.array(b.row0 + doc)), pa.array((at - b.first[doc]).astype(np.int32))], ["key", "doc_id", "pos"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.where(F.col(key).isNotNull()).select(F.col(key), F.col(text)).mapInArrow(run, f"key long, doc_id {kind}, pos int")


def _segments(met: DataFrame, kind: str, m: int, least: int) -> DataFrame:
    """(doc_id, a, b, other, o_a, first, keys): a document's neighbours' matches, merged where they overlap on one diagonal with one document.

    keys are of the suffixes to extend: the ends, or all of a segment shorter than `least`.
    """

    def merge(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        pos, o_pos, suffix = table["pos"].to_numpy(), table["o_pos"].to_numpy(), table["key"].to_numpy()
        other = table["other"].combine_chunks().dictionary_encode()
        code, first = other.indices.to_numpy(), table["first"].to_numpy()
        order = np.lexsort((pos, pos - o_pos, code))
        pos, o_pos, code, first, suffix = pos[order], o_pos[order], code[order], first[order], suffix[order]
        new = np.ones(len(pos), bool)
        new[1:] = (code[1:] != code[:-1]) | (pos[1:] - o_pos[1:] != pos[:-1] - o_pos[:-1]) | (pos[1:] > pos[:-1] + m)
        start = np.flatnonzero(new)
        stop = np.append(start[1:], len(pos)) - 1
        keys = [suffix[i : j + 1].tolist() if pos[j] + m - pos[i] < least else [int(suffix[i]), int(suffix[j])] for i, j in zip(start, stop, strict=True)]
        return pa.table({"doc_id": pa.array([key[0].as_py()] * len(start), table["doc_id"].type), "a": pa.array(pos[start], pa.int32()), "b": pa.array(pos[stop] + m, pa.int32()), "other": other.dictionary.take(pa.array(code[start])), "o_a": pa.array(o_pos[start], pa.int32()), "first": pa.array(np.logical_and.reduceat(first, start)), "keys": pa.array(keys, pa.list_(pa.int64()))})

    return met.select("doc_id", "pos", "other", "o_pos", "first", "key").groupBy("doc_id").applyInArrow(merge, f"doc_id {kind}, a int, b int, other {kind}, o_a int, first boolean, keys array<long>")


def _windows(docs: DataFrame, suffixes: DataFrame, text: str, key: str, least: int, slack: int) -> DataFrame:
    """(key, doc_id, pos): hashes of the windows of `least` words that begin at most `slack` words before the suffixes (doc_id, pos)."""
    kind = docs.schema[key].dataType.simpleString()
    lists = suffixes.groupBy(F.col("doc_id").alias("__id")).agg(F.collect_list("pos").alias("marks"))  # bounded by the document's length
    texts = split_join(docs.select(F.col(key).alias("__id"), F.col(text).alias("__text")), lists, ["__id"]).select("__id", "__text", "marks")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = batch.column(2)
            at, flat = np.asarray(marks.offsets), marks.flatten().to_numpy()
            at = at - at[0]
            for b in blocks(batch.column(1)):
                n_marks = np.diff(at[b.row0 : b.row0 + b.n + 1])
                doc = np.repeat(np.arange(b.n), n_marks)
                mark = flat[at[b.row0] : at[b.row0 + b.n]] + b.first[doc]
                step = np.zeros(len(b.hash) + 2, np.int64)
                np.add.at(step, np.minimum(np.maximum(b.first[doc], mark - slack), len(b.hash)), 1)
                np.add.at(step, np.minimum(mark + 1, len(b.hash) + 1), -1)
                start = np.flatnonzero(np.cumsum(step)[: len(b.hash)] > 0)
                start = start[start + least <= b.first[b.doc[start] + 1]]
                own = b.doc[start]
                yield pa.RecordBatch.from_arrays([pa.array(span_hashes(prefix_sums(b.hash), start, start + least).view(np.int64)), batch.column(0).take(pa.array(b.row0 + own)), pa.array((start - b.first[own]).astype(np.int32))], ["key", "doc_id", "pos"])

    return texts.mapInArrow(run, f"key long, doc_id {kind}, pos int")


def passages(docs: DataFrame, least: int = LEAST, slack: int = SLACK, k: int = K, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row for each maximal span of a document that is made of passages of at least `least` words that another document has too:
    doc_id, start_word, end_word, other_id (a document that has its beginning), other_start, first (no lesser key has any of it)."""
    if least - slack < k or slack < k:
        raise ValueError("slack must lie between k and least - k")
    kind, m = docs.schema[key].dataType.simpleString(), least - slack
    met = neighbours(_suffixes(docs, text, key, least, slack, k))
    segments = written(_segments(met, kind, m, least))
    extend = split_join(met.select("key", "doc_id", "pos"), segments.select(F.explode("keys").alias("key")).distinct(), ["key"])
    ends = neighbours(_windows(docs, extend, text, key, least, slack))
    long = segments.where(F.col("b") - F.col("a") >= least).select("doc_id", "a", "b", "other", "o_a", "first")
    spans = long.unionByName(ends.select("doc_id", F.col("pos").alias("a"), (F.col("pos") + least).alias("b"), "other", F.col("o_pos").alias("o_a"), "first"))

    def merge(key_: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        out: list[list] = []
        for a, b, other, o_a, first in sorted(zip(*[table[c].to_pylist() for c in ("a", "b", "other", "o_a", "first")], strict=True), key=lambda r: (r[0], -r[1], r[2])):
            if out and a <= out[-1][1]:
                out[-1][1] = max(out[-1][1], b)
                out[-1][4] = out[-1][4] and first
            else:
                out.append([a, b, other, o_a, first])
        cols = list(zip(*out, strict=True))
        return pa.table({"doc_id": pa.array([key_[0].as_py()] * len(out), table["doc_id"].type), "start_word": pa.array(cols[0], pa.int32()), "end_word": pa.array(cols[1], pa.int32()), "other_id": pa.array(cols[2], table["other"].type), "other_start": pa.array(cols[3], pa.int32()), "first": pa.array(cols[4], pa.bool_())})

    return spans.groupBy("doc_id").applyInArrow(merge, f"doc_id {kind}, start_word int, end_word int, other_id {kind}, other_start int, first boolean")


def cut(docs: DataFrame, spans: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs without the spans' words (each with the white space after it)."""
    columns = docs.columns
    lists = spans.groupBy(F.col(key).alias("__id") if key in spans.columns else F.col("doc_id").alias("__id")).agg(F.array_sort(F.collect_list(F.struct("start_word", "end_word"))).alias("__cut"))
    rows = split_join(docs.withColumn("__id", F.col(key)), lists, ["__id"], "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[str | None] = []
            texts, cuts = batch.column(batch.schema.names.index(text)), batch.column(batch.schema.names.index("__cut")).to_pylist()
            for b in blocks(texts):
                for i in range(b.n):
                    if not cuts[b.row0 + i]:
                        out.append(texts[b.row0 + i].as_py())
                        continue
                    data, start, at = b.bytes_of(i), b.start[b.first[i] : b.first[i + 1]] - b.text_at[i], 0
                    kept = []
                    for c in cuts[b.row0 + i]:
                        kept.append(data[at : int(start[c["start_word"]])])
                        at = int(start[c["end_word"]]) if c["end_word"] < len(start) else len(data)
                    kept.append(data[at:])
                    out.append(b"".join(kept).decode())
            arrays = [pa.array(out, batch.schema.field(text).type) if c == text else batch.column(batch.schema.names.index(c)) for c in columns]
            yield pa.RecordBatch.from_arrays(arrays, columns)

    return rows.mapInArrow(run, docs.schema)
