"""Spark pieces shared by the operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters that separate words.
SPACES = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def buckets(spark: SparkSession) -> int:
    """As many as the session's shuffles have partitions, which the user sizes to the input."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder, which all executors share: the session's, or in local mode, where none is set, a temporary one."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = context.getConf().get("spark.checkpoint.dir")
        if not folder and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="tracefl-checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """checkpoint() in the folder that all executors share."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


@contextmanager
def _freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what runs inside go as soon as it ends; else they stay until the driver happens to collect its garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before) if before is not None else spark.conf.unset(key)


def written(df: DataFrame) -> DataFrame:
    """df as a Parquet table below the checkpoint folder: cuts the lineage like checkpoint(), is smaller on disk, and leaves no shuffle files."""
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    with _freed(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def split_join(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    """Equi-join whose hot keys Spark can split.

    Adaptive execution splits a hot partition only if both sides come straight from
    exchanges of the join's own. A side that was just grouped by the same columns
    would be used as it is; a key of another form makes the exchange anew.
    """
    l_key = F.struct(*[left[c].alias(f"k{i}") for i, c in enumerate(on)])
    r_key = F.struct(*[right[c].alias(f"k{i}") for i, c in enumerate(on)])
    a = left.withColumn("_jk", F.xxhash64(l_key))
    b = right.select(F.xxhash64(r_key).alias("_jk"), *[F.col(c).alias(f"_r_{c}") if c in on else F.col(c) for c in right.columns])
    cond = a["_jk"] == b["_jk"]
    for c in on:
        cond = cond & a[c].eqNullSafe(b[f"_r_{c}"])
    out = a.join(b, cond, how)
    return out.drop("_jk", *[f"_r_{c}" for c in on])


def hash32(*parts: Column | str | int) -> Column:
    """First 32 bits of md5 over the parts, equal in other SQL engines."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, component): connected components of an undirected graph of longs, named by their least node.

    Alternates links from each node's larger neighbours to its least one, and from a
    node to the least of its smaller ones, until every edge is a star. Each round is two
    groupings with partial aggregation and two joins that Spark can split; nothing comes
    to the driver but a count and a hash. Rounds grow with the logarithm of the size.
    """
    e = written(edges.select(F.greatest(a, b).alias("v"), F.least(a, b).alias("u")).where("u < v").distinct())
    state = None
    for _ in range(most_rounds):
        both = e.select(F.explode(F.array(F.struct(F.col("v").alias("n"), F.col("u").alias("m")), F.struct(F.col("u").alias("n"), F.col("v").alias("m")))).alias("x")).select("x.*")
        low = both.groupBy("n").agg(F.min("m").alias("low")).select("n", F.least("n", "low").alias("low"))
        # large star: larger neighbours move to the least of the neighbourhood
        large = split_join(both.where("m > n"), low, ["n"]).select(F.col("m").alias("v"), F.col("low").alias("u")).where("u < v").distinct()
        # small star: a node and its smaller neighbours move to the least of them
        low2 = large.groupBy("v").agg(F.min("u").alias("low"))
        small = split_join(large, low2, ["v"]).select(F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("low").alias("u")), F.struct("v", F.col("low").alias("u")))).alias("e")).select("e.*").where("u < v").distinct()
        e = written(small)
        # stars stay as they are: the edges are settled when their number and hash are
        now = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("v", "u").cast("decimal(20,0)"))).first())
        if now == state or not now[0]:
            break
        state = now
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("v").alias("node"), F.col("u").alias("component")).unionAll(e.select(F.col("u").alias("node"), F.col("u").alias("component")).distinct())


def _partners(key: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """For rows sorted by (key, doc): each row's partner row (-1: none), whether its document is the key's first, and the start of the last run.

    A run is a key's rows of one document. The partner is the last row of the run before, or for a key's first
    run the first row of the run after.
    """
    n = len(key)
    change = np.flatnonzero((key[1:] != key[:-1]) | (doc[1:] != doc[:-1])) + 1
    start = np.concatenate([[0], change])
    same_before = np.zeros(len(start), bool)
    same_before[1:] = key[start[1:]] == key[start[1:] - 1]
    partner = np.where(same_before, start - 1, -1)
    follows = np.zeros(len(start), bool)
    follows[:-1] = same_before[1:]
    after = np.append(start[1:], n)
    partner = np.where(~same_before & follows, after, partner)
    length = np.diff(np.append(start, n))
    return np.repeat(partner, length), np.repeat(~same_before, length), int(start[-1])


def neighbours(rows: DataFrame) -> DataFrame:
    """rows (key long, doc_id, pos int): with `other` and `o_pos`, the neighbour from another document in the order (key, doc_id, pos), and `first`.

    Rows are sorted over range partitions, so a key of any weight spans as many as it needs, and each row is
    compared with its neighbours only. Rows without a neighbour go. Where a key's rows meet the end of a partition, the
    few that found none there look at the rows that stand at partitions' ends.
    """
    kind = rows.schema["doc_id"].dataType.simpleString()
    ordered = rows.select("key", "doc_id", "pos").repartitionByRange(buckets(rows.sparkSession), "key", "doc_id", "pos").sortWithinPartitions("key", "doc_id", "pos")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["key", "doc_id", "pos", "other", "o_pos", "first", "edge"]
        held: list | None = None  # the run that may go on, after the last row before it
        dealt, first_key, doc_type = 0, None, None  # rows of `held` that have been dealt with

        def out(cols: list, partner: np.ndarray, first: np.ndarray, rows_: np.ndarray, edge: bool) -> pa.RecordBatch:
            key, doc, pos = cols
            at = np.maximum(partner[rows_], 0)
            none = partner[rows_] < 0
            return pa.RecordBatch.from_arrays([pa.array(key[rows_]), pa.array(doc[rows_], doc_type), pa.array(pos[rows_]), pa.array(doc[at], doc_type, mask=none), pa.array(pos[at], mask=none), pa.array(first[rows_]), pa.array(np.full(len(rows_), edge))], names)

        for batch in batches:
            if not batch.num_rows:
                continue
            doc_type = batch.column(1).type
            part = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            if held is None:
                held, first_key = part, part[0][0]
                yield out(held, np.full(len(part[0]), -1), np.zeros(len(part[0]), bool), np.array([0]), True)
            else:
                held = [np.concatenate(x) for x in zip(held, part, strict=True)]
            partner, first, last = _partners(held[0], held[1])
            done = np.arange(dealt, last)
            done = done[(partner[done] >= 0) | (held[0][done] == first_key)]
            if len(done):
                yield out(held, partner, first, done, False)
            keep = max(0, last - 1)
            held, dealt = [x[keep:] for x in held], last - keep
        if held is not None:
            partner, first, _ = _partners(held[0], held[1])
            done = np.arange(dealt, len(held[0]))
            yield out(held, partner, first, done, False)
            yield out(held, np.full(len(held[0]), -1), np.zeros(len(held[0]), bool), np.array([len(held[0]) - 1]), True)

    found = written(ordered.mapInArrow(run, f"key long, doc_id {kind}, pos int, other {kind}, o_pos int, first boolean, edge boolean"))
    ends = found.where("edge").select("key", F.col("doc_id").alias("e_doc"), F.col("pos").alias("e_pos")).distinct()  # two rows a partition
    alone = found.where("not edge and other is null").select("key", "doc_id", "pos")
    late = alone.join(F.broadcast(ends), "key").where("doc_id != e_doc").groupBy("key", "doc_id", "pos").agg(F.min(F.struct("e_doc", "e_pos")).alias("o"))
    late = late.select("key", "doc_id", "pos", F.col("o.e_doc").alias("other"), F.col("o.e_pos").alias("o_pos"), F.lit(False).alias("first"))
    out = found.where("not edge and other is not null").select("key", "doc_id", "pos", "other", "o_pos", "first").unionAll(late)
    # keys that may span partitions (two a partition): which document is their first
    least = found.where("not edge").groupBy("key").agg(F.min("doc_id").alias("_least")).join(F.broadcast(ends.select("key").distinct()), "key")  # not a semi-join: that would be pushed below the grouping
    return out.join(F.broadcast(least), "key", "left").withColumn("first", F.coalesce(F.col("doc_id") == F.col("_least"), "first")).drop("_least")
