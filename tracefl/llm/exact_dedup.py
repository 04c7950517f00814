"""Exact dedup: static binary-fuse filters of an immutable snapshot screen incoming digests.

A text's digest is SHA-256 of it without white space, in UTF-8. ``snapshot`` keeps one row for each digest, and
for each bucket of digests a three-wise binary-fuse filter with 8-bit fingerprints (about 9 bits a
digest, false positives near 1/256). An incoming batch is first grouped by digest (so duplicates
within it are found apart from the snapshot, with partial sums and no group in one place). Its distinct digests
are sent to their bucket's filter; only positives join the snapshot's exact bucket, and the two
representatives' texts are compared byte by byte.

Filters stay in their buckets: nothing of the corpus' size is broadcast or collected.

Defined results: a null text counts as empty, so all empty, null and white-space texts are one group; of equal
texts the row with the most code points stays, then the least key (a null key last). An empty
table gives an empty table.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, buckets, cut_lineage, split_join
from .words import mix

TRIES = 64


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, "")


class BinaryFuse:
    """Static three-wise binary-fuse filter over distinct unsigned 64-bit keys: no false negatives."""

    def __init__(self, seed: int, segment: int, cells: np.ndarray):
        self.seed, self.segment, self.cells = seed, segment, cells

    @staticmethod
    def _slots(h: np.ndarray, segment: int, n_cells: int) -> np.ndarray:
        """Three neighbouring segments of the cells; one slot in each."""
        starts = np.uint64(n_cells // segment - 2)
        at = (((h >> np.uint64(32)) * starts) >> np.uint64(32)) * np.uint64(segment)
        mask = np.uint64(segment - 1)
        return np.stack([at + (h & mask), at + np.uint64(segment) + ((h >> np.uint64(14)) & mask), at + np.uint64(2 * segment) + (mix(h) & mask)]).astype(np.int64)

    @staticmethod
    def _print(h: np.ndarray) -> np.ndarray:
        return (mix(h + np.uint64(0x5851F42D4C957F2D)) & np.uint64(255)).astype(np.uint8)

    @classmethod
    def build(cls, keys: np.ndarray) -> BinaryFuse:
        keys = np.unique(keys.astype(np.uint64))
        n = len(keys)
        segment = 1 << max(2, min(14, int(np.log(max(n, 2)) / np.log(3.33) + 2.25)))
        factor = max(1.125, 0.875 + 0.25 * np.log(1e6) / np.log(max(n, 3)))
        n_cells = (max(3, -(-int(n * factor + 8) // segment) + 2)) * segment
        for seed in range(TRIES):
            h = mix(keys + mix(np.array([seed + 1], np.uint64))[0])
            order = cls._peel(cls._slots(h, segment, n_cells), n_cells)
            if order is not None:
                return cls(seed, segment, cls._fill(h, *order, segment, n_cells))
            if seed % 8 == 7:
                n_cells += segment * max(1, n_cells // segment // 8)
        raise RuntimeError("no filter found")

    @staticmethod
    def _peel(slots: np.ndarray, n_cells: int):
        """Rounds of (keys, their lone cells): in each, the keys that are alone in some cell go."""
        n = slots.shape[1]
        count = np.bincount(slots.ravel(), minlength=n_cells)
        xor = np.zeros(n_cells, np.int64)
        for s in slots:
            np.bitwise_xor.at(xor, s, np.arange(n))
        lone, rounds, gone = np.flatnonzero(count == 1), [], 0
        while len(lone):
            key, where = np.unique(xor[lone], return_index=True)
            rounds.append((key, lone[where]))
            gone += len(key)
            touched = slots[:, key].ravel()
            np.subtract.at(count, touched, 1)
            np.bitwise_xor.at(xor, touched, np.tile(key, 3))
            touched = np.unique(touched)
            lone = touched[count[touched] == 1]
        return (rounds, slots) if gone == n else None

    @classmethod
    def _fill(cls, h, rounds, slots, segment, n_cells):
        cells, prints = np.zeros(n_cells, np.uint8), cls._print(h)
        for key, own in reversed(rounds):  # a round's lone cells belong to no other key of that round or of a later one
            s = slots[:, key]
            cells[own] = 0
            cells[own] = prints[key] ^ cells[s[0]] ^ cells[s[1]] ^ cells[s[2]]
        return cells

    def contains(self, keys: np.ndarray) -> np.ndarray:
        h = mix(keys.astype(np.uint64) + mix(np.array([self.seed + 1], np.uint64))[0])
        s = self._slots(h, self.segment, len(self.cells))
        return (self.cells[s[0]] ^ self.cells[s[1]] ^ self.cells[s[2]]) == self._print(h)

    def to_bytes(self) -> bytes:
        return np.array([self.seed, self.segment], np.int64).tobytes() + self.cells.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> BinaryFuse:
        seed, segment = np.frombuffer(data[:16], np.int64)
        return cls(int(seed), int(segment), np.frombuffer(data, np.uint8, offset=16))


def digests(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(doc_id, chars, sha, incoming) of each row."""
    t = F.coalesce(F.col(text), F.lit(""))
    return docs.select(F.col(key).alias("doc_id"), F.char_length(t).cast("long").alias("chars"), F.unhex(F.sha2(normalised(F.col(text)).cast("binary"), 256)).alias("sha"), F.col("__in").alias("incoming"))


def grouped(rows: DataFrame) -> DataFrame:
    """(sha, keep_id, chars, n) for each digest: the row that stays, and how many there are."""
    best = F.struct((-F.col("chars")).alias("c"), F.col("doc_id").isNull().alias("last"), F.col("doc_id").alias("d"))
    g = rows.groupBy("sha").agg(F.min(best).alias("b"), F.count("*").alias("n"))
    return g.select("sha", F.col("b.d").alias("keep_id"), (-F.col("b.c")).alias("chars"), "n")


def _bucket(n: int) -> Column:
    return F.pmod(F.conv(F.hex(F.substring("sha", 1, 4)), 16, 10).cast("long"), F.lit(n)).cast("int")


def _keys(column: pa.Array) -> np.ndarray:
    return np.array([int.from_bytes(x[4:12], "little") for x in column.to_pylist()], np.uint64)


def snapshot(rows: DataFrame, n_buckets: int) -> tuple[DataFrame, DataFrame]:
    """The immutable part: (bucket, sha, keep_id, chars, n) and its filters (bucket, filter)."""
    kept = grouped(rows).withColumn("bucket", _bucket(n_buckets))

    def build(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        return pa.table({"bucket": pa.array([key[0].as_py()], pa.int32()), "filter": pa.array([BinaryFuse.build(_keys(table["sha"])).to_bytes()], pa.binary())})

    return kept, kept.select("bucket", "sha").groupBy("bucket").applyInArrow(build, "bucket int, filter binary")


def screen(incoming: DataFrame, filters: DataFrame) -> DataFrame:
    """incoming (bucket, sha) with `maybe`: false only if the snapshot doesn't have the digest."""

    def probe(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        hit = BinaryFuse.from_bytes(right["filter"][0].as_py()).contains(_keys(left["sha"])) if right.num_rows and left.num_rows else np.zeros(left.num_rows, bool)
        return pa.table({"sha": left["sha"], "maybe": pa.array(hit)})

    return incoming.select("bucket", "sha").groupBy("bucket").cogroup(filters.groupBy("bucket")).applyInArrow(probe, "sha binary, maybe boolean")


def verified(docs: DataFrame, pairs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Digests of pairs (sha, a, b: the keys of two rows) whose texts are equal byte by byte."""
    wanted = pairs.select("sha", F.explode(F.array_distinct(F.array("a", "b"))).alias("__id"))
    texts = split_join(docs.select(F.col(key).alias("__id"), F.col(text).alias("__text")), wanted, ["__id"])
    texts = texts.select("sha", normalised(F.col("__text")).alias("_t"))
    texts = texts.where(F.unhex(F.sha2(F.col("_t").cast("binary"), 256)) == F.col("sha"))  # keys may repeat
    return texts.groupBy("sha").agg(F.min("_t").alias("x"), F.max("_t").alias("y")).where("x = y").select("sha")


def resolve(docs: DataFrame, batch: Column, text: str = "text", key: str = "doc_id", n_buckets: int | None = None) -> DataFrame:
    """One row for each row of docs: doc_id, keep_id, group_size, kept, text_sha256, and incoming, chars, sha.

    batch: true for rows of the incoming batch; all others are the snapshot. Rows that are equal even in key and
    length are all marked as kept if one is; ``dedup`` keeps one of them.
    """
    n_buckets = n_buckets or buckets(docs.sparkSession)
    # 60 bytes a row, written once: the texts are read and hashed once
    rows = cut_lineage(digests(docs.withColumn("__in", F.coalesce(batch, F.lit(True))), text, key))
    old, filters = snapshot(rows.where("not incoming"), n_buckets)
    new = grouped(rows.where("incoming")).withColumn("bucket", _bucket(n_buckets))
    maybe = screen(new, filters).where("maybe").select("sha")
    positive = new.join(maybe, "sha", "left_semi")
    exact = positive.alias("n").join(old.alias("o"), F.col("n.sha") == F.col("o.sha")).select(F.col("n.sha").alias("sha"), F.col("o.keep_id").alias("a"), F.col("n.keep_id").alias("b"))
    same = verified(docs, exact, text, key).withColumn("same", F.lit(True))
    # a digest's snapshot and batch groups are one if the bytes agree, else (a collision) they stay two
    both = old.withColumn("incoming", F.lit(False)).unionByName(new.withColumn("incoming", F.lit(True))).join(same, "sha", "left")
    best = F.struct((-F.col("chars")).alias("c"), F.col("keep_id").isNull().alias("last"), F.col("keep_id").alias("d"))
    groups = both.withColumn("part", F.when(F.col("same"), F.lit(None)).otherwise(F.col("incoming"))).groupBy("sha", "part").agg(F.min(best).alias("b"), F.sum("n").alias("group_size"))
    groups = groups.select("sha", F.explode(F.when(F.col("part").isNull(), F.array(F.lit(True), F.lit(False))).otherwise(F.array("part"))).alias("incoming"), F.col("b.d").alias("keep_id"), (-F.col("b.c")).alias("best_chars"), "group_size")
    out = split_join(rows, groups, ["sha", "incoming"])
    return out.select("doc_id", "keep_id", "group_size", (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("chars") == F.col("best_chars"))).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"), "incoming", "chars", "sha")


def dedup(docs: DataFrame, batch: Column, text: str = "text", key: str = "doc_id", n_buckets: int | None = None) -> DataFrame:
    """docs without duplicates, whole rows; of rows that tie in key and length as well, one."""
    kept = resolve(docs, batch, text, key, n_buckets).where("kept").select(F.col("doc_id").alias("__id"), F.col("sha").alias("__sha"), F.col("chars").alias("__chars")).distinct()
    rows = docs.withColumns({"__id": F.col(key), "__sha": F.unhex(F.sha2(normalised(F.col(text)).cast("binary"), 256)), "__chars": F.char_length(F.coalesce(F.col(text), F.lit(""))).cast("long")})
    rows = rows.dropDuplicates(["__id", "__sha", "__chars"])  # partial on the map side; the join needs no further exchange
    cond = F.col("d.__id").eqNullSafe(F.col("k.__id")) & (F.col("d.__sha") == F.col("k.__sha")) & (F.col("d.__chars") == F.col("k.__chars"))
    return rows.alias("d").join(kept.alias("k"), cond, "left_semi").select(*docs.columns)
