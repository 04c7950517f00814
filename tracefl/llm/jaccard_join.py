"""N-gram Jaccard join by MinHash banding.

Texts become sets of word n-grams (five words; a text of fewer words is one gram of all of them). Texts with one and
the same set are one class from the start. Of each distinct set a MinHash signature is cut into bands whose
number and rows are chosen for a target recall at the threshold. Band hashes are shuffled with partial
minima; a set is a candidate of the least set in each of its bands (a star: no pairs within a band).
Connected components of these stars bound where links can be, and in each component all pairs are verified
exactly on full n-gram sets: components are cut into chunks, and one task gets two chunks at a time, so a
large group of near copies is split among tasks, and what comes out is a count of links for each set
and the links of a forest, never the pairs. So the sole loss is that of the bands, and within a component not even that.

Classes are the connected components of the verified links; each gets the least key of its rows.

Defined results: null texts and texts without words have the empty set; they are one class with no links (copies of one
set aren't links). Equal rows are copies. A null key is allowed but is never a class name if the class has another. An
empty table gives an empty table.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut_lineage, split_join
from .words import Block, blocks, grams, mix

N = 5
THRESHOLD = 0.8
RECALL = 0.995
CHUNK = 128
CELLS = 4 << 20


def band_plan(threshold: float = THRESHOLD, recall: float = RECALL, most_hashes: int = 128) -> tuple[int, int]:
    """(bands, rows): the most rows, so the fewest idle candidates, whose bands reach the recall at the threshold within most_hashes."""
    best = (most_hashes, 1)
    for rows in range(1, most_hashes + 1):
        hit = threshold**rows
        bands = math.ceil(math.log(1 - recall) / math.log(1 - hit))
        if bands * rows > most_hashes:
            break
        best = (bands, rows)
    return best


def gram_sets(b: Block, n: int = N) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, hashes): each text's distinct n-grams, sorted within the text."""
    at, h = grams(b, n)
    doc = b.doc[at]
    words = np.diff(b.first)
    short = np.flatnonzero((words > 0) & (words < n))
    if len(short):
        whole = np.array([mix(np.array([_fold(b.hash[b.first[i] : b.first[i + 1]])], np.uint64))[0] for i in short], np.uint64)
        h, doc = np.concatenate([h, whole]), np.concatenate([doc, short])
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    if len(h):
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
        h, doc = h[new], doc[new]
    return np.searchsorted(doc, np.arange(b.n + 1)), h


def _fold(h: np.ndarray) -> np.uint64:
    out = np.uint64(len(h))
    with np.errstate(over="ignore"):
        for x in h:
            out = out * np.uint64(0xD6E8FEB86659FD93) + x
    return out


def signatures(offsets: np.ndarray, h: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """Band hashes (sets by bands); sets must not be empty."""
    out = np.zeros((len(offsets) - 1, bands), np.uint64)
    rng = np.random.default_rng(20_240_501)
    for band in range(bands):
        key = np.full(len(offsets) - 1, band, np.uint64)
        for _ in range(rows):
            a, c = rng.integers(1, 1 << 63, 2, dtype=np.uint64)
            x = (h ^ c) * (a | np.uint64(1))
            x ^= x >> np.uint64(29)
            key = mix(key * np.uint64(0xD6E8FEB86659FD93) + np.minimum.reduceat(x * np.uint64(0xBF58476D1CE4E5B9), offsets[:-1]))
        out[:, band] = key
    return out


def _set_keys(offsets: np.ndarray, h: np.ndarray) -> np.ndarray:
    """A 63-bit name for each set: sums of two mixes of its grams."""
    one = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(h), dtype=np.uint64)])
    two = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(h * np.uint64(3) + np.uint64(1)), dtype=np.uint64)])
    size = np.diff(offsets).astype(np.uint64)
    key = mix((one[offsets[1:]] - one[offsets[:-1]]) + mix((two[offsets[1:]] - two[offsets[:-1]]) + size))
    return (key >> np.uint64(1)).astype(np.int64)


def sets_of(docs: DataFrame, text: str = "text", key: str = "doc_id", n: int = N, plan: tuple[int, int] | None = None) -> DataFrame:
    """(doc_id, set, size, bands): the name of each text's n-gram set, its size, and its band hashes (none for the empty set)."""
    bands, rows = plan or band_plan()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in blocks(batch.column(1)):
                offsets, h = gram_sets(b, n)
                size = np.diff(offsets)
                full = np.flatnonzero(size)
                sig = signatures(np.concatenate([offsets[:-1][full], [len(h)]]), h, bands, rows) if len(full) else np.zeros((0, bands), np.uint64)
                at = np.zeros(b.n + 1, np.int32)
                at[1:] = np.cumsum((size > 0) * bands)
                lists = pa.ListArray.from_arrays(pa.array(at), pa.array(sig.ravel().view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(b.row0, b.n), pa.array(_set_keys(offsets, h)), pa.array(size.astype(np.int32)), lists], ["doc_id", "set", "size", "bands"])

    return docs.select(F.col(key), F.col(text)).mapInArrow(run, f"doc_id {docs.schema[key].dataType.simpleString()}, set long, size int, bands array<long>")


def candidates(distinct: DataFrame) -> DataFrame:
    """(a, b): from each set to the least set in each of its bands."""
    banded = distinct.select("set", F.posexplode("bands").alias("band", "h"))
    least = banded.groupBy("band", "h").agg(F.min("set").alias("b"), F.max("set").alias("top")).where("b < top").drop("top")
    return split_join(banded, least, ["band", "h"]).where("set > b").select(F.col("set").alias("a"), "b").distinct()


def overlaps(a_at: np.ndarray, a: np.ndarray, b_at: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of the sets in a with those in b (sets by sets)."""
    na, nb = len(a_at) - 1, len(b_at) - 1
    out = np.zeros((na, nb), np.int64)
    shared = np.intersect1d(a, b)  # grams of one side only can't count
    if not len(shared):
        return out
    pa_, pb_ = np.searchsorted(shared, a), np.searchsorted(shared, b)
    in_a = (pa_ < len(shared)) & (shared[np.minimum(pa_, len(shared) - 1)] == a)
    in_b = (pb_ < len(shared)) & (shared[np.minimum(pb_, len(shared) - 1)] == b)
    da, db = np.repeat(np.arange(na), np.diff(a_at))[in_a], np.repeat(np.arange(nb), np.diff(b_at))[in_b]
    ga, gb = pa_[in_a], pb_[in_b]
    width = max(1, CELLS // (4 * max(na, nb)))
    for lo in range(0, len(shared), width):  # dense, but never more than a few MB at once
        w = min(width, len(shared) - lo)
        x, y = np.zeros((na, w), np.float32), np.zeros((nb, w), np.float32)
        sa, sb = (ga >= lo) & (ga < lo + w), (gb >= lo) & (gb < lo + w)
        x[da[sa], ga[sa] - lo] = 1
        y[db[sb], gb[sb] - lo] = 1
        out += np.rint(x @ y.T).astype(np.int64)
    return out


def _forest(n: int, pairs: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the pairs."""
    root = list(range(n))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for i, j in pairs.tolist():
        x, y = find(i), find(j)
        if x != y:
            root[x] = y
            out.append((i, j))
    return out


def verify(members: DataFrame, threshold: float = THRESHOLD, n: int = N, chunk: int = CHUNK, check: bool = True) -> DataFrame:
    """members (component, set, text): (set, other, n): verified links of a forest (n = 0), and with other null a set's number of links in one pair of chunks. check: rows whose text hasn't the set of their name don't count."""
    counted = members.groupBy("component").agg(F.count("*").alias("m")).withColumn("k", F.ceil(F.col("m") / chunk).cast("int"))
    sized = split_join(members, counted.drop("m"), ["component"]).withColumn("c", F.pmod(F.xxhash64("set"), F.col("k")).cast("int"))
    # chunk c meets every chunk once: as the first of (c, j) for j >= c and as the second of (i, c) for i < c
    dealt = sized.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("k") - 1))).select("component", "set", "text", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), "c")

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        i, j = key[1].as_py(), key[2].as_py()
        sets, side = np.array(table["set"].to_pylist(), np.int64), np.array(table["c"].to_pylist())
        got = [gram_sets(b, n) for b in blocks(table["text"])]
        # rows that repeat a key bring each other's texts: each set counts once, with its own text
        own = np.concatenate([_set_keys(o, x) for o, x in got]) == sets if check else np.ones(len(sets), bool)
        once = np.zeros(len(sets), bool)
        once[np.flatnonzero(own)[np.unique(sets[own], return_index=True)[1]]] = True
        sizes = np.concatenate([np.diff(o) for o, _ in got])
        h = np.concatenate([x for _, x in got])
        at = np.concatenate([[0], np.cumsum(sizes)])

        def part(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            return np.concatenate([[0], np.cumsum(sizes[rows])]), np.concatenate([h[at[r] : at[r + 1]] for r in rows]) if len(rows) else h[:0]

        left = np.flatnonzero((side == i) & once)
        right = left if i == j else np.flatnonzero((side == j) & once)
        both = overlaps(*part(left), *part(right)) if len(left) and len(right) else np.zeros((len(left), len(right)), np.int64)
        total = sizes[left][:, None] + sizes[right][None, :] - both
        ok = both >= threshold * total - 1e-9
        if i == j:
            ok = np.triu(ok, 1)
        x, y = np.nonzero(ok)
        x, y = left[x], right[y]
        links = np.bincount(x, minlength=len(sets)) + np.bincount(y, minlength=len(sets))
        tree = _forest(len(sets), np.stack([x, y], axis=1))
        have = np.flatnonzero(links)
        return pa.table({"set": pa.array([int(sets[a]) for a, _ in tree] + sets[have].tolist(), pa.int64()), "other": pa.array([int(sets[b]) for _, b in tree] + [None] * len(have), pa.int64()), "n": pa.array([0] * len(tree) + links[have].tolist(), pa.int64())})

    return dealt.groupBy("component", "i", "j").applyInArrow(run, "set long, other long, n long")


def join(docs: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL, n: int = N, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row for each row of docs: doc_id, class_id (the least key of its class), n_links (other texts, by distinct set, that it is linked with), copies (rows with its set), set."""
    rows = cut_lineage(sets_of(docs, text, key, n, band_plan(threshold, recall)).select("doc_id", "set", "size", "bands"))
    distinct = rows.where("size > 0").groupBy("set").agg(F.first("bands").alias("bands"))
    comps = cut_lineage(components(candidates(distinct)).withColumnRenamed("node", "set"))
    # one text for each set of a component of two or more
    first = rows.groupBy("set").agg(F.min(F.struct(F.col("doc_id").isNull().alias("z"), "doc_id")).alias("f"), F.count("*").alias("copies")).select("set", F.col("f.doc_id").alias("first_id"), "copies")
    wanted = split_join(comps, first, ["set"]).select("set", "component", F.col("first_id").alias("__id"))
    texts = split_join(docs.select(F.col(key).alias("__id"), F.col(text).alias("text")), wanted, ["__id"])
    found = cut_lineage(verify(texts.select("component", "set", "text"), threshold, n))
    classes = components(found.where("other is not null").select(F.col("set").alias("a"), F.col("other").alias("b"))).withColumnsRenamed({"node": "set", "component": "class"})
    links = found.where("other is null").groupBy("set").agg(F.sum("n").alias("n_links"))
    named = first.join(classes, "set", "left").join(links, "set", "left").withColumn("class", F.coalesce("class", "set"))
    names = named.groupBy("class").agg(F.min(F.struct(F.col("first_id").isNull().alias("z"), "first_id")).alias("f")).select("class", F.col("f.first_id").alias("class_id"))
    per_set = split_join(named, names, ["class"]).select("set", "class_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), "copies")
    return split_join(rows.select("doc_id", "set"), per_set, ["set"]).select("doc_id", "class_id", "n_links", "copies", "set")


def dedup(docs: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL, n: int = N, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs with one document of each class, the one of the least key; keys are taken as unique (rows that repeat a key share its fate)."""
    keep = join(docs, threshold, recall, n, text, key).where(F.col("doc_id").eqNullSafe(F.col("class_id"))).select(F.col("doc_id").alias("__id")).distinct()
    return split_join(docs.withColumn("__id", F.col(key)), keep, ["__id"]).drop("__id")
