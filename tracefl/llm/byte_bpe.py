"""Byte-level BPE encoding and decoding by a global distinct-word shuffle.

Texts are dealt to buckets by a hash. Each bucket's pre-tokens are exploded to its distinct words; those go, packed
by (bucket, place), to the word's place, where each distinct word is encoded once; the ids go back, in the same order, to
the buckets that asked, and a bucket's texts are put together again from them by position. A frequent word so
costs one entry for each bucket, never one for each occurrence, and the vocabulary of a corpus is never
broadcast. The texts move once (the exchange is used twice) and positions never leave their bucket.
Decoding joins the ids with the token-byte table, which has as many rows as the tokenizer (fixed, about
50,000), at each executor.

A bucket is worked on as a whole; their number is the session's shuffle partitions unless given. Buckets are named so that
Spark's hash puts one in each shuffle partition: named 0, 1, ..., some partitions would get several and a third of them none.

Defined results: null and empty texts give no ids and empty bytes; strings of special tokens are ordinary text;
rows need not be distinct; an empty table gives an empty table. Extra columns are carried along if asked for.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import buckets

_NONE = 1 << 60
_loaded: dict[str, dict[bytes, int]] = {}


def ranks(path: str) -> dict[bytes, int]:
    """The vocabulary file, once in each process."""
    if path not in _loaded:
        with open(path, "rb") as f:
            _loaded[path] = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return _loaded[path]


def token_bytes(path: str) -> list[bytes]:
    table = ranks(path)
    out = [b""] * (max(table.values()) + 1)
    for k, v in table.items():
        out[v] = k
    return out


def encode_word(word: bytes, table: dict[bytes, int]) -> list[int]:
    """Byte-pair merges of one pre-token by rank, least rank first, leftmost of equals."""
    whole = table.get(word)
    if whole is not None:
        return [whole]
    parts = [word[i : i + 1] for i in range(len(word))]
    if len(parts) > 400:
        return _encode_long(parts, table)
    rank = [table.get(word[i : i + 2], _NONE) for i in range(len(word) - 1)]
    while rank and (best := min(rank)) != _NONE:
        i = rank.index(best)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del rank[i]
        if i < len(rank):
            rank[i] = table.get(parts[i] + parts[i + 1], _NONE)
        if i:
            rank[i - 1] = table.get(parts[i - 1] + parts[i], _NONE)
    return [table[p] for p in parts]


def _encode_long(parts: list[bytes], table: dict[bytes, int]) -> list[int]:
    """The same with a heap over linked neighbours, for words of any length in n log n."""
    import heapq

    n = len(parts)
    after, before, version = list(range(1, n + 1)), list(range(-1, n - 1)), [0] * n
    heap: list[tuple[int, int, int, int]] = []

    def offer(i: int) -> None:
        j = after[i]
        if j < n and (r := table.get(parts[i] + parts[j])) is not None:
            heapq.heappush(heap, (r, i, version[i], version[j]))

    for i in range(n):
        offer(i)
    alive = [True] * n
    while heap:
        _, i, vi, vj = heapq.heappop(heap)
        j = after[i]
        if not alive[i] or version[i] != vi or j >= n or version[j] != vj:
            continue
        parts[i] += parts[j]
        alive[j] = False
        version[i] += 1
        after[i] = after[j]
        if after[i] < n:
            before[after[i]] = i
        offer(i)
        if before[i] >= 0:
            offer(before[i])
    return [table[p] for p, live in zip(parts, alive, strict=True) if live]


def _chunks(text: str) -> list[str] | None:
    """The text cut before each space, or None where a space is followed by white space or ends the text.

    With patterns that let a word begin with one space, no match crosses a space that stands before other than white space, and
    what comes before it matches as at an end. So equal chunks have equal pre-tokens wherever they stand.
    """
    parts = text.split(" ")
    rest = parts[1:]
    if any(not c or c[0].isspace() for c in set(rest)):
        return None
    return parts


def _tokens(chunks: Iterable[str], find: Callable[[str], list[str]]) -> dict[str, list[str]]:
    """Pre-tokens of each distinct chunk (with the space before it), all found in one text: those that begin with a space begin a chunk."""
    own = list(chunks)
    if not own:
        return {}
    found = find(" " + " ".join(own))
    begin = [i for i, t in enumerate(found) if t[0] == " "]
    if len(begin) != len(own):
        return {c: find(" " + c) for c in own}
    return {c: found[a:b] for c, a, b in zip(own, begin, [*begin[1:], len(found)], strict=True)}


def _placed(words: Iterable[str], n: int) -> dict[int, list[str]]:
    """The words by their place (a hash of the word), sorted: the same for the same words in every run."""
    out: dict[int, list[str]] = {}
    for w in sorted(words):
        out.setdefault(zlib.crc32(w.encode()) % n, []).append(w)
    return out


def _pack(parts: list[bytes]) -> bytes:
    lengths = np.array([len(p) for p in parts], "<u4").tobytes()
    return len(parts).to_bytes(4, "little") + zstandard.ZstdCompressor(level=3).compress(lengths + b"".join(parts))


def _unpack(blob: bytes) -> list[bytes]:
    data = zstandard.ZstdDecompressor().decompress(blob[4:])
    n = int.from_bytes(blob[:4], "little")
    end = np.cumsum(np.frombuffer(data, "<u4", n)) + 4 * n
    return [data[a:b] for a, b in zip([4 * n, *end[:-1].tolist()], end.tolist(), strict=True)] if n else []


def bucket_names(spark: SparkSession, n: int) -> list[int]:
    """n integers, the i-th of which Spark's hash partitioning sends to partition i of n."""
    tried = n * (n.bit_length() + 12)
    while True:
        found = spark.range(tried).select(F.pmod(F.hash(F.col("id").cast("int")), F.lit(n)).alias("p"), "id").groupBy("p").agg(F.min("id")).collect()  # n rows
        if len(found) == n:
            return [i for _, i in sorted(tuple(r) for r in found)]
        tried *= 2


def encode(docs: DataFrame, path: str, pattern: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), digest: bool = False, n_buckets: int | None = None, by_chunk: bool = True) -> DataFrame:
    """keep's columns with n_tokens, ids (little-endian unsigned 32-bit) and decoded (bytes); with digest, SHA-256 of the two instead.

    by_chunk: find pre-tokens once for each distinct chunk between spaces; for patterns that let words begin with a space (see _chunks).
    """
    n = n_buckets or buckets(docs.sparkSession)
    kept = [c for c in keep if c not in ("n_tokens", "ids", "decoded", "ids_sha256", "decoded_sha256", "_bucket", "_text")]
    placed = docs.select(*[F.col(f"`{c}`") for c in kept], F.coalesce(F.col(text), F.lit("")).alias("_text"))
    names_of = F.expr(f"array({', '.join(map(str, bucket_names(docs.sparkSession, n)))})")
    dealt = F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in kept], "_text"), F.lit(n)).cast("int")
    placed = placed.withColumn("_bucket", F.get(names_of, dealt)).repartition(n, "_bucket")
    at = len(kept)

    def distinct_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = regex.compile(pattern).findall
        seen: dict[int, tuple[set[str], set[str]]] = {}
        for batch in batches:
            for t, b in zip(batch.column(at), batch.column(at + 1).to_pylist(), strict=True):
                words, chunks = seen.setdefault(b, (set(), set()))
                parts = _chunks(t.as_py()) if by_chunk else None
                words.update(find(t.as_py() if parts is None else parts[0]))
                chunks.update(parts[1:] if parts else ())
        for b, (words, chunks) in seen.items():
            words.update(*_tokens(chunks, find).values())
            for place, own in _placed(words, n).items():
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([place], pa.int32()), pa.array([_pack([w.encode() for w in own])], pa.binary())], ["bucket", "place", "words"])

    def encode_once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, done = ranks(path), {}
        for batch in batches:
            out = []
            for words in batch.column(2):
                ids = []
                for w in _unpack(words.as_py()):
                    got = done.get(w)
                    if got is None:
                        if len(done) > 500_000:  # a full memory starts anew
                            done.clear()
                        got = done[w] = np.array(encode_word(w, table), "<u4").tobytes()
                    ids.append(got)
                out.append(_pack(ids))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.binary())], ["bucket", "place", "ids"])

    # all columns of `placed`, so that both of its uses share one exchange
    asked = placed.mapInArrow(distinct_words, "bucket int, place int, words binary")
    known = asked.repartition(n, "place").mapInArrow(encode_once, "bucket int, place int, ids binary")

    names = [*kept, "n_tokens", *(("ids_sha256", "decoded_sha256") if digest else ("ids", "decoded"))]

    def reassemble(key: tuple[pa.Scalar, ...], texts: pa.Table, words: pa.Table) -> pa.Table:
        find, table = regex.compile(pattern).findall, token_bytes(path)
        words_: set[str] = set()
        chunks: set[str] = set()
        safe = []  # the cut texts aren't kept: their chunks would be many small strings
        for t in texts["_text"]:
            parts = _chunks(t.as_py()) if by_chunk else None
            safe.append(parts is not None)
            words_.update(find(t.as_py() if parts is None else parts[0]))
            chunks.update(parts[1:] if parts else ())
        parts = None
        tokens = _tokens(chunks, find)
        words_.update(*tokens.values())
        ids_of: dict[str, bytes] = {}
        blobs = dict(zip(words["place"].to_pylist(), words["ids"], strict=True))
        for place, own in _placed(words_, n).items():  # in the order in which they were asked for
            ids_of.update(zip(own, _unpack(blobs[place].as_py()), strict=True))
        join = lambda ws: b"".join(map(ids_of.__getitem__, ws))
        ids_of_chunk = {c: join(ws) for c, ws in tokens.items()}
        del tokens, words_, chunks, blobs
        n_tokens, left, right = [], [], []
        for t, whole in zip(texts["_text"], safe, strict=True):
            parts = t.as_py().split(" ") if whole else [t.as_py()]
            ids = join(find(parts[0])) + b"".join(map(ids_of_chunk.__getitem__, parts[1:]))
            decoded = b"".join(map(table.__getitem__, np.frombuffer(ids, "<u4").tolist()))
            n_tokens.append(len(ids) // 4)
            left.append(hashlib.sha256(ids).hexdigest() if digest else ids)
            right.append(hashlib.sha256(decoded).hexdigest() if digest else decoded)
        kind = pa.string() if digest else pa.binary()
        return pa.table([*[texts[c] for c in kept], pa.array(n_tokens, pa.int64()), pa.array(left, kind), pa.array(right, kind)], names=names)

    ddl = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in kept)
    kind = "string" if digest else "binary"
    return placed.groupBy("_bucket").cogroup(known.groupBy("bucket")).applyInArrow(reassemble, f"{ddl}n_tokens long, {names[at + 1]} {kind}, {names[at + 2]} {kind}")
