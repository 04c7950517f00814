"""Vectorised words of text columns.

A word is a maximal run of bytes outside ``[\\x20\\x09-\\x0D]``; as these are ASCII,
splitting UTF-8 bytes equals splitting code points. All functions work on a
bounded block of an Arrow string column at once, so a batch of any size needs
memory for one block only (or for its longest text).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
BLOCK_BYTES = 1 << 20
_BASE = 0x9E3779B97F4A7C15 | 1
_INV = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept between calls."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        grown = np.full(max(n, 1 << 16), base, np.uint64)
        grown[0] = 1
        have = np.cumprod(grown, dtype=np.uint64)
        if n <= 8 << 20:  # one very long text must not stay in memory
            _powers[base] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of the spans [start, end) from the prefix sums of value * base**index."""
    inv = powers(_INV, len(prefix))
    return mix((prefix[end] - prefix[start]) * inv[start] + (end - start).astype(np.uint64))


def prefix_sums(values: np.ndarray) -> np.ndarray:
    out = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values.astype(np.uint64) * powers(_BASE, len(values)) if len(values) else values, out=out[1:], dtype=np.uint64)
    return out


@dataclass
class Block:
    """Texts row0..row1 of a column: their bytes, and the words in them."""

    row0: int
    data: np.ndarray  # uint8, all texts one after the other
    text_at: np.ndarray  # n + 1 byte offsets of the texts
    start: np.ndarray  # byte offsets of the words
    end: np.ndarray
    first: np.ndarray  # n + 1 offsets of each text's words
    doc: np.ndarray  # text of each word
    hash: np.ndarray
    prefix: np.ndarray  # prefix sums over the bytes

    @property
    def n(self) -> int:
        return len(self.text_at) - 1

    def bytes_of(self, i: int) -> bytes:
        return self.data[self.text_at[i] : self.text_at[i + 1]].tobytes()


def _raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    column = column.cast(pa.large_string()) if column.type != pa.large_string() else column
    column = column.fill_null("") if column.null_count else column
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    return at, (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8))


def blocks(column: pa.Array, block_bytes: int = BLOCK_BYTES) -> Iterator[Block]:
    """The column in blocks of about block_bytes; each text is whole in one block. Nulls are empty texts."""
    at, data = _raw(column)
    n, i = len(at) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + block_bytes, side="right")) - 1)
        yield _block(i, data[at[i] : at[j]], at[i : j + 1] - at[i])
        i = j


def _block(row0: int, data: np.ndarray, text_at: np.ndarray) -> Block:
    size = len(data)
    inside = ~SPACE[data]
    begins, ends = inside.copy(), inside.copy()
    if size:
        cut = text_at[1:-1]
        cut = cut[(cut > 0) & (cut < size)]
        begins[1:] &= ~inside[:-1]
        begins[cut] |= inside[cut]
        ends[:-1] &= ~inside[1:]
        ends[cut - 1] |= inside[cut - 1]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    first = np.searchsorted(start, text_at)
    doc = np.repeat(np.arange(len(text_at) - 1), np.diff(first))
    prefix = prefix_sums(data)
    return Block(row0, data, text_at, start, end, first, doc, span_hashes(prefix, start, end), prefix)


def grams(block: Block, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(position of the first word, hash) of each k-word window that lies in one text."""
    n = len(block.hash)
    if n < k:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    at = np.flatnonzero(block.doc[: n - k + 1] == block.doc[k - 1 :])
    if k <= 12:
        h = np.zeros(len(at), np.uint64)
        for j in range(k):
            h = h * np.uint64(0xD6E8FEB86659FD93) + block.hash[at + j]
        return at, mix(h)
    return at, span_hashes(prefix_sums(block.hash), at, at + k)


def repeated(keys: np.ndarray) -> np.ndarray:
    """True where the key occurs twice or more."""
    if len(keys) < 2:
        return np.zeros(len(keys), bool)
    order = np.argsort(keys)
    same = keys[order][1:] == keys[order][:-1]
    out = np.zeros(len(keys), bool)
    out[order[1:][same]] = True
    out[order[:-1][same]] = True
    return out


def minimisers(hashes: np.ndarray, owner: np.ndarray, window: int) -> np.ndarray:
    """Indices chosen as the least hash of some run of `window` neighbours with one owner (all of a shorter run's least)."""
    n = len(hashes)
    if n == 0:
        return np.zeros(0, np.int64)
    edge = np.flatnonzero(np.diff(owner)) + 1
    lo, hi = np.concatenate([[0], edge]), np.concatenate([edge, [n]])
    # sliding minimum by doubling, over windows cut off at the owner's end
    w = 1
    best, value = np.arange(n), hashes.copy()
    last = np.repeat(hi - 1, hi - lo)
    while w < window:
        step = min(w, window - w)
        to = np.minimum(np.arange(n) + step, last)
        other = value[to]
        take = other < value
        best = np.where(take, best[to], best)
        value = np.where(take, other, value)
        w += step
    # a window that is cut off by the end counts only if the run is shorter than a window
    whole = np.arange(n) + window - 1 <= last
    whole[lo] = True
    return np.unique(best[whole])
