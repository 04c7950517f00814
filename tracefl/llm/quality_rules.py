"""Quality rules: base counts, and distribution divergence from language references.

For each document two histograms are compared with those of its language by Jensen-Shannon distance (base 2,
so 0 to 1): over character classes, and over the language's common words (one bin for all others). The
references are the sums over all documents of the language, so they follow the corpus; languages without a list
of common words share one reference. A distance counts only from a least number of words on: below it a
histogram is mostly noise, and the document passes.

Everything about one text is found in one vectorised pass over blocks of texts. The references
are 5 languages by about 150 bins whatever the corpus' size, so they may come to the driver.

Defined results: null and empty texts have no words, all counts 0, and fail the base rule; a null or unknown
language is compared with the shared reference of characters and the nearest language's words; a reference without any words passes everything.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import SPACE, Block, blocks, grams, mix, prefix_sums, repeated, span_hashes

# Frequent function words of four languages.
COMMON = {
    "en": "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were her all she there would their we him been has when who will no more if out so".split(),
    "fr": "de la le et les des en un une du que dans est pour qui il au sur par pas plus ne se ce avec sont son cette ou mais comme nous sa aux tout leur ont elle été être fait même ses deux".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei einer um am sind noch wie einem über so zum war haben nur oder".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más o pero sus le ha me si sin sobre este ya entre cuando todo esta ser son dos también fue había era".split(),
}
CLASSES = ("lower", "upper", "digit", "stop", "symbol", "other mark", "space", "line", "beyond ascii")
LANGS = (*COMMON, "*")
_CLASS = np.full(256, 5, np.uint8)
_CLASS[ord("a") : ord("z") + 1] = 0
_CLASS[ord("A") : ord("Z") + 1] = 1
_CLASS[ord("0") : ord("9") + 1] = 2
_CLASS[[ord(c) for c in ".,;:'\"-()?"]] = 3
_CLASS[[ord(c) for c in "#*$%&|<>"]] = 4
_CLASS[[9, 11, 12, 13, 32]] = 6
_CLASS[10] = 7
_CLASS[0xC0:] = 8
_CLASS[0x80:0xC0] = 255  # the rest of a character
_SYMBOL = np.isin(np.arange(256), [ord(c) for c in "#*$%&|<>"])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_EDGE = np.isin(np.arange(256), [ord(c) for c in ".,;:!?\"'()"])


def _hash_words(words: list[str]) -> np.ndarray:
    data = [w.encode() for w in words]
    flat = np.frombuffer(b"".join(data), np.uint8)
    end = np.cumsum([len(d) for d in data])
    return span_hashes(prefix_sums(flat), end - [len(d) for d in data], end)


_TABLES = {lang: np.sort(_hash_words(words)) for lang, words in COMMON.items()}
_TABLES["*"] = np.unique(np.concatenate(list(_TABLES.values())))
BINS = {lang: len(t) + 1 for lang, t in _TABLES.items()}


def base_counts(b: Block) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of each text of a block."""
    n, data = b.n, b.data
    out = {"n_words": np.diff(b.first)}

    def summed(flags: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
        return total[b.text_at[1:]] - total[b.text_at[:-1]]

    out["word_chars"] = summed(~SPACE[data] & ((data & 0xC0) != 0x80))
    out["n_symbols"] = summed(_SYMBOL[data])
    # lines end at a line feed or with their text
    feed = np.flatnonzero(data == 10)
    cut = np.unique(np.concatenate([feed + 1, b.text_at[1:-1], [len(data)]]))
    stop = np.concatenate([cut, [len(data)]])[: len(cut)]
    begin = np.concatenate([[0], cut])[: len(stop)]
    at_feed = np.zeros(len(data) + 1, bool)
    at_feed[feed + 1] = True
    line_end = stop - at_feed[stop]
    ok = line_end > begin
    begin, line_end = begin[ok], line_end[ok]
    has = np.searchsorted(b.start, line_end) > np.searchsorted(b.start, begin)
    begin, line_end = begin[has], line_end[has]
    doc = np.searchsorted(b.text_at, begin, side="right") - 1
    key = mix(span_hashes(b.prefix, begin, line_end) + doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    _, one = np.unique(key, return_index=True)
    out["n_dup_lines"] = np.bincount(doc, minlength=n) - np.bincount(doc[one], minlength=n)
    at, h = grams(b, 8)
    again = at[repeated(mix(h + b.doc[at].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))] if len(at) else at
    step = np.zeros(len(b.hash) + 1, np.int64)
    np.add.at(step, again, 1)
    np.add.at(step, again + 8, -1)
    covered = np.cumsum(step)[:-1] > 0
    out["n_repeat_words"] = np.bincount(b.doc[covered], minlength=n)
    return out


def histograms(b: Block, lang: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Character classes (n by 9) and common words (a row for each text, by its language)."""
    cls = _CLASS[b.data]
    owner = np.repeat(np.arange(b.n), np.diff(b.text_at))
    whole = cls != 255
    chars = np.bincount(owner[whole] * len(CLASSES) + cls[whole], minlength=b.n * len(CLASSES)).reshape(b.n, -1)
    low = _LOWER[b.data]
    start, end = b.start.copy(), b.end.copy()
    for _ in range(3):  # marks around a word aren't part of it
        start += (end - start > 1) & _EDGE[b.data[np.minimum(start, len(b.data) - 1)]]
        end -= (end - start > 1) & _EDGE[b.data[end - 1]]
    h = span_hashes(prefix_sums(low), start, end)
    words: list[np.ndarray] = [np.zeros(0)] * b.n
    for name, table in _TABLES.items():
        mine = np.flatnonzero(lang == name)
        if not len(mine):
            continue
        of = np.isin(b.doc, mine) if len(mine) < b.n else np.ones(len(h), bool)
        at = np.searchsorted(table, h[of])
        at[at == len(table)] = 0
        at = np.where(table[at] == h[of], at, len(table))
        rank = np.full(b.n, -1)
        rank[mine] = np.arange(len(mine))
        got = np.bincount(rank[b.doc[of]] * (len(table) + 1) + at, minlength=len(mine) * (len(table) + 1)).reshape(len(mine), -1)
        for i, row in zip(mine, got, strict=True):
            words[i] = row
    return chars, words


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance (base 2) of each row of counts p from the counts q."""
    p = p / np.maximum(p.sum(axis=1, keepdims=True), 1)
    q = (q / max(q.sum(), 1))[None, :]
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        kl = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1) + np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    return np.sqrt(np.clip(kl / 2, 0, 1))


def nearest(rows: np.ndarray, refs: dict[tuple[str, str], np.ndarray]) -> np.ndarray:
    """Least distance of each row of counts over all languages' common words from a language's reference; 0 if there is none."""
    out = []
    for x in COMMON:
        if refs[x, "words"].sum():
            own = rows[:, np.searchsorted(_TABLES["*"], _TABLES[x])]
            out.append(js_distance(np.column_stack([own, rows.sum(axis=1) - own.sum(axis=1)]), refs[x, "words"]))
    return np.min(out, axis=0) if out else np.zeros(len(rows))


def _lang(column: pa.Array) -> np.ndarray:
    return np.array([x if x in COMMON else "*" for x in column.to_pylist()], object)


def references(docs: DataFrame, text: str = "text", lang: str = "lang") -> dict[tuple[str, str], np.ndarray]:
    """Counts by language and kind ('chars' or 'words') over all documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chars = {x: np.zeros(len(CLASSES), np.int64) for x in LANGS}
        words = {x: np.zeros(BINS[x], np.int64) for x in LANGS}
        for batch in batches:
            langs = _lang(batch.column(1))
            for b in blocks(batch.column(0)):
                mine = langs[b.row0 : b.row0 + b.n]
                c, w = histograms(b, mine)
                for x in set(mine):
                    chars[x] += c[mine == x].sum(axis=0)
                for x, row in zip(mine, w, strict=True):
                    words[x] += row
        rows = [(x, kind, i, int(v)) for kind, part in (("chars", chars), ("words", words)) for x, counts in part.items() for i, v in enumerate(counts) if v]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.string(), pa.string(), pa.int32(), pa.int64()))], ["lang", "kind", "bin", "n"])

    counted = docs.select(F.col(text), F.col(lang)).mapInArrow(count, "lang string, kind string, bin int, n long")
    out = {(x, kind): np.zeros(len(CLASSES) if kind == "chars" else BINS[x], np.float64) for x in LANGS for kind in ("chars", "words")}
    for r in counted.groupBy("lang", "kind", "bin").agg(F.sum("n").alias("n")).collect():  # at most 5 languages by 200 bins
        out[r["lang"], r["kind"]][r["bin"]] = r["n"]
    for x in COMMON:  # the shared reference for characters holds all languages
        out["*", "chars"] += out[x, "chars"]
    return out


def judge(docs: DataFrame, least_words: int = 50, most_chars: float = 0.28, most_words: float = 0.42, text: str = "text", lang: str = "lang", key: str = "doc_id", refs: dict | None = None) -> DataFrame:
    """One row for each document: its key, the base counts, base_failed, the two distances (null below least_words) and kept."""
    refs = refs if refs is not None else references(docs, text, lang)
    kind = docs.schema[key].dataType

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs = _lang(batch.column(2))
            for b in blocks(batch.column(1)):
                mine = langs[b.row0 : b.row0 + b.n]
                c = base_counts(b)
                chars, words = histograms(b, mine)
                d_chars, d_words = np.zeros(b.n), np.zeros(b.n)
                for x in set(mine):
                    of = np.flatnonzero(mine == x)
                    if refs[x, "chars"].sum():
                        d_chars[of] = js_distance(chars[of], refs[x, "chars"])
                    rows = np.stack([words[i] for i in of])
                    if x == "*":
                        d_words[of] = nearest(rows, refs)
                    elif refs[x, "words"].sum():
                        d_words[of] = js_distance(rows, refs[x, "words"])
                base = (c["n_words"] < 20) | (100 * c["n_repeat_words"] > 30 * c["n_words"])
                judged = c["n_words"] >= least_words
                kept = ~base & ~(judged & ((d_chars > most_chars) | (d_words > most_words)))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(b.row0, b.n), *[pa.array(c[k].astype(np.int64)) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], pa.array(base), pa.array(kept), pa.array(d_chars, mask=~judged), pa.array(d_words, mask=~judged)],
                    ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "js_chars", "js_words"],
                )

    schema = f"doc_id {kind.simpleString()}, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, js_chars double, js_words double"
    return docs.select(F.col(key), F.col(text), F.col(lang)).mapInArrow(score, schema)
