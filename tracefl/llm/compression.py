"""Quality classifier by compression: zstandard dictionaries of good and of bad text.

Two dictionaries are built from labelled texts, one for each label. A text is cut into chunks of 512 bytes
(all of it); each chunk is compressed with both, and the difference of the summed sizes over their sum says
which dictionary suits it better. A logistic curve over that difference, fitted on labelled texts that the
dictionaries haven't seen, makes it a probability. Every text counts as if it had some more bytes of the sample's mean difference, so that very
short texts lean to it.

The labelled sample is bounded: at most ``per_label`` rows of each label, those of least hash, and of each text
``text_chunks`` evenly spaced chunks for the curve and ``sample_chunks`` for the dictionaries; all are parameters. Scoring reads every whole text, in the executors, with no shuffle.

Defined results: null and empty texts score as the sample's mean difference does; without labelled rows of both
labels every score is the share of good ones (0.5 without any rows); repeated rows get equal scores; an
empty table gives an empty table.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LEVEL = 12


@dataclass(frozen=True)
class Model:
    good: bytes
    bad: bytes
    slope: float
    offset: float
    chunk: int = 512
    centre: float = 0.0  # the difference that a text without bytes has: the sample's mean
    weight: int = 64  # so many compressed bytes of it are added to every text

    def difference(self, data: bytes, good, bad) -> float:
        """(bytes with the bad dictionary - with the good one) / their sum; the frames' fixed bytes don't count. Short texts lean to the centre."""
        g = b = 0
        for i in range(0, len(data), self.chunk):
            part = data[i : i + self.chunk]
            g += len(good.compress(part)) - 8
            b += len(bad.compress(part)) - 8
        return (b - g + self.weight * self.centre) / max(1, b + g + self.weight)


def _compressors(good: bytes, bad: bytes) -> list:
    out = []
    for d in (good, bad):
        z = zstandard.ZstdCompressionDict(d, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        z.precompute_compress(level=LEVEL)
        out.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=z, write_content_size=False, write_dict_id=False))
    return out


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> tuple[float, float]:
    """Weights of sigmoid(a x + b) by Newton's method; x is scaled first."""
    s = float(np.std(x)) or 1.0
    m = float(np.mean(x))
    z = np.stack([(x - m) / s, np.ones_like(x)], axis=1)
    w = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-z @ w))
        h = (z * (p * (1 - p))[:, None]).T @ z + ridge * len(x) * np.eye(2) + 1e-9 * np.eye(2)
        step = np.linalg.solve(h, z.T @ (y - p) - ridge * len(x) * w * [1, 0])
        w = w + np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-8:
            break
    return w[0] / s, w[1] - w[0] * m / s


def chunks_of(data: bytes, chunk: int, n: int) -> list[bytes]:
    """Up to n chunks, evenly spaced over the whole text."""
    parts = [data[i : i + chunk] for i in range(0, len(data), chunk)]
    return parts if len(parts) <= n else [parts[i * len(parts) // n] for i in range(n)]


def fit(rows: list[tuple[bytes, int]], chunk: int = 512, dictionary_bytes: int = 1 << 19, sample_chunks: int = 16) -> Model:
    """rows: (text, label), a bounded sample. Every other row of a label goes to its dictionary, the rest to the curve."""
    by = {k: [t for t, y in rows if y == k] for k in (0, 1)}
    if not (len(by[0]) > 1 and len(by[1]) > 1):
        share = (len(by[1]) + 1) / (len(rows) + 2)
        return Model(b"", b"", 0.0, math.log(share / (1 - share)), chunk)
    ends = []
    for k in (1, 0):
        parts = [c for t in by[k][::2] for c in chunks_of(t, chunk, sample_chunks)]
        n = min(len(parts), max(1, dictionary_bytes // 256))  # at least 256 bytes of each chunk; of more chunks than have room, evenly spaced ones
        each = max(1, dictionary_bytes // max(1, n))
        ends.append(b"\n".join(parts[i * len(parts) // n][:each] for i in range(n)))
    tools = _compressors(*ends)
    rest = [(t, k) for k in (0, 1) for t in by[k][1::2]]
    plain = Model(*ends, 0.0, 0.0, chunk, weight=0)
    centre = float(np.mean([plain.difference(t, *tools) for t, _ in rest]))
    model = Model(*ends, 0.0, 0.0, chunk, centre)
    x = np.array([model.difference(t, *tools) for t, _ in rest])
    y = np.array([k for _, k in rest], float)
    return Model(*ends, *_logistic(x, y), chunk, centre)


def sample(docs: DataFrame, labels: DataFrame, usable: Column, per_label: int = 1500, text: str = "text", key: str = "doc_id", label: str = "quality", chunk: int = 512, text_chunks: int = 128) -> list[tuple[bytes, int]]:
    """Bounded: at most per_label labelled rows of each label, of least hash; only their texts move, and of a text
    of over text_chunks chunks that many, evenly spaced, which the executors cut: 64 KB a row."""
    ids = labels.where(usable & F.col(label).isin(0, 1) & F.col(key).isNotNull()).select(F.col(key).alias("_id"), F.col(label).cast("int").alias("_y")).distinct()
    ids = ids.withColumn("_h", F.xxhash64("_id"))
    chosen = ids.where("_y = 0").orderBy("_h", "_id").limit(per_label).unionAll(ids.where("_y = 1").orderBy("_h", "_id").limit(per_label))
    # 2 * per_label rows of 20 bytes, by the limits above
    got = docs.select(F.col(key).alias("_id"), F.col(text).cast("binary").alias("_t")).join(F.broadcast(chosen), "_id").where("_t is not null").select("_h", "_y", "_t")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cut = [b"".join(chunks_of(t.as_buffer().to_pybytes(), chunk, text_chunks)) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(cut, pa.binary())], ["_h", "_y", "_t"])

    got = got.mapInArrow(run, "_h long, _y int, _t binary")
    rows = sorted(got.select("_h", "_y", "_t").collect(), key=lambda r: (r["_h"], r["_y"], bytes(r["_t"])))
    return [(bytes(r["_t"]), r["_y"]) for r in rows]


def score(docs: DataFrame, model: Model, text: str = "text", into: str = "score") -> DataFrame:
    """docs with a column `into` (it replaces one of that name): the chance that the label is 1."""
    columns = [c for c in docs.columns if c != into]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tools = _compressors(model.good, model.bad) if model.good and model.bad else None
        for batch in batches:
            out = []
            for t in batch.column(len(columns)):
                data = t.as_buffer().to_pybytes() if t.is_valid else b""
                x = model.difference(data, *tools) if tools else 0.0
                out.append(1 / (1 + math.exp(-max(-30.0, min(30.0, model.slope * x + model.offset)))))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(out, pa.float64())], [*columns, into])

    ddl = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in columns)
    return docs.select(*[F.col(f"`{c}`") for c in columns], F.col(text).cast("binary").alias("_scored")).mapInArrow(run, f"{ddl}{', ' if ddl else ''}`{into}` double")
