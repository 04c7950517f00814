"""Features of the order trace and the feature sets, and a synthetic catalogue with the published sizes."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

# Names of browser interfaces, in the order of their feature ids.
NAMED = ("fillText", "strokeText", "fillStyle", "strokeStyle", "toDataURL", "save", "restore", "addEventListener", "font", "measureText", "createDataChannel", "createOffer", "onicecandidate", "localDescription", "audio")
# Members that the audio rule names.
AUDIO = ("createOscillator", "createDynamicsCompressor", "destination", "startRendering", "oncomplete")
# End of each API's range of slots (a slot is 0..999; above 412 lie the generic ones).
SLOT_ENDS = (("fillText", 60), ("strokeText", 80), ("fillStyle", 140), ("strokeStyle", 160), ("toDataURL", 230), ("save", 250), ("restore", 270), ("addEventListener", 290), ("font", 330), ("measureText", 370), ("createDataChannel", 380), ("createOffer", 390), ("onicecandidate", 400), ("localDescription", 410), ("audio", 412))
GENERIC = 83
RETURNS = ("AF", "AO", "NF", "NO", "RF", "RO")
PATTERNS = ("text and style", "text and export", "style and export", "many fonts", "many measures", "peer offer", "peer candidate", "any of save restore listener", "font and measure")
N_COUNTS = len(NAMED) + GENERIC
FIRST_FLAG = N_COUNTS
FIRST_PATTERN = FIRST_FLAG + len(NAMED) * len(RETURNS)
N_FEATURES = FIRST_PATTERN + len(PATTERNS)
NATIVE_APIS = ("toDataURL", "localDescription", "audio", "measureText")
CANVAS_PEER = tuple(a for a in NAMED if a not in ("audio",))

#: Sizes that the paper reports: set -> (all, counts, customs).
PUBLISHED = {"full": (1514, 684, 830), "lab": (1330, 500, 830), "extension": (588, 96, 492), "native": (109, 109, 0), "compact": (149, 126, 23)}


@dataclass(frozen=True)
class Feature:
    feature_id: int
    api: str
    kind: str  # count or custom
    is_native: bool
    default: float | None = 0.0


def features() -> list[Feature]:
    natives = {*NATIVE_APIS, *(f"generic_{i}" for i in range(12))}
    out = [Feature(i, a, "count", a in natives) for i, a in enumerate((*NAMED, *(f"generic_{g}" for g in range(GENERIC))))]
    out += [Feature(FIRST_FLAG + i * len(RETURNS) + j, f"{a} returns {r}", "custom", False) for i, a in enumerate(NAMED) for j, r in enumerate(RETURNS)]
    return out + [Feature(FIRST_PATTERN + i, p, "custom", False) for i, p in enumerate(PATTERNS)]


def feature_set(name: str, ranked: Iterable[int] = (), k: int = 40) -> list[int]:
    """Feature ids of a set. `compact` is the native set and the first k others of a ranking."""
    every = features()
    if name == "full":
        return [f.feature_id for f in every]
    if name == "counts":
        return [f.feature_id for f in every if f.kind == "count"]
    if name == "lab":  # what needs no native tracing: the generic natives go
        return [f.feature_id for f in every if not (f.is_native and f.api.startswith("generic_"))]
    if name == "extension":
        own = [f.feature_id for f in every if f.api.split(" returns ")[0] in CANVAS_PEER or f.feature_id >= FIRST_PATTERN]
        keep = [i for i in own if i < FIRST_FLAG or i >= FIRST_PATTERN] + [i for i in own if FIRST_FLAG <= i < FIRST_PATTERN][:54]
        return sorted(keep)
    native = [f.feature_id for f in every if f.is_native]
    if name == "native":
        return native
    if name == "compact":
        more = [i for i in ranked if i not in set(native)][:k]
        return sorted([*native, *more])
    raise ValueError(f"no feature set {name}")


def table(spark: SparkSession) -> DataFrame:
    """The catalogue as rows: fixed size, so it may be broadcast."""
    return spark.createDataFrame([(f.feature_id, f.api, f.kind, f.is_native, f.default) for f in features()], "feature_id int, api string, kind string, is_native boolean, default_value double")


def synthetic() -> list[Feature]:
    """A catalogue of the published sizes: 500 lab counts, 75 further ones, 109 native ones, 830 customs."""
    out = [Feature(i, f"lab_{i}", "count", False) for i in range(500)]
    out += [Feature(500 + i, f"found_{i}", "count", False) for i in range(75)]
    out += [Feature(575 + i, f"native_{i}", "count", True) for i in range(109)]
    return out + [Feature(684 + i, f"custom_{i}", "custom", False) for i in range(830)]


def synthetic_set(name: str, ranked: Iterable[int] = ()) -> list[int]:
    every = synthetic()
    counts = {f.feature_id for f in every if f.kind == "count"}
    native = {f.feature_id for f in every if f.is_native}
    customs = sorted({f.feature_id for f in every} - counts)
    lab = set(range(500))
    return sorted({"full": counts | {*customs}, "lab": lab | {*customs}, "extension": {*range(96)} | {*customs[:492]}, "native": native, "compact": native | {*range(17)} | {*customs[:23]}}[name])


def sql_values() -> str:
    """The catalogue as a DuckDB VALUES list."""
    rows = ", ".join(f"({f.feature_id}, '{f.api}', '{f.kind}', {str(f.is_native).lower()}, {f.default})" for f in features())
    return f"(VALUES {rows}) c(feature_id, api, kind, is_native, default_value)"
