"""Rule labeller: four families of high-precision rules over a script's accesses, in one aggregate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .features import evidence

FAMILIES = ("canvas", "canvas_font", "webrtc", "audio")


def _any(*apis: str) -> Column:
    return sum((F.col(f"n_{a}") for a in apis), F.lit(0)) > 0


def canvas() -> Column:
    """Text and style are drawn and the picture is read back, and nothing hints at drawing for a user."""
    return _any("fillText", "strokeText") & _any("fillStyle", "strokeStyle") & _any("toDataURL") & ~_any("save", "restore", "addEventListener")


def canvas_font(min_fonts: int = 20, min_calls: int = 20) -> Column:
    """More than so many fonts are set and text is measured more than so many times."""
    return (F.col("fonts") > min_fonts) & (F.col("n_measureText") > min_calls)


def webrtc() -> Column:
    return _any("createDataChannel", "createOffer") & _any("onicecandidate", "localDescription")


def audio(strict: bool = False) -> Column:
    """Any member of the list; strict: two different ones at least."""
    return F.col("audio_members") >= (2 if strict else 1)


def rules(**how) -> dict[str, Column]:
    return {"canvas": canvas(), "canvas_font": canvas_font(how.get("min_fonts", 20), how.get("min_calls", 20)), "webrtc": webrtc(), "audio": audio(how.get("strict", False))}


def apply(trace: DataFrame, **how) -> DataFrame:
    """(script_id, canvas, canvas_font, webrtc, audio, y)."""
    own = rules(**how)
    flags = evidence(trace).select("script_id", *[c.alias(n) for n, c in own.items()])
    return flags.withColumn("y", F.greatest(*[F.col(n).cast("int") for n in FAMILIES]))


def families(labelled: DataFrame) -> DataFrame:
    return labelled.withColumn("families", F.array_compact(F.array(*[F.when(F.col(n), F.lit(n)) for n in FAMILIES])))


def prevalence(labelled: DataFrame) -> DataFrame:
    return labelled.agg(F.count("*").alias("scripts"), F.sum("y").cast("long").alias("positives"), *[F.count_if(F.col(n)).alias(n) for n in FAMILIES])


def sweep(trace: DataFrame, grid: DataFrame) -> DataFrame:
    """How many scripts the font rule takes at each cut; the grid is a small table of the user's."""
    e = evidence(trace).select("script_id", "fonts", "n_measureText")
    return F.broadcast(grid).join(e, (F.col("fonts") > F.col("cut")) & (F.col("n_measureText") > F.col("cut")), "left").groupBy("cut").agg(F.count("script_id").alias("scripts"))


#: DuckDB CTEs `evidence` and `labelled`, over `trace`.
def _sql_evidence() -> str:
    from .catalogue import AUDIO, NAMED

    sums = ", ".join(f"coalesce(sum(n_calls) FILTER (api_id = {i}), 0) AS n_{a}" for i, a in enumerate(NAMED))
    members = ", ".join(f"'{a}'" for a in AUDIO)
    return f"""evidence AS (SELECT script_id, {sums}, coalesce(max(n_calls) FILTER (api_id = {NAMED.index("font")}), 0) AS fonts,
  count(DISTINCT CASE WHEN api IN ({members}) THEN api END) AS audio_members FROM trace GROUP BY script_id)"""


SQL_EVIDENCE = _sql_evidence()
SQL_LABELLED = """labelled AS (SELECT *, CAST(canvas OR canvas_font OR webrtc OR audio AS INT) AS y FROM (SELECT script_id,
  n_fillText + n_strokeText > 0 AND n_fillStyle + n_strokeStyle > 0 AND n_toDataURL > 0 AND n_save + n_restore + n_addEventListener = 0 AS canvas,
  fonts > 20 AND n_measureText > 20 AS canvas_font,
  n_createDataChannel + n_createOffer > 0 AND n_onicecandidate + n_localDescription > 0 AS webrtc,
  audio_members > 0 AS audio FROM evidence))"""


def _sql_features() -> str:
    from .catalogue import FIRST_FLAG, FIRST_PATTERN, NAMED, RETURNS

    ret = "CASE ret " + " ".join(f"WHEN '{r}' THEN {i}" for i, r in enumerate(RETURNS)) + " END"
    clauses = ["n_fillText + n_strokeText > 0 AND n_fillStyle + n_strokeStyle > 0", "n_fillText + n_strokeText > 0 AND n_toDataURL > 0", "n_fillStyle + n_strokeStyle > 0 AND n_toDataURL > 0", "fonts > 20", "n_measureText > 20", "n_createDataChannel + n_createOffer > 0", "n_onicecandidate + n_localDescription > 0", "n_save + n_restore + n_addEventListener > 0", "n_font > 0 AND n_measureText > 0"]
    conj = " UNION ALL ".join(f"SELECT script_id, {FIRST_PATTERN + i} AS feature_id, 1.0::DOUBLE AS v FROM evidence WHERE {c}" for i, c in enumerate(clauses))
    return f"""feats AS (SELECT script_id, api_id AS feature_id, CAST(sum(n_calls) AS DOUBLE) AS v FROM trace GROUP BY ALL
  UNION ALL SELECT DISTINCT script_id, {FIRST_FLAG} + api_id * {len(RETURNS)} + {ret}, 1.0::DOUBLE FROM trace WHERE api_id < {len(NAMED)} AND {ret} IS NOT NULL
  UNION ALL {conj})"""


SQL_FEATURES = _sql_features()
