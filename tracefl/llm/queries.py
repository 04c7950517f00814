"""The operators' queries over the whole tables, with the SQL that some can be checked against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, chaining, compression, exact_dedup, jaccard_join, line_dedup, mixing, quality_rules, suffix_array, tool_calls
from .common import documents


def incoming():
    """The rows that stand for a new batch: a quarter by a hash of the key; the others are the snapshot."""
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(4)) == 0


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.resolve(documents(spark, sf_dir), incoming()).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(documents(spark, sf_dir))


def tokenizer() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.encode(documents(spark, sf_dir), *tokenizer(), digest=True)


def held_out():
    return F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0


def quality_model(docs: DataFrame, labels: DataFrame) -> compression.Model:
    return compression.fit(compression.sample(docs, labels, ~held_out()))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = quality_model(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return compression.score(docs.select("doc_id", "text"), model).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join(documents(spark, sf_dir)).select("doc_id", "class_id", "n_links", "copies")



def op3_tool_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    calls, results = tool_calls.from_messages(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    return tool_calls.link(calls, results, tool_calls.SCHEMAS)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.resolve(documents(spark, sf_dir))


def op7_chaining(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chaining.passages(documents(spark, sf_dir))


def op9_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_array.passages(documents(spark, sf_dir))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_mixing, op2_exact_dedup, op3_tool_calls, op4_quality_rules, op5_line_dedup, op6_byte_bpe, op7_chaining, op8_quality_classifier, op9_suffix_array, op10_jaccard_join)}


OP2_SQL = """
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS chars,
         sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id,
       first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY chars DESC, doc_id) AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       doc_id = first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY chars DESC, doc_id) AS kept,
       text_sha256
FROM t
"""

#: Sizes, targets by the level of capped shares, then whole blocks in hash order and the rows of the block at the border.
OP1_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         CAST('0x' || substr(md5('17|row|' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8) AS BIGINT) AS h
  FROM documents),
s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         [3, 1, 2][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INT)] AS w
  FROM d GROUP BY source),
r AS (
  SELECT *, (sum(source_size) OVER () * 3 / 2.0 - coalesce(sum(2 * source_size) OVER before, 0))
            / (sum(w) OVER () - coalesce(sum(w) OVER before, 0)) AS try
  FROM s WINDOW before AS (ORDER BY 2 * source_size / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
l AS (SELECT arg_min(try, 2 * source_size / w) AS level FROM r WHERE try * w <= 2 * source_size),
t AS (
  SELECT source, source_size,
         CAST(CASE WHEN level IS NULL OR level * w >= 2 * source_size THEN 2 * source_size ELSE level * w END AS DOUBLE) AS target
  FROM r, l),
g AS (
  SELECT *, CAST(floor(target / greatest(source_size, 1)) AS BIGINT) AS whole_passes,
         CAST(greatest(0, least(31, ceil(log2(greatest(1.0, source_size / greatest(32768.0, sum(source_size) OVER () / 32768.0)))))) AS INT) AS bits
  FROM t),
p AS (
  SELECT d.*, source_size, target, whole_passes, target - whole_passes * source_size AS rest, h >> (32 - bits) AS block
  FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source),
b AS (
  SELECT source, block, sum(size) AS words, any_value(rest) AS rest,
         CAST('0x' || substr(md5('17|super|' || block), 1, 8) AS BIGINT) % 64 AS super,
         CAST('0x' || substr(md5('17|block|' || coalesce(source, chr(0) || 'null') || '|' || block), 1, 8) AS BIGINT) AS o
  FROM p GROUP BY source, block),
q AS (
  SELECT *, coalesce(sum(words) OVER (PARTITION BY source ORDER BY super, o, block ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM b),
x AS (
  SELECT p.*, before, before + words <= p.rest AS inside, before < p.rest AND before + words > p.rest AS border,
         coalesce(sum(size) OVER (PARTITION BY p.source, p.block ORDER BY h, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS sofar
  FROM p JOIN q ON p.source IS NOT DISTINCT FROM q.source AND p.block = q.block)
SELECT doc_id, size, source_size, target,
       CAST(size * (whole_passes + CASE WHEN inside OR (border AND before + sofar + size / 2.0 <= rest) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM x
"""

#: Plain turns as calls and results; every dependency points back, so a call's place is its turn.
OP3_SQL = r"""
WITH m AS (SELECT *, CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS BIGINT) AS words FROM conversations),
c AS (
  SELECT conv_id, turn, 't' || turn AS call_id, role, text, words,
         CASE WHEN role = 'user' AND turn > 0 THEN list_sort(list_distinct(['t' || (turn - 1), 't' || (turn - 2)])) ELSE [] END AS deps
  FROM m WHERE role IN ('user', 'system')),
r AS (SELECT conv_id, 't' || (turn - 1) AS call_id, turn, text AS content FROM m WHERE role = 'assistant'),
j AS (SELECT c.*, r.turn AS r_turn, content FROM c LEFT JOIN r USING (conv_id, call_id))
SELECT conv_id, call_id, turn, turn AS place, 0 AS step, false AS cyclic,
       CASE WHEN r_turn IS NULL THEN 'pending' ELSE 'linked' END AS status,
       CASE WHEN role = 'user' THEN CAST(length(text) = 0 AS INT) + CAST(words < 1 OR words > 4096 AS INT) ELSE CAST(length(text) = 0 AS INT) END AS n_errors,
       CASE WHEN role = 'user' THEN CASE WHEN length(text) = 0 THEN '$.prompt: below minLength' WHEN words < 1 THEN '$.words: below minimum' WHEN words > 4096 THEN '$.words: above maximum' END
            WHEN length(text) = 0 THEN '$.rule: below minLength' END AS first_error,
       '{"arguments":' || CASE WHEN role = 'user' THEN '{"prompt":' || to_json(text) || ',"words":' || words || '}' ELSE '{"rule":' || to_json(text) || '}' END
         || ',"depends_on":[' || array_to_string(list_transform(deps, lambda x: '"' || x || '"'), ',') || '],"id":"' || call_id || '","name":"'
         || CASE WHEN role = 'user' THEN 'reply' ELSE 'instruct' END || '"' || CASE WHEN r_turn IS NULL THEN '' ELSE ',"result":' || to_json(content) END || '}' AS json
FROM j
UNION ALL
SELECT conv_id, call_id, turn, turn, 0, false, 'orphan', 0, NULL, '{"id":"' || call_id || '","result":' || to_json(content) || '}'
FROM r WHERE NOT EXISTS (SELECT 1 FROM c WHERE c.conv_id = r.conv_id AND c.call_id = r.call_id)
"""

ORACLES: dict[str, str] = {"op1_mixing": OP1_SQL, "op3_tool_calls": OP3_SQL, "op2_exact_dedup": OP2_SQL}
