"""Queries over the operators of this subpackage, with production parameters, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, linededup, minhash, mixing, ordermin, quality, sharding, tiff, toxicity
from .common import documents, labels

BPE_FILE = "byte_bpe_multi_50k.tiktoken"


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.document_shards(documents(spark, sf_dir))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.deduplicate(documents(spark, sf_dir).select("doc_id", "text"))
    spans = F.array_join(F.transform("removed_spans", lambda s: F.concat_ws("-", s["start"].cast("string"), s["end"].cast("string"))), ",")
    return out.select("doc_id", F.col("n_units").cast("long").alias("n_units"), F.col("n_removed").cast("long").alias("n_removed"), spans.alias("removed"), "text")


def op3_byte_bpe(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    import public_tokenizers

    return bpe.digest(documents(spark, sf_dir), bpe.load_ranks(path or public_tokenizers.path(BPE_FILE)), public_tokenizers.PATTERN)


#: Target shares of the domains' tokens in op4_soft_mixing: other languages than the largest are weighted up, that one down.
MIX_WEIGHTS = {"en": 0.4, "fr": 0.2, "de": 0.2, "es": 0.2}


def op4_soft_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.rates(documents(spark, sf_dir), labels(spark, sf_dir), weights=MIX_WEIGHTS)


def op5_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiff.round_trip(documents(spark, sf_dir))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.document_toxicity(documents(spark, sf_dir), labels(spark, sf_dir))


def op7_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(documents(spark, sf_dir))


def op8_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = chat.perspectives(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    return out.select("conv_id", "speaker", "part", F.col("n_turns").cast("long").alias("n_turns"), "rendered", chat.mask_string(F.col("mask")).alias("mask"))


def op9_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.document_quality(documents(spark, sf_dir), labels(spark, sf_dir))


def op10_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ordermin.edit_check(documents(spark, sf_dir))


#: Lines of any length, and sentences (of lines with several) of five words or 20 characters, that an earlier document or place has.
LINE_DEDUP_SQL = """
WITH lines AS (
  SELECT DISTINCT doc_id, k, unnest(range(len(l))) AS i, unnest(l) AS line
  FROM (SELECT doc_id, md5(coalesce(text, '')) AS k, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)
), parts AS (
  SELECT doc_id, k, i, line, unnest(range(1, len(p) + 1)) AS j, unnest(p) AS part, len(p) AS n
  FROM (SELECT *, string_split(replace(replace(replace(line, '. ', '.' || chr(1)), '! ', '!' || chr(1)), '? ', '?' || chr(1)), chr(1)) AS p FROM lines)
), units AS (
  SELECT doc_id, k, i, 0 AS j, line AS unit FROM lines UNION ALL SELECT doc_id, k, i, j, part FROM parts WHERE n > 1
), normed AS (
  SELECT doc_id, k, i, j, trim(regexp_replace(lower(unit), '[ \\t\\r\\n\\f\\v]+', ' ', 'g')) AS unit FROM units
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY unit ORDER BY doc_id NULLS FIRST, k, i, j) AS place
  FROM normed WHERE unit <> '' AND (j = 0 OR length(unit) >= 20 OR length(unit) - length(replace(unit, ' ', '')) >= 4)
), gone AS (
  SELECT doc_id, k, i, j FROM ranked WHERE place > 1
), placed AS (
  SELECT *, coalesce(sum(length(line) + 1) OVER (PARTITION BY doc_id, k ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS at_line FROM lines
), spots AS (
  SELECT p.doc_id, p.k, p.i, p.j, p.n, p.part, l.line, l.at_line,
    l.at_line + coalesce(sum(length(p.part) + 1) OVER (PARTITION BY p.doc_id, p.k, p.i ORDER BY p.j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS at_part,
    EXISTS (SELECT 1 FROM gone g WHERE g.doc_id IS NOT DISTINCT FROM p.doc_id AND g.k = p.k AND g.i = p.i AND g.j = 0) AS line_gone,
    EXISTS (SELECT 1 FROM gone g WHERE g.doc_id IS NOT DISTINCT FROM p.doc_id AND g.k = p.k AND g.i = p.i AND g.j = p.j) AS part_gone
  FROM parts p JOIN placed l ON l.doc_id IS NOT DISTINCT FROM p.doc_id AND l.k = p.k AND l.i = p.i
), spans AS (
  SELECT DISTINCT doc_id, k, at_line AS a, at_line + length(line) AS b FROM spots WHERE line_gone
  UNION ALL SELECT doc_id, k, at_part, at_part + length(part) FROM spots WHERE part_gone AND NOT line_gone
), removed AS (
  SELECT doc_id, k, count(*) AS n_removed, string_agg(a::BIGINT || '-' || b::BIGINT, ',' ORDER BY a) AS removed FROM spans GROUP BY 1, 2
), kept AS (
  SELECT doc_id, k, i, string_agg(part, ' ' ORDER BY j) AS line FROM spots WHERE NOT line_gone AND NOT part_gone GROUP BY 1, 2, 3
), rest AS (
  SELECT doc_id, k, string_agg(line, chr(10) ORDER BY i) AS text FROM kept GROUP BY 1, 2
)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN 0 ELSE len(string_split(d.text, chr(10))) END::BIGINT AS n_units, coalesce(r.n_removed, 0)::BIGINT AS n_removed,
  coalesce(r.removed, '') AS removed, CASE WHEN d.text IS NULL THEN NULL WHEN r.k IS NULL THEN d.text ELSE coalesce(t.text, '') END AS text
FROM (SELECT *, md5(coalesce(text, '')) AS k FROM documents) d
LEFT JOIN removed r ON r.doc_id IS NOT DISTINCT FROM d.doc_id AND r.k = d.k LEFT JOIN rest t ON t.doc_id IS NOT DISTINCT FROM d.doc_id AND t.k = d.k
"""

NEAR_DUPLICATES_SQL = """
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), grams AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM words WHERE len(w) > 0)
), sizes AS (
  SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id
), shared AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2
), links AS (
  SELECT x, y FROM shared JOIN sizes s ON s.doc_id = x JOIN sizes t ON t.doc_id = y WHERE 100 * c >= 85 * (s.n + t.n - c)
), sym AS (
  SELECT x, y FROM links UNION SELECT y, x FROM links
), reach AS (
  SELECT doc_id AS node, doc_id AS far FROM documents UNION SELECT r.node, b.y FROM reach r JOIN sym b ON b.x = r.far
), least AS (
  SELECT node, min(far) AS component FROM reach GROUP BY node
)
SELECT d.doc_id, coalesce(s.n, 0)::BIGINT AS n_shingles, l.component AS component_id, d.doc_id = l.component AS kept
FROM documents d LEFT JOIN sizes s USING (doc_id) JOIN least l ON l.node = d.doc_id
"""

#: Every part of 256 turns, after the conversation's first system turn where the part doesn't hold it. (Turns all have numbers here.)
PERSPECTIVES_SQL = """
WITH turns AS (
  SELECT DISTINCT conv_id, turn, coalesce(role, 'unknown') AS role, text, floor(turn / 256)::BIGINT AS part FROM conversations
), lead AS (
  SELECT * FROM turns WHERE role = 'system' AND turn IS NOT NULL QUALIFY row_number() OVER (PARTITION BY conv_id ORDER BY turn, text NULLS FIRST) = 1
), full_ AS (
  SELECT conv_id, turn, role, text, part, 1 AS own FROM turns
  UNION ALL SELECT l.conv_id, l.turn, l.role, l.text, p.part, 0 FROM lead l JOIN (SELECT DISTINCT conv_id, part FROM turns) p ON p.conv_id IS NOT DISTINCT FROM l.conv_id AND p.part <> l.part
), cast_ AS (
  SELECT DISTINCT conv_id, role AS speaker FROM turns WHERE role <> 'system'
), seg AS (
  SELECT t.conv_id, c.speaker, t.part, t.turn, t.role, t.text, t.own,
    '<|im_start|>' || CASE WHEN t.role = c.speaker THEN 'assistant' WHEN t.role = 'system' THEN 'system'
      ELSE 'user name=' || translate(replace(t.role, '<|im_', '<| im_'), chr(10) || chr(13), '  ') END || chr(10) AS head,
    replace(coalesce(t.text, ''), '<|im_', '<| im_') || '<|im_end|>' || chr(10) AS body
  FROM full_ t JOIN cast_ c ON c.conv_id IS NOT DISTINCT FROM t.conv_id
), placed AS (
  SELECT *, coalesce(sum(length(head) + length(body)) OVER (PARTITION BY conv_id, speaker, part ORDER BY own, turn, role, text NULLS FIRST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + length(head) AS s FROM seg
)
SELECT conv_id, speaker, part::BIGINT AS part, sum(own)::BIGINT AS n_turns, string_agg(head || body, '' ORDER BY own, turn, role, text NULLS FIRST) AS rendered,
  coalesce(string_agg(s::BIGINT || '-' || (s + length(body))::BIGINT, ',' ORDER BY s) FILTER (role = speaker), '') AS mask
FROM placed GROUP BY conv_id, speaker, part
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (op1_sharding, op2_line_dedup, op3_byte_bpe, op4_soft_mixing, op5_tiff, op6_toxicity, op7_minhash, op8_perspectives, op9_line_quality, op10_order_minhash)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op2_line_dedup": LINE_DEDUP_SQL, "op7_minhash": NEAR_DUPLICATES_SQL, "op8_perspectives": PERSPECTIVES_SQL}
