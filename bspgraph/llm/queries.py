"""The queries of this subpackage, each over its whole table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, exactdup, langid, linededup, mixing, neardup, pii, quality, telephony, toxicity
from .common import documents, labels


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grades: 0 poor, 1 sound but toxic, 2 sound; a document is kept if it
    probably reaches grade 1."""
    sound = F.col("quality") == 1
    grade = F.when(~sound, 0).when(sound & (F.col("toxic") == 1), 1).when(sound, 2)
    return quality.quality_report(documents(spark, sf_dir), labels(spark, sf_dir).select("doc_id", grade.alias("grade")))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_report(documents(spark, sf_dir))


def op3_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exactdup.exact_groups(documents(spark, sf_dir))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity_report(documents(spark, sf_dir), labels(spark, sf_dir))


def op5_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(documents(spark, sf_dir))


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.codec_report(documents(spark, sf_dir), public_tokenizers.path(bpe.VOCABULARY))


def op7_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.line_report(documents(spark, sf_dir))


def op8_telephony(spark: SparkSession, sf_dir: str) -> DataFrame:
    return telephony.audio_report(documents(spark, sf_dir))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(documents(spark, sf_dir))


QUERIES = {f.__name__: f for f in (op1_quality, op2_pii, op3_exact, op4_toxicity, op5_neardup, op6_bpe, op7_lines, op8_telephony, op9_mixing, op10_language)}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_SPACES = " || ".join(f"chr({c})" for c in (32, 9, 10, 11, 12, 13))

OP3_SQL = f"""
WITH t AS (SELECT doc_id, translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}') AS body FROM documents)
SELECT doc_id,
       max(doc_id) OVER (PARTITION BY body) AS keep_id,
       count(*) OVER (PARTITION BY body) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY body) AS kept,
       sha256(body) AS text_sha256
FROM t
"""

OP7_SQL = f"""
WITH split AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents),
lines AS (SELECT doc_id, unnest(parts) AS line, generate_subscripts(parts, 1) AS place FROM split),
keyed AS (SELECT *, translate(trim(line, {_SPACES}), '{_UPPER}', '{_LOWER}') AS line_key FROM lines),
found AS (
  SELECT line_key, max(doc_id) AS stays FROM keyed WHERE length(line_key) >= 40
  GROUP BY line_key HAVING count(DISTINCT doc_id) >= 5
),
marked AS (SELECT k.*, f.stays IS NOT NULL AND f.stays <> k.doc_id AS gone FROM keyed k LEFT JOIN found f USING (line_key))
SELECT doc_id,
       count(*) AS n_lines,
       count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY place) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

OP9_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         greatest(0.05, CASE WHEN length(text) > 0 THEN
           1 - 4 * ((length(text) - length(translate(text, '#$%&*|<>{}[]=_~^\', ''))) / CAST(length(text) AS DOUBLE)) ELSE 1.0 END) AS quality,
         (CAST('0x' || substr(md5('mix-1:' || doc_id), 1, 12) AS BIGINT) + 0.5::DOUBLE) / 281474976710656::DOUBLE AS u
  FROM documents
),
keyed AS (SELECT *, -ln(u) / quality AS rank_key FROM sized),
sources AS (SELECT source, CAST(sum(size) AS DOUBLE) AS source_size FROM keyed GROUP BY source),
weighed AS (
  SELECT *, 3 * source_size AS most, sum(source_size) OVER () AS total,
         [5.0, 2.0, 1.0][CAST((row_number() OVER (ORDER BY source IS NULL, source COLLATE "C") - 1) % 3 AS INT) + 1]::DOUBLE AS weight
  FROM sources
),
levels AS (
  SELECT *, (total - coalesce(sum(most) OVER (ORDER BY most / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(weight) OVER (ORDER BY most / weight, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed
),
goals AS (
  SELECT source, source_size, round(CASE WHEN most <= level * weight THEN most
         ELSE weight * (SELECT arg_min(level, most / weight) FROM levels WHERE most > level * weight) END, 6) AS target
  FROM levels
),
running AS (
  SELECT k.*, g.source_size, g.target, least(3, CASE WHEN g.source_size > 0 THEN floor(g.target / g.source_size) ELSE 0 END) AS epochs,
         coalesce(sum(size) OVER (PARTITION BY k.source ORDER BY rank_key, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM keyed k JOIN goals g ON k.source IS NOT DISTINCT FROM g.source
)
SELECT doc_id, size, CAST(source_size AS BIGINT) AS source_size, target,
       CAST(size * (epochs + CASE WHEN epochs < 3 AND before + size / 2.0 <= target - epochs * source_size THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM running
"""

ORACLES = {"op3_exact": OP3_SQL, "op7_lines": OP7_SQL, "op9_mixing": OP9_SQL}
