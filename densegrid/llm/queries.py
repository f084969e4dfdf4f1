"""One query per operator, on its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from densegrid.llm import decontaminate, fingerprint, html_extract, langid, line_dedup, lm_score, pii, quality, sentencepiece_codec, simhash


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract_pages(_table(spark, sf_dir, "pages"))


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.fingerprint_report(_table(spark, sf_dir, "documents"))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_table(spark, sf_dir, "documents"))


def op6_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.encode(_table(spark, sf_dir, "documents"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


#: For the synthetic tables alone, so that runs can be compared; real data need a secret of their own.
TABLES_KEY = b"no secret: synthetic tables"


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.mask_documents(_table(spark, sf_dir, "documents"), TABLES_KEY)


def op10_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.score(_table(spark, sf_dir, "documents"))


#: Lines are compared as text, positions by row numbers over the same order.
OP7_SQL = r"""
WITH cut AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
lines AS (SELECT doc_id, unnest(ls) AS s, generate_subscripts(ls, 1) AS i FROM cut),
solid AS (
    SELECT doc_id, i, trim(s, chr(32) || chr(9) || chr(13) || chr(11) || chr(12)) AS s FROM lines
    WHERE trim(s, chr(32) || chr(9) || chr(13) || chr(11) || chr(12)) <> ''),
win AS (
    SELECT doc_id, i AS i0, lead(i, 2) OVER w AS i2, s || chr(10) || lead(s, 1) OVER w || chr(10) || lead(s, 2) OVER w AS passage
    FROM solid WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
again AS (
    SELECT doc_id, i0, i2 FROM
    (SELECT *, row_number() OVER (PARTITION BY passage ORDER BY doc_id, i0) AS turn FROM win WHERE i2 IS NOT NULL) WHERE turn > 1),
gone AS (SELECT DISTINCT l.doc_id, l.i FROM lines l JOIN again a ON l.doc_id = a.doc_id AND l.i BETWEEN a.i0 AND a.i2),
left_over AS (
    SELECT l.doc_id, string_agg(l.s, chr(10) ORDER BY l.i) AS text FROM lines l
    WHERE NOT EXISTS (SELECT 1 FROM gone g WHERE g.doc_id = l.doc_id AND g.i = l.i) GROUP BY l.doc_id),
counts AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT d.doc_id, CASE WHEN c.n IS NULL THEN d.text ELSE coalesce(k.text, '') END AS text, CAST(coalesce(c.n, 0) AS INTEGER) AS removed_lines
FROM documents d LEFT JOIN counts c ON d.doc_id = c.doc_id LEFT JOIN left_over k ON d.doc_id = k.doc_id
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_html_extraction, op2_fingerprints, op3_decontamination, op4_simhash, op5_language_id, op6_sentencepiece, op7_line_dedup, op8_quality, op9_pii, op10_lm_score)}


def oracle_sql() -> dict[str, str]:
    return {"op7_line_dedup": OP7_SQL}
