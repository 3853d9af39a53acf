"""The registered queries of this subpackage and, where SQL can express them, their DuckDB equivalents."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, id_files, licences, main_text, media, mixing, near_copies, neighbours, quality, secrets
from .common import table


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_plan(table(spark, sf_dir, "documents"))


def op2_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_digest(table(spark, sf_dir, "documents"))


def op3_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.search(table(spark, sf_dir, "embeddings"))


def op4_quality_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies.join_documents(table(spark, sf_dir, "documents"))


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan_licences(table(spark, sf_dir, "documents")).drop("findings")


def op7_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text.extract_pages(table(spark, sf_dir, "pages"))


def op8_id_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return id_files.encode_to_files(table(spark, sf_dir, "documents"))


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digest(table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_digest(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_mix_sources, op2_media_columns, op3_prefix_forest, op4_quality_votes, op5_near_copies, op6_license_scan, op7_main_text, op8_id_files, op9_bpe, op10_secret_scan)}


def oracle_sql() -> dict[str, str]:
    return {"op7_main_text": OP7}


#: The given pages mark their content by one article element; an independent reading of it by patterns.
OP7 = r"""
SELECT page_id, url, text, CAST(length(text) AS BIGINT) AS n_chars
FROM (
  SELECT page_id, url,
    trim(regexp_replace(replace(replace(replace(replace(regexp_replace(regexp_replace(
      regexp_extract(coalesce(html, ''), '<article>(.*?)(</article>|<footer>|$)', 1, 's'),
      '</?b>', '', 'g'), '<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&'), '\s+', ' ', 'g')) AS text
  FROM pages)
"""
