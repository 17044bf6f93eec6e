"""The query of each operator, over its whole table, and its SQL where SQL can express it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, media, mixing, neardup, packing, pii, quality, repeats, token_counts, token_files
from .common import documents


def op1_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.removals(documents(spark, sf_dir)).drop("kept", "spans")


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    scored = quality.classify(docs, documents(spark, sf_dir, "labels"))
    return scored.select("doc_id", quality.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find(documents(spark, sf_dir)))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.section_token_counts(documents(spark, sf_dir))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited_fingerprints(documents(spark, sf_dir))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_files(documents(spark, sf_dir))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


OP8_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents
), sources AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         row_number() OVER (ORDER BY source NULLS LAST) AS place FROM sized GROUP BY source
), weighed AS (
  SELECT *, CAST((place - 1) % 3 + 1 AS BIGINT) AS weight, 3 * source_size AS cap,
         CAST(3 * source_size AS DOUBLE) / CAST((place - 1) % 3 + 1 AS BIGINT) AS ratio FROM sources
), levels AS (
  SELECT *, (sum(source_size) OVER () - (sum(cap) OVER low - cap))::DOUBLE
            / (sum(weight) OVER () - (sum(weight) OVER low - weight))::DOUBLE AS level
  FROM weighed WINDOW low AS (ORDER BY ratio, place ROWS UNBOUNDED PRECEDING)
), water AS (
  SELECT *, first_value(CASE WHEN ratio > level THEN level END IGNORE NULLS)
            OVER (ORDER BY ratio, place ROWS UNBOUNDED PRECEDING) AS w FROM levels
), targets AS (
  SELECT source, source_size, CASE WHEN w IS NULL THEN CAST(cap AS DOUBLE) ELSE w * weight END AS target FROM water
), upto AS (
  SELECT s.doc_id, s.size, t.source_size, t.target,
         CASE WHEN t.source_size > 0 THEN CAST(floor(t.target / t.source_size) AS BIGINT) ELSE 0 END AS times,
         CAST(sum(s.size) OVER (PARTITION BY s.source ORDER BY md5('mix-1:' || coalesce(CAST(s.doc_id AS VARCHAR), '')), s.doc_id, s.size
                           ROWS UNBOUNDED PRECEDING) AS BIGINT) - s.size AS before
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target,
       CAST(times * size + greatest(0, least(size, CAST(floor(target) AS BIGINT) - times * source_size - before)) AS BIGINT) AS taken
FROM upto
"""


def op9_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.store_and_read(documents(spark, sf_dir))


def op10_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.classes(documents(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    named = (op1_repeats, op2_quality, op3_pii, op4_packing, op5_token_counts, op6_fingerprints, op7_token_files, op8_mixing, op9_media, op10_neardup, pipeline)
    return {f.__name__: f for f in named}


def oracle_sql() -> dict[str, str]:
    return {"op8_mixing": OP8_SQL}
