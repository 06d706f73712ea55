"""The queries of this subpackage and, where SQL can express one, its DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.llm import exact_dedup, lang_id, license_scan, mixing, near_dedup, packing, quality_resample, quality_rules, sharding, token_codes
from histreplay.llm.common import documents


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


SHARDS = 8
SOURCE_WEIGHTS = (5.0, 2.0, 1.0)


def op1_hypervector_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lang_id.identify(documents(spark, sf_dir)).withColumnRenamed("id", "doc_id")


def op2_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality_resample.resample(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return found.select(F.col("id").alias("doc_id"), "log_ratio", "key", "rank", "kept")


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mixing.mix(documents(spark, sf_dir), SOURCE_WEIGHTS)
    return found.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")


def op4_token_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = token_codes.token_files(documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"), end_id=0)
    return token_codes.read_documents(spark, path).withColumnRenamed("id", "doc_id")


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_dedup.exact_duplicates(documents(spark, sf_dir), hash_all=True)
    return found.select(F.col("id").alias("doc_id"), "keep_id", "group_size", "kept", F.col("full_hash").alias("text_sha256"))


def op6_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(documents(spark, sf_dir)).withColumnRenamed("id", "doc_id")


def op7_jump_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = sharding.shard_documents(documents(spark, sf_dir), SHARDS)
    return found.select(F.col("id").alias("doc_id"), "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op8_risk_controlled_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality_rules.judge(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    base = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rejected_by")
    return found.select(F.col("id").alias("doc_id"), *base)


def op9_neighbour_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.pack(documents(spark, sf_dir), vocabulary("word_bpe_49k.json"), with_ids=False)
    return pieces.withColumnRenamed("id", "doc_id")


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = license_scan.scan_licenses(documents(spark, sf_dir))
    return found.withColumnRenamed("id", "doc_id").drop("detections")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages of corpus_pipeline at the repository's top."""
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir).drop("ids")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    every = (op1_hypervector_language, op2_importance_resampling, op3_mix_sources, op4_token_codes, op5_exact_dedup, op6_minhash_near_dedup, op7_jump_sharding, op8_risk_controlled_rules, op9_neighbour_packing, op10_license_scan, pipeline)
    return {f.__name__: f for f in every}


_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_SQL_MIX = rf"""
WITH docs AS (
  SELECT doc_id, source, CAST(len({_WORDS.format("coalesce(text, '')")}) AS BIGINT) AS size,
         length(text) - length(translate(text, '#*$%&|<>', '')) AS marks,
         (CAST('0x' || substr(md5(doc_id || ':11'), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0 AS u
  FROM documents),
keyed AS (SELECT *, -ln(u) / coalesce(greatest(0.1, 1.0 - CAST(marks AS DOUBLE) / greatest(size, 1)), 1.0) AS k FROM docs),
sources AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS n,
         [5.0, 2.0, 1.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS w
  FROM docs GROUP BY source),
ranked AS (SELECT *, row_number() OVER (ORDER BY 3.0 * n / w, source) AS r FROM sources),
levels AS (
  SELECT r, (SELECT sum(n) FROM sources) - coalesce(sum(3 * n) OVER (ORDER BY r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS room,
         sum(w) OVER (ORDER BY r ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest, n, w
  FROM ranked),
cut AS (SELECT r, CAST(room AS DOUBLE) / rest AS unit FROM levels WHERE w * (CAST(room AS DOUBLE) / rest) <= 3.0 * n ORDER BY r LIMIT 1),
goals AS (SELECT source, n, CASE WHEN ranked.r < cut.r THEN 3.0 * n ELSE w * unit END AS target FROM ranked, cut),
plan AS (SELECT *, CASE WHEN n > 0 THEN CAST(floor(target / n) AS BIGINT) ELSE 0 END AS epochs FROM goals),
placed AS (
  SELECT doc_id, size, n, target, epochs, CAST(floor(target - epochs * n + 0.5) AS BIGINT) AS budget,
         coalesce(sum(size) OVER (PARTITION BY keyed.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM keyed JOIN plan ON keyed.source IS NOT DISTINCT FROM plan.source)
SELECT doc_id, size, n AS source_size, target, CAST(epochs * size + greatest(0, least(size, budget - before)) AS BIGINT) AS taken FROM placed
"""

_SQL_EXACT = """
WITH hashed AS (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents),
groups AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM hashed GROUP BY text_sha256)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM hashed JOIN groups USING (text_sha256)
"""

_SQL_NEAR = rf"""
WITH RECURSIVE tokens AS (SELECT doc_id, {_WORDS.format(f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')")} AS w FROM documents),
grams AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM tokens WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id),
pairs AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM grams x JOIN grams y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
linked AS (
  SELECT a, b FROM pairs JOIN sizes s ON s.doc_id = a JOIN sizes t ON t.doc_id = b
  WHERE 100 * shared >= 75 * (s.n + t.n - shared)),
ways AS (SELECT a, b FROM linked UNION ALL SELECT b, a FROM linked),
reach AS (SELECT doc_id, doc_id AS root FROM documents UNION SELECT ways.b, reach.root FROM reach JOIN ways ON ways.a = reach.doc_id WHERE reach.root < ways.b),
roots AS (SELECT doc_id, min(root) AS component_id FROM reach GROUP BY doc_id)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, component_id, d.doc_id = component_id AS kept
FROM documents d JOIN roots USING (doc_id) LEFT JOIN sizes USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_mix_sources": _SQL_MIX, "op5_exact_dedup": _SQL_EXACT, "op6_minhash_near_dedup": _SQL_NEAR}
