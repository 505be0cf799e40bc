"""The registered queries of this subpackage, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, html_layout, license_scan, lm_scoring, mixing, packing, pii, quality_mil, quality_rules, simhash
from .common import fold_bucket, read_table


def op1_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "lost_words", "clean_text")
    return quality_rules.clean_lines(read_table(spark, sf_dir, "documents").select("doc_id", "text")).select(*cols)


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(read_table(spark, sf_dir, "documents")).drop("spans")


def byte_bpe() -> dict:
    import public_tokenizers

    return {"json_path": public_tokenizers.path("byte_bpe_50k.json"), "ranks_path": public_tokenizers.path("byte_bpe_50k.tiktoken"), "pattern": public_tokenizers.PATTERN}


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read_table(spark, sf_dir, "documents"), byte_bpe())


def op4_posting_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(read_table(spark, sf_dir, "embeddings"), lambda i: i % 20 == 0)


def op5_quality_mil(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_mil.train(docs, read_table(spark, sf_dir, "labels"))
    scored = quality_mil.add_score(docs, model, keep=["doc_id"])
    return scored.select("doc_id", (fold_bucket(F.col("doc_id"), 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_digits(F.col("fp")).alias("fingerprint"), "component_id")


def op7_log_bilinear(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(read_table(spark, sf_dir, "documents"))


def op8_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


#: A deployment passes its own secret; the registered query needs a fixed one.
PII_KEY = "not-a-secret"


def op9_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.replace(read_table(spark, sf_dir, "documents").select("doc_id", "text"), PII_KEY)
    kinds = [F.element_at("entities", k).cast("long").alias(f"n_{k}") for k in pii.PATTERNS]
    return found.select("doc_id", "text", "n_entities", *kinds)


def op10_html_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_layout.extract(read_table(spark, sf_dir, "pages"), keep=["page_id", "url"])


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {"pipeline": pipeline, "op1_line_rules": op1_line_rules, "op2_license_scan": op2_license_scan, "op3_best_fit_packing": op3_best_fit_packing, "op4_posting_lists": op4_posting_lists, "op5_quality_mil": op5_quality_mil, "op6_simhash": op6_simhash, "op7_log_bilinear": op7_log_bilinear, "op8_source_mixing": op8_source_mixing, "op9_pii_surrogates": op9_pii_surrogates, "op10_html_layout": op10_html_layout}


_PHRASES = "|".join(quality_rules.BOILERPLATE_PHRASES).replace("'", "''")

OP1_SQL = rf"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), windows AS (
  SELECT rid, unnest(range(1, len(w) - 1)) AS i, w FROM d WHERE len(w) >= 3
), repeats AS (
  SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, w[i], w[i + 1], w[i + 2]) AS n FROM windows) WHERE n > 1
), covered AS (
  SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest([i, i + 1, i + 2]) AS p FROM repeats) GROUP BY rid
), lines AS (
  SELECT rid, l, place, regexp_extract_all(l, '[^\x20\x09-\x0D]+') AS w
  FROM (SELECT rid, unnest(string_split(t, chr(10))) AS l, generate_subscripts(string_split(t, chr(10)), 1) AS place FROM d)
), judged AS (
  SELECT rid, l, place, len(w) AS n, CASE
      WHEN len(w) = 0 THEN false
      WHEN len(list_filter(w, lambda x: x IN ('|', '»', '›', '•', '·', '>', '/', '-'))) >= 3
       AND len(list_filter(w, lambda x: x IN ('|', '»', '›', '•', '·', '>', '/', '-'))) * 100 > len(w) * 20 THEN true
      WHEN len(regexp_extract_all(l, '[#*$%&<>~^=_\\]')) * 100 > len(w) * 50
        OR len(regexp_extract_all(l, '[!?]{{2,}}')) * 100 > len(w) * 30
        OR NOT (regexp_matches(l, '[.!?:;,…。؟।]["''’”»)\]]*[\x20\x09-\x0D]*$') OR regexp_matches(l, '[.!?…。؟।]["''’”»)\]]*[\x20\x09]')) THEN true
      WHEN len(w) <= 25 AND regexp_matches(l, '(?i)(?:{_PHRASES})') THEN true
      WHEN len(w) >= 8 AND len(list_distinct(w)) * 100 < len(w) * 30 THEN true
      ELSE false END AS failed
  FROM lines
), per AS (
  SELECT rid, count(*) FILTER (n > 0) - count(DISTINCT l) FILTER (n > 0) AS n_dup_lines, coalesce(sum(n) FILTER (failed), 0) AS lost_words,
         coalesce(string_agg(l, chr(10) ORDER BY place) FILTER (NOT failed), '') AS clean_text
  FROM judged GROUP BY rid
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words,
       CAST(length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
       CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
       CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words,
       len(w) < 50 OR 100 * coalesce(c.n, 0) > 50 * len(w) AS base_failed,
       NOT (len(w) < 50 OR 100 * coalesce(c.n, 0) > 50 * len(w)) AND lost_words * 100 <= len(w) * 50 AS kept,
       CAST(lost_words AS BIGINT) AS lost_words, clean_text
FROM d LEFT JOIN covered c USING (rid) JOIN per USING (rid)
"""


def oracle_sql() -> dict[str, str]:
    """SQL for what SQL can express; the other queries are held against brute force in the tests."""
    return {"op1_line_rules": OP1_SQL}
