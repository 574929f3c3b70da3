"""Registered queries of the pipeline operators, each over its whole table, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ldp_hist.llm import decontaminate, exact_dedup, feistel, html_text, langid, line_dedup, pieces, secrets_scan, sharding, simhash


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


QUERIES = {
    "op1_training_order": lambda spark, d: feistel.training_shards(_table(spark, d, "documents")),
    "op2_lpt_shards": lambda spark, d: sharding.lpt_shards(_table(spark, d, "documents")),
    "op3_language_id": lambda spark, d: langid.language_id(_table(spark, d, "documents")),
    "op4_simhash_components": lambda spark, d: simhash.near_components(_table(spark, d, "documents")),
    "op5_secret_scan": lambda spark, d: secrets_scan.scan_secrets(_table(spark, d, "documents")),
    "op6_decontamination": lambda spark, d: decontaminate.contamination(_table(spark, d, "documents").select("doc_id", "text"), _table(spark, d, "benchmark")).select("row.doc_id", "item_ids", "similarity"),
    "op7_line_dedup": lambda spark, d: line_dedup.line_dedup(_table(spark, d, "documents")),
    "op8_sentencepiece": lambda spark, d: pieces.encode_documents(_table(spark, d, "documents")),
    "op9_exact_dedup": lambda spark, d: exact_dedup.exact_dedup(_table(spark, d, "documents")),
    "op10_main_text": lambda spark, d: html_text.extract_pages(_table(spark, d, "pages")),
}

_LOWER = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES = {
    "op7_line_dedup": rf"""
WITH docs AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
keyed AS (
  SELECT doc_id, lines, list_transform(lines, lambda x: {_LOWER.format("trim(x, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13))")}) AS keys
  FROM docs),
heavy AS (
  SELECT key FROM (SELECT DISTINCT doc_id, unnest(keys) AS key FROM keyed) WHERE length(key) >= 1
  GROUP BY key HAVING count(*) >= 10),
lines AS (SELECT doc_id, unnest(lines) AS line, unnest(keys) AS key, generate_subscripts(lines, 1) AS pos FROM keyed)
SELECT l.doc_id, count(*)::BIGINT AS n_lines, count(h.key)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(l.line, chr(10) ORDER BY l.pos) FILTER (h.key IS NULL), '')) AS kept_sha256
FROM lines l LEFT JOIN heavy h ON l.key = h.key GROUP BY l.doc_id""",
    "op9_exact_dedup": f"""
WITH t AS (SELECT doc_id, sha256({_LOWER.format("coalesce(text, '')")}) AS text_sha256 FROM documents),
g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*)::BIGINT AS group_size FROM t GROUP BY text_sha256)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, t.text_sha256 FROM t JOIN g USING (text_sha256)""",
}
