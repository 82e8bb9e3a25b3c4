"""One query for each operator, with production parameters over its whole table, and SQL where SQL can tell the result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe_trie, exact_dedup, license_rules, line_dedup, media, mixing, secrets, simhash, token_count, toxicity


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(_documents(spark, sf_dir)).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_components(_documents(spark, sf_dir)).select("doc_id", "fingerprint", "component_id")


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = mixing.schedule(_documents(spark, sf_dir))
    return plan.select("doc_id", "size", "source_size", "target", "taken")


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_report(_documents(spark, sf_dir))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.token_counts(_documents(spark, sf_dir), _vocabulary("byte_bpe_50k.json"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op7_media_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_columns(_documents(spark, sf_dir))


def op8_bpe_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_trie.encoded_digests(_documents(spark, sf_dir), _vocabulary("word_bpe_49k.json"))


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_rules.license_scan(_documents(spark, sf_dir))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_scan(_documents(spark, sf_dir))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_exact_dedup, op2_simhash_near_dedup, op3_source_mix, op4_line_dedup, op5_token_counts, op6_toxicity, op7_media_chunks, op8_bpe_trie, op9_license_scan, op10_secret_scan)}


OP1_SQL = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS plain FROM documents
), g AS (SELECT *, sha256(plain) AS sha FROM d)
SELECT doc_id, first_value(doc_id) OVER best AS keep_id, count(*) OVER (PARTITION BY plain) AS group_size,
       row_number() OVER best = 1 AS kept, sha AS text_sha256
FROM g WINDOW best AS (PARTITION BY plain ORDER BY n DESC, doc_id)
"""

OP3_SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
         substr(md5(concat(coalesce(CAST(doc_id AS VARCHAR), ''), ':7:', coalesce(text, ''))), 1, 16) AS turn FROM documents
), s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS queue FROM d GROUP BY source
), w AS (SELECT *, CAST(CASE (queue - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS DOUBLE) AS weight, 3 * source_size AS cap FROM s
), l AS (
  SELECT *, row_number() OVER by_level AS place,
         CAST(sum(source_size) OVER () - coalesce(sum(cap) OVER (by_level ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE)
         / (sum(weight) OVER () - coalesce(sum(weight) OVER (by_level ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level
  FROM w WINDOW by_level AS (ORDER BY cap / weight, source NULLS LAST)
), f AS (SELECT place, level FROM l WHERE cap > weight * level ORDER BY place LIMIT 1
), t AS (
  SELECT l.source, queue, source_size, CASE WHEN f.place IS NULL OR l.place < f.place THEN CAST(cap AS DOUBLE) ELSE weight * f.level END AS target FROM l LEFT JOIN f ON true
), q AS (
  SELECT d.*, queue, source_size, target, CAST(sum(size) OVER (PARTITION BY queue ORDER BY turn, doc_id NULLS LAST, size, rid) - size AS BIGINT) AS before
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
), c AS (SELECT q.*, copy, copy * source_size + before AS begins FROM q, (VALUES (0), (1), (2)) v(copy) WHERE size > 0 AND target > 0
), words AS (
  SELECT rid, queue, turn, doc_id, size, copy, CAST(0 AS BIGINT) AS spot, size AS n, CAST(begins + size AS DOUBLE) / target AS finish FROM c WHERE begins + size <= target
  UNION ALL
  SELECT rid, queue, turn, doc_id, size, copy, spot, 1, CAST(begins + spot + 1 AS DOUBLE) / target
  FROM (SELECT *, unnest(range(0, size)) AS spot FROM c WHERE begins + size > target AND begins < target + 1000)
), o AS (SELECT *, sum(n) OVER (ORDER BY finish, queue, turn, doc_id NULLS LAST, size, copy, spot, rid) AS sent FROM words
), g AS (SELECT rid, sum(greatest(0, least(n, (SELECT sum(size) FROM d) - (sent - n)))) AS taken FROM o GROUP BY rid)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target, CAST(coalesce(taken, 0) AS BIGINT) AS taken FROM q LEFT JOIN g USING (rid)
"""

OP4_SQL = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents
), k AS (
  SELECT *, translate(regexp_replace(regexp_replace(line, '^[\x20\x09-\x0D]+', ''), '[\x20\x09-\x0D]+$', ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l
), r AS (SELECT key, max(doc_id) AS top FROM k WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3
), m AS (SELECT k.*, r.key IS NOT NULL AND k.doc_id <> r.top AS gone FROM k LEFT JOIN r ON k.key = r.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_dedup": OP1_SQL, "op3_source_mix": OP3_SQL, "op4_line_dedup": OP4_SQL}
