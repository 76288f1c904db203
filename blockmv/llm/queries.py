"""Queries of the corpus operators, registered by ``__spark_entry__`` when this subpackage is present."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, fingerprints, importance, packing, quality_rules, simhash, suffix_dedup, toxicity, warc
from .common import table


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.removal_report(table(spark, sf_dir, "documents"))


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.compare_with_next(table(spark, sf_dir, "documents"))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = warc.read_archives(warc.write_archives(table(spark, sf_dir, "pages")))
    return records.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "archive_id", "error")


def op4_tool_call_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.link_conversations(table(spark, sf_dir, "conversations")).drop("message")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return importance.resample(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op8_forced_boundary_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return bpe.encode_digests(docs, public_tokenizers.path("word_bpe_49k.json")).drop("text")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.document_components(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_verdicts(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_suffix_dedup": op1_suffix_dedup,
    "op2_fingerprints": op2_fingerprints,
    "op3_warc": op3_warc,
    "op4_tool_call_linking": op4_tool_call_linking,
    "op5_toxicity": op5_toxicity,
    "op6_importance_resampling": op6_importance_resampling,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_forced_boundary_bpe": op8_forced_boundary_bpe,
    "op9_simhash": op9_simhash,
    "op10_quality_rules": op10_quality_rules,
}

#: Hashes, models and tokens have no SQL; tests hold those queries against brute force.
ORACLE_SQL: dict[str, str] = {
    "op4_tool_call_linking": """WITH RECURSIVE c AS (
  SELECT 'c' || conv_id || '-' || turn AS id, turn, text, role, conv_id, row_number() OVER () AS k FROM conversations WHERE role IN ('user', 'system')),
r AS (SELECT 'c' || conv_id || '-' || (turn - 1) AS id, turn, text FROM conversations WHERE role IS NULL OR role NOT IN ('user', 'system')),
w AS (SELECT DISTINCT a.id, b.id AS up FROM c a JOIN c b ON b.conv_id = a.conv_id AND (b.turn = a.turn - 2 OR (b.turn = a.turn - 1 AND b.role = 'system'))),
p AS (SELECT DISTINCT id, 0::BIGINT AS depth FROM c WHERE id NOT IN (SELECT id FROM w)
  UNION SELECT w.id, p.depth + 1 FROM p JOIN w ON w.up = p.id),
d AS (SELECT id, max(depth) AS depth FROM p GROUP BY id),
q AS (SELECT c.id, CASE role WHEN 'user' THEN 'ask' ELSE 'configure' END AS tool, c.turn, depth, c.text IS NOT NULL AS ok,
    CASE role WHEN 'user' THEN '{"conversation":' || conv_id || ',"prompt":' || to_json(c.text) || ',"turn":' || turn || '}'
      ELSE '{"instructions":' || to_json(c.text) || ',"turn":' || turn || '}' END AS args,
    row_number() OVER (PARTITION BY c.id ORDER BY role <> 'user', to_json(c.text)::VARCHAR, k) AS nth,
    row_number() OVER (PARTITION BY conv_id ORDER BY depth, turn, c.id, role <> 'user', to_json(c.text)::VARCHAR) - 1 AS ordinal
  FROM c LEFT JOIN d ON c.id = d.id)
SELECT coalesce(q.id, r.id) AS call_id,
  CASE WHEN q.id IS NULL THEN 'no_call' WHEN nth > 1 THEN 'repeated_call' WHEN r.id IS NULL THEN 'no_result' ELSE 'linked' END AS status,
  tool, q.turn AS call_position, r.turn AS result_position, depth, ordinal, ok AS arguments_valid,
  md5('{"arguments":' || coalesce(args, 'null') || ',"id":' || to_json(coalesce(q.id, r.id)) || ',"result":'
    || coalesce(to_json(r.text)::VARCHAR, 'null') || ',"tool":' || coalesce(to_json(tool)::VARCHAR, 'null') || '}') AS message_md5
FROM q FULL JOIN r ON q.id = r.id AND q.nth = 1
""",
}
