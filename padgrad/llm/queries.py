"""Queries ``opN_<name>`` of the text operators, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.line_dedup import dedup_lines

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs, min_docs=10).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


OP3_SQL = r"""
WITH lines AS (
  SELECT doc_id, generate_subscripts(parts, 1) AS pos, unnest(parts) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents)
), keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM lines
), frequent AS (
  SELECT k FROM keyed WHERE k <> '' GROUP BY k HAVING count(DISTINCT doc_id) >= 10
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (f.k IS NOT NULL) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (f.k IS NULL), '')) AS kept_sha256
FROM keyed LEFT JOIN frequent f USING (k)
GROUP BY doc_id
"""


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.sharding import shard_rows

    out = shard_rows(_table(spark, sf_dir, "documents").select("doc_id", "source", "text"), shards=40)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from padgrad.llm.packing import pack_documents

    return pack_documents(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), end_id=1)


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from padgrad.llm.token_files import read_token_files, write_token_files
    from padgrad.shared import fresh_path

    folder = fresh_path(spark, "token-ids")
    files = write_token_files(_table(spark, sf_dir, "documents"), folder, public_tokenizers.path("word_bpe_49k.json"), end_id=2, space_joins=False)
    return read_token_files(spark, folder, files)


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.quality import held_out, score_quality

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score_quality(docs, _table(spark, sf_dir, "labels").select("doc_id", "quality"))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("quality_score").alias("score"), (F.col("quality_score") >= 0.3).cast("int").alias("predicted"))


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.main_text import extract_main_text

    return extract_main_text(_table(spark, sf_dir, "pages"))


def op6_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.fingerprint import fingerprint_edits

    return fingerprint_edits(_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_context_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.context_tree import score_texts

    out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2, F.lit(False))
    scored = score_texts(_table(spark, sf_dir, "documents").select("doc_id", "text"), ~out)
    return scored.select("doc_id", (~F.col("trained")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.decontamination import find_leaks

    leaks = find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))
    return leaks.withColumn("similarity", F.round("similarity", 6))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from padgrad.llm.near_dedup import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "documents"), percent=85)


def queries() -> dict:
    return {"op1_packing": op1_packing, "op2_quality": op2_quality, "op3_line_dedup": op3_line_dedup, "op4_main_text": op4_main_text, "op5_token_files": op5_token_files, "op6_fingerprint": op6_fingerprint, "op7_context_tree": op7_context_tree, "op8_sharding": op8_sharding, "op9_decontamination": op9_decontamination, "op10_near_dedup": op10_near_dedup}


def oracle_sql() -> dict:
    return {"op3_line_dedup": OP3_SQL}
