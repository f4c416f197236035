"""Corpus pipeline: documents to packed training sequences.

``STAGES`` lists the stages in order. Each takes ``(spark, docs, sf_dir)`` and works on
all that the stage before kept; all but the last return the columns of ``documents``
(``n_chars`` follows the text). ``run`` writes each stage's result to the shared folder
and reads it again, so a lost executor never costs a finished stage. Stages with
Python workers first have the executors give back the heap that earlier stages left free.

Nulls, empty and very long texts, ties, repeated rows and extra columns are handled as
the stages' operators say; rows that share an id are judged each by its own text; an empty table gives no pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from padgrad.llm.decontamination import decontaminate
from padgrad.llm.line_dedup import dedup_lines
from padgrad.llm.near_dedup import drop_near_duplicates
from padgrad.llm.packing import pack_documents
from padgrad.llm.quality import score_quality
from padgrad.llm.workers import shrink_heaps
from padgrad.shared import written

#: Documents that score less are rejected.
LEAST_QUALITY = 0.3
MIN_DOCS, NEAR_PERCENT, LEAK_SIMILARITY = 10, 80, 0.8


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject."""
    shrink_heaps(spark)
    scored = score_quality(docs, _table(spark, sf_dir, "labels").select("doc_id", "quality"))
    return scored.where(F.col("quality_score") >= LEAST_QUALITY).select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document without the lines that many documents have."""
    out = dedup_lines(docs, MIN_DOCS)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast("long"))
    return out.select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near-duplicates, the one with the smallest id (a null id last)."""
    shrink_heaps(spark)
    return drop_near_duplicates(docs, NEAR_PERCENT)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose own text holds no benchmark item."""
    return decontaminate(docs, _table(spark, sf_dir, "benchmark"), LEAK_SIMILARITY).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of at most 2048 tokens."""
    import public_tokenizers

    shrink_heaps(spark)
    return pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), end_id=1)


STAGES = [("quality", quality), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("decontamination", decontamination), ("packing", packing)]

#: SQL cannot express the classifier, MinHash or the tokenizer; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
