"""Sharding by proportional stratified interleaving.

Rows of a source are put in a seeded random order; a row's fractional rank is its
place in that order over the source's size. Sorting all rows by fractional rank
spreads every source evenly, so equal cuts of that order all match the mixture and
differ by at most one row (law ``rows``).

Ranks are exact and distributed: rows are bucketed by their hash (about the square
root of all rows buckets), bucket counts are summed, and only rows of one bucket are
ranked together. A source with a third of all rows spreads over all buckets. Only
narrow rows (no texts) are shuffled.

Defined cases: null text has size 16 and checksum 0; a null source is a stratum of
its own; repeated rows are rows of their own, and rows that are alike in all take any order among them; a very
long text counts by its bytes and is never moved; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ROW_OVERHEAD = 16


def _offsets(counts: DataFrame, bucket: str, part: list[str]) -> DataFrame:
    """Adds ``before`` (rows in earlier buckets) and ``total`` for each ``part``."""
    w = Window.partitionBy(*part) if part else Window.partitionBy()
    running = w.orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("before", F.coalesce(F.sum("n").over(running), F.lit(0))).withColumn("total", F.sum("n").over(w))


def interleaved_order(rows: DataFrame, n_rows: int, seed: int = 17) -> DataFrame:
    """``rows`` (``source``, ``doc_id``, ...) with ``place``: 0-based place in the interleaved order."""
    buckets = max(1, math.isqrt(n_rows))
    stratum = F.struct(F.col("source").isNull().alias("none"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("name"))
    h = F.xxhash64(F.lit(seed), "doc_id", "text_crc32", "size")
    base = rows.withColumn("stratum", stratum).withColumn("h", h).withColumn("b", F.pmod(F.shiftrightunsigned("h", 16), F.lit(buckets)))
    tie = ["h", "doc_id", "text_crc32"]
    by = _offsets(base.groupBy("stratum", "b").agg(F.count("*").alias("n")), "b", ["stratum"]).drop("n")
    ranked = base.withColumn("r", F.row_number().over(Window.partitionBy("stratum", "b").orderBy(*tie)))
    # exact fraction: (2 rank - 1) / (2 size), kept as a double only for the bucket and the order
    frac = ranked.join(by.hint("merge"), ["stratum", "b"]).withColumn("f", (F.col("before") + F.col("r") - 0.5) / F.col("total"))
    frac = frac.drop("before", "total", "r", "b").withColumn("g", F.least(F.floor(F.col("f") * buckets), F.lit(buckets - 1)))
    order = _offsets(frac.groupBy("g").agg(F.count("*").alias("n")), "g", []).drop("n", "total")
    w = Window.partitionBy("g").orderBy("f", "stratum", *tie)
    out = frac.withColumn("r", F.row_number().over(w)).join(order.hint("merge"), "g")
    return out.withColumn("place", F.col("before") + F.col("r") - 1).drop("g", "before", "r", "f", "h", "stratum")


def shard_rows(docs: DataFrame, shards: int = 40, seed: int = 17) -> DataFrame:
    """``(doc_id, source, size, text_crc32, shard, slot)``: shard sizes differ by one row at most."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", "source", (F.octet_length(text) + ROW_OVERHEAD).cast("long").alias("size"), F.crc32(text.cast("binary")).cast("long").alias("text_crc32"))
    n = docs.count()
    placed = interleaved_order(rows, n, seed).withColumn("shard", F.expr(f"int((place * {shards}) div {max(1, n)})"))
    first = F.expr(f"(shard * {n} + {shards - 1}) div {shards}")
    return placed.withColumn("slot", F.col("place") - first).drop("place")
