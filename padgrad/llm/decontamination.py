"""Benchmark decontamination: item-sized windows around rare shingles, exact check.

1. Words are runs of letters and digits, lower-cased. Every position of every
   document gives the hash of its k-word shingle (k = 5, or an item's length where
   that is less). A window as similar to an item as asked for shares at least
   ``threshold`` of the weight of the item's distinct shingles, so it has one of the item's
   rarest ones that together weigh more than the rest: only those are looked up. This
   loses no match and keeps shingles that many items share out of the search.
2. A hit at position p of a shingle of an item of L words is held by the windows of L
   words that start at ``p - L + k`` to ``p``, cut off at the text's end. All of them are
   made for that item, so words put in or left out before the hit do not matter.
3. Windows are checked exactly: shared over united distinct shingles, weighted by their
   characters.

No fingerprint stands between a window and its check: a SimHash within any radius below 64 bits
would lose some similar windows.

All of it is DataFrame expressions. Shingle rows are made and filtered within the scan
when the items' shingles are few enough to broadcast (their number is checked);
otherwise they are shuffled. Documents with hits are read again by id, likewise.

Defined cases: null or empty text has no words and no match; an item without words
matches nothing; repeated documents are found each; an empty benchmark finds nothing, an empty table
gives no rows. Of windows that are equally similar the first one is reported; items with one id and
different words are items of their own and the best of them is reported. Very long texts have a row for each
hit and its windows, never for each position, after the scan. Extra columns pass through, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from padgrad.llm.textcols import free_names, id_key, sized
from padgrad.shared import scratch, stored, written


def plain_words(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", -1), lambda w: w != "")


def shingle_hashes(words: Column, k: int) -> Column:
    """Hash of the ``k``-word shingle at each position; empty if there are fewer words."""
    last = F.size(words) - k
    at = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(k)]))


def shingle_texts(words: Column, k: Column) -> Column:
    at = F.when(F.size(words) >= k, F.sequence(F.lit(0), F.size(words) - k)).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda i: F.array_join(F.slice(words, i + 1, k), " "))


def item_table(benchmark: DataFrame, size: int) -> DataFrame:
    """``(item_id, words, n, k, item)`` of items that have words; ``item`` stands for id and words."""
    out = benchmark.select("item_id", plain_words(F.col("text")).alias("words")).withColumn("n", F.size("words"))
    out = out.where("n > 0").withColumn("k", F.least(F.col("n"), F.lit(size))).withColumn("item", F.xxhash64("item_id", "words"))
    return out.dropDuplicates(["item"])


def anchors(items: DataFrame, threshold: float, sizes: list[int]) -> DataFrame:
    """``(k, hash, n, item)``: the rarest distinct shingles of each item that a match must have one of."""
    parts = []
    for k in sizes:
        own = items.where(F.col("k") == k)
        parts.append(own.select("item", "n", "k", F.explode(F.zip_with(shingle_hashes(F.col("words"), k), shingle_texts(F.col("words"), F.col("k")), lambda h, t: F.struct(h.alias("hash"), F.length(t).alias("weight")))).alias("s")))
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    rows = rows.select("item", "n", "k", "s.hash", "s.weight").dropDuplicates(["item", "hash"])
    common = rows.groupBy("k", "hash").agg(F.count("*").alias("in_items"))
    rows = rows.join(common, ["k", "hash"])
    by = Window.partitionBy("item")
    order = by.orderBy("in_items", "hash").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("total", F.sum("weight").over(by)).withColumn("before", F.coalesce(F.sum("weight").over(order), F.lit(0)))
    # a hair more than asked for, so that rounding of the threshold loses nothing
    return rows.where(F.col("before") <= (1 - threshold + 1e-9) * F.col("total")).select("k", "hash", "n", "item")


def matching_windows(docs: DataFrame, benchmark: DataFrame, threshold: float, size: int) -> DataFrame:
    """``(doc_id, did, th, item_id, similarity, start, n)``: all windows that reach the threshold; ``did`` and ``th`` stand for id and text."""
    items = written(item_table(benchmark, size), "leak-items")
    sizes = sorted(r["k"] for r in items.select("k").distinct().collect())  # at most ``size`` values
    if not sizes:
        return docs.sparkSession.createDataFrame([], "doc_id long, did long, th long, item_id long, similarity double, start int, n int")
    keys = written(anchors(items, threshold, sizes), "leak-anchors")
    base = docs.select("doc_id", id_key(F.col("doc_id")).alias("did"), F.xxhash64("text").alias("th"), plain_words(F.col("text")).alias("w"))
    hits = None
    for k in sizes:
        rows = base.select("did", "th", F.posexplode(shingle_hashes(F.col("w"), k)).alias("pos", "hash"))
        own = keys.where(F.col("k") == k)
        found = rows.join(sized(own.select("hash").distinct()), "hash", "left_semi").join(sized(own.select("hash", "n", "item")), "hash")
        first = F.greatest(F.lit(0), F.col("pos") - F.col("n") + k)
        found = found.select("did", "th", "item", "n", F.explode(F.sequence(first, F.col("pos"))).alias("start"))
        hits = found if hits is None else hits.unionByName(found)
    hits = written(hits.distinct(), "leak-windows")
    own = sized(hits.select("did", "th").distinct())
    texts = base.join(own, ["did", "th"], "left_semi").dropDuplicates(["did", "th"])
    windows = hits.join(texts, ["did", "th"]).select("doc_id", "did", "th", "item", "start", "n", F.slice("w", F.col("start") + 1, F.col("n")).alias("part"))
    pairs = windows.join(items.select("item", "item_id", "words", "k"), "item")
    a, b = shingle_texts(F.col("part"), F.col("k")), shingle_texts(F.col("words"), F.col("k"))

    def weight(s):
        return F.aggregate(s, F.lit(0), lambda acc, x: acc + F.length(x))

    sim = pairs.select("doc_id", "did", "th", "item_id", "start", "n", a.alias("a"), b.alias("b")).withColumn("similarity", weight(F.array_intersect("a", "b")) / weight(F.array_union("a", "b")))
    return sim.where(F.col("similarity") >= threshold).drop("a", "b")


def find_leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.8, size: int = 5) -> DataFrame:
    """``(doc_id, item_id, similarity, start, words)``: the best window of each document for each item it holds."""
    found = matching_windows(docs, benchmark, threshold, size)
    best = found.groupBy("did", "item_id").agg(F.max(F.struct("similarity", (-F.col("start")).alias("neg"), "n", "doc_id")).alias("x"))
    return best.select("x.doc_id", "item_id", "x.similarity", (-F.col("x.neg")).alias("start"), F.col("x.n").alias("words"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.8) -> DataFrame:
    """``docs`` without the rows whose own text holds a benchmark item; other rows with the same id, or none, stay."""
    did, th = free_names(docs, "__did", "__th")
    with scratch(docs.sparkSession):
        found = matching_windows(docs, benchmark, threshold, 5)
        leaks = stored(found.select(F.col("did").alias(did), F.col("th").alias(th)).distinct(), "leak-docs")
    rows = docs.withColumn(did, id_key(F.col("doc_id"))).withColumn(th, F.xxhash64("text"))
    return rows.join(sized(leaks), [did, th], "left_anti").drop(did, th)
