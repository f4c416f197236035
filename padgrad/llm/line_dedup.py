"""Line dedup: lines whose key occurs in many documents go, the rest is put together again.

Plan. One pass hashes every line's key (128 bits, two 64-bit hashes) into a narrow
table ``(document, row, position, hash)`` in the shared folder. Document counts per
hash are partial sums before the shuffle, so a line that a third of all documents
carry costs one row a task. Marking lines: keys with more than ``1/HOT_SHARE`` of all lines (lines,
not documents: one document may repeat a line without end) are at most ``HOT_SHARE`` many and are broadcast;
every other key holds less than that share of the rows, so an ordinary shuffled semi-join is even. Texts are
shuffled once, by document, to meet the positions they lose.

Defined cases: null or empty text is one empty line; empty keys are never dropped;
rows that repeat a ``doc_id`` (or have none) count as one document for the threshold
and are each rewritten by themselves; a very long text has as many rows of ``lines`` as lines;
an empty table gives no rows; extra columns pass through, and columns named
``n_lines``, ``n_dropped`` or ``text`` are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from padgrad.llm.textcols import ascii_lower, ascii_strip, id_key, text_lines
from padgrad.shared import written

#: More keys than this cannot each hold 1/HOT_SHARE of all lines.
HOT_SHARE = 1000
_SALT = 7919


def line_key(line: Column) -> Column:
    """What makes two lines equal: blanks stripped at both ends, A-Z lower-cased."""
    return ascii_lower(ascii_strip(line))


def _hashed_lines(docs: DataFrame) -> DataFrame:
    hashes = F.transform(
        F.transform(text_lines(F.col("text")), line_key),
        lambda k: F.when(k != "", F.struct(F.xxhash64(k).alias("h1"), F.xxhash64(k, F.lit(_SALT)).alias("h2"))),
    )
    return docs.select(
        id_key(F.col("doc_id")).alias("did"), F.xxhash64("text").alias("th"), F.posexplode(hashes).alias("pos", "h")
    ).where("h is not null").select("did", "th", "pos", "h.h1", "h.h2")


def frequent_keys(lines: DataFrame, min_docs: int) -> DataFrame:
    """``(h1, h2, n, held)``: keys found in at least ``min_docs`` documents, with their documents and lines."""
    per_doc = lines.groupBy("h1", "h2", "did").agg(F.count("*").alias("c"))
    return per_doc.groupBy("h1", "h2").agg(F.count("*").alias("n"), F.sum("c").alias("held")).where(F.col("n") >= min_docs)


def dropped_positions(lines: DataFrame, keys: DataFrame, total: int) -> DataFrame:
    """``(did, th, drop)``: positions of the lines to go, for each row that loses any."""
    cut = max(1, total // HOT_SHARE)
    hot = F.broadcast(keys.where(F.col("held") > cut).select("h1", "h2"))
    cold = keys.where(F.col("held") <= cut).select("h1", "h2").hint("merge")
    on = ["h1", "h2"]
    hits = lines.join(hot, on, "left_semi").unionByName(lines.join(hot, on, "left_anti").join(cold, on, "left_semi"))
    return hits.groupBy("did", "th").agg(F.collect_set("pos").alias("drop"))


def dedup_lines(docs: DataFrame, min_docs: int = 10) -> DataFrame:
    """``docs`` with ``text`` rewritten, ``n_lines`` (before) and ``n_dropped`` added."""
    lines = written(_hashed_lines(docs), "lines")
    keys = written(frequent_keys(lines, min_docs), "line-keys")
    drops = dropped_positions(lines, keys, lines.count())
    kept = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    parts = docs.select(
        *[F.col(c).alias(f"__c{i}") for i, c in enumerate(kept)],
        id_key(F.col("doc_id")).alias("__did"), F.xxhash64("text").alias("__th"), text_lines(F.col("text")).alias("__lines"),
    )
    both = parts.join(drops.select(F.col("did").alias("__did"), F.col("th").alias("__th"), F.col("drop").alias("__drop")), ["__did", "__th"], "left")
    n = F.size("__lines")
    stay = F.array_except(F.sequence(F.lit(0), n - 1), F.col("__drop"))
    text = F.when(F.col("__drop").isNull(), F.array_join("__lines", "\n")).otherwise(
        F.array_join(F.transform(stay, lambda i: F.get(F.col("__lines"), i)), "\n")
    )
    out = [F.col(f"__c{i}").alias(c) if c != "text" else text.alias("text") for i, c in enumerate(kept)]
    return both.select(*out, n.cast("long").alias("n_lines"), F.coalesce(F.size("__drop"), F.lit(0)).cast("long").alias("n_dropped"))
