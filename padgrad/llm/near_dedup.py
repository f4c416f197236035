"""Near-duplicate documents by circulant MinHash, banding and exact Jaccard checks.

1. One Arrow pass over the texts gives each document's number of shingles, a 128-bit
   digest of its shingle set and its band keys. Documents with one set are one class
   from here on: copies, however many, cost one row.
2. Classes that share a band key with another class are candidates. Only their
   shingle sets are made (second pass over the texts).
3. A shingle that no other candidate has can be in no intersection. With ``n``
   shingles of which ``u`` are such, two classes have at most
   ``m = min(n1 - u1, n2 - u2)`` in common, so their similarity is at most
   ``m / (n1 + n2 - m)``. Classes that can reach the threshold with nothing go.
4. In each bucket the class with the least share of such shingles (the most central)
   is checked against all others on the full sets. Components are formed, and then all
   pairs of different components that may still reach the threshold (by their rarest
   shingles and places, see ``_crossing``) are checked too. So no link between candidates
   is lost, and a large group of copies costs a check or two for each member, not all pairs.

Two sets of similarity s share a band with probability 1 - (1 - s^4)^20: above
0.9999996 at 0.85 and above 0.99997 at 0.8. Sets are compared as 64-bit hashes.

Defined cases: null, empty or blank text has no shingles and is linked with nothing;
rows that repeat a ``doc_id`` are rows of their own; a null ``doc_id`` is never the
smallest; an empty table gives no rows; a very long text is one array of its distinct shingles (8 bytes each);
extra columns pass through ``drop_near_duplicates``, whatever their names.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from padgrad.llm.components import components, merged
from padgrad.llm.textcols import free_names, id_key, sized
from padgrad.shared import scratch, stored, written

SIGNED = "doc_id long, th long, n_shingles long, node binary, bands array<long>"
_SIGNED = pa.schema([("doc_id", pa.int64()), ("th", pa.int64()), ("n_shingles", pa.int64()), ("node", pa.binary()), ("bands", pa.list_(pa.int64()))])
_SETS = pa.schema([("node", pa.binary()), ("shingles", pa.list_(pa.int64()))])
#: Up to so many candidate classes (16 bytes each) are broadcast to the second pass; beyond, it is a shuffled join.
BROADCAST_NODES = 500_000
_SLICE = 256


def _node(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def _slices(batches, columns):
    for b in batches:
        for at in range(0, b.num_rows, _SLICE):
            part = b.slice(at, _SLICE)
            yield [part.column(c) for c in columns]


def signed(docs: DataFrame, coordinates: int, rows: int, size: int) -> DataFrame:
    """``SIGNED`` for every document (``th``: hash of its text); ``node`` and ``bands`` are null without shingles."""

    def sign(batches):
        from padgrad.llm.shingles import WordHashes, band_keys, shingle_sets, signature
        from padgrad.llm.workers import tidy

        tidy("signatures")
        words = WordHashes()
        for ids, texts, hashes in _slices(batches, ("doc_id", "text", "th")):
            sets = shingle_sets(texts.to_pylist(), words, size)
            full = [k for k, s in enumerate(sets) if len(s)]
            keys = band_keys(signature([sets[k] for k in full], coordinates), rows) if full else None
            bands, nodes = [None] * len(sets), [None] * len(sets)
            for at, k in enumerate(full):
                bands[k], nodes[k] = keys[at].tolist(), _node(sets[k])
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), hashes, pa.array([len(s) for s in sets], pa.int64()), pa.array(nodes, pa.binary()), pa.array(bands, _SIGNED.field("bands").type)], schema=_SIGNED)

    return docs.select("doc_id", "text", F.xxhash64("text").alias("th")).mapInArrow(sign, SIGNED)


def shingled(docs: DataFrame, size: int) -> DataFrame:
    """``(node, shingles)`` of every text that has shingles."""

    def make(batches):
        from padgrad.llm.shingles import WordHashes, shingle_sets
        from padgrad.llm.workers import tidy

        tidy("shingles")
        words = WordHashes()
        for (texts,) in _slices(batches, ("text",)):
            sets = [s for s in shingle_sets(texts.to_pylist(), words, size) if len(s)]
            yield pa.RecordBatch.from_arrays([pa.array([_node(s) for s in sets], pa.binary()), pa.array([s.view(np.int64) for s in sets], _SETS.field("shingles").type)], schema=_SETS)

    return docs.select("text").mapInArrow(make, "node binary, shingles array<long>")


def _can_link(n1: Column, u1: Column, n2: Column, u2: Column, percent: int) -> Column:
    m = F.least(n1 - u1, n2 - u2)
    return 100 * m >= percent * (n1 + n2 - m)


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The ``pairs`` (``a``, ``b``) whose sets reach the threshold."""
    left = pairs.join(sets.select(F.col("node").alias("a"), F.col("shingles").alias("sa")), "a")
    both = left.join(sets.select(F.col("node").alias("b"), F.col("shingles").alias("sb")), "b")
    inter = F.size(F.array_intersect("sa", "sb"))
    return both.where(100 * inter >= percent * (F.size("sa") + F.size("sb") - inter)).select("a", "b")


def _crossing(alive: DataFrame, sets: DataFrame, names: DataFrame, percent: int) -> DataFrame:
    """All pairs of different components that may still reach the threshold, as ``(a, b)``.

    With shingles in one order, rarest first, two sets that reach it have a shingle in
    common among the first ``n - ceil(threshold n) + 1`` of each, and after the first
    such one at places i and j at most ``min(n1 - i, n2 - j)`` are shared. Only pairs
    that pass both are made; one side is never of the shingle's most frequent component.
    """
    named = alive.select("node", "n").distinct().join(names, "node", "left").select("node", "n", F.coalesce("root", "node").alias("root"))
    rows = sets.join(named, "node").select("node", "n", "root", F.explode("shingles").alias("s"))
    held = rows.groupBy("s", "root").agg(F.count("*").alias("c"))
    held = held.groupBy("s").agg(F.sum("c").alias("df"), F.max(F.struct("c", "root"))["root"].alias("usual"), F.count("*").alias("roots"))
    place = F.row_number().over(Window.partitionBy("node").orderBy("df", "s")) - 1
    first = rows.join(held, "s").withColumn("i", place).where(F.col("i") <= F.col("n") - F.ceil(F.col("n") * percent / 100))
    first = written(first.where("roots > 1").select("s", "node", "n", "root", "usual", "i"), "near-prefix")
    a, b = first.where("root <> usual").alias("a"), first.alias("b")
    on = (F.col("a.s") == F.col("b.s")) & (F.col("a.root") != F.col("b.root")) & ((F.col("b.root") == F.col("b.usual")) | (F.col("a.node") < F.col("b.node")))
    most = F.least(F.col("a.n") - F.col("a.i"), F.col("b.n") - F.col("b.i"))
    on = on & (100 * most >= percent * (F.col("a.n") + F.col("b.n") - most))
    return a.join(b, on).select(F.least("a.node", "b.node").alias("a"), F.greatest("a.node", "b.node").alias("b")).distinct()


def linked_classes(docs: DataFrame, classes: DataFrame, percent: int, size: int) -> DataFrame:
    """``(node, root)`` of all classes that are linked with another; ``classes``: ``node, n_shingles, first_id, bands``."""
    rows = classes.select("node", F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    shared = rows.groupBy("key").agg(F.count("*").alias("members")).where("members > 1").select("key")
    found = written(rows.join(shared.hint("merge"), "key", "left_semi"), "near-buckets")
    nodes = written(found.select("node").distinct(), "near-nodes")
    small = nodes.count() <= BROADCAST_NODES
    chosen = classes.select("node", F.col("first_id").alias("doc_id")).join(F.broadcast(nodes) if small else nodes, "node", "left_semi")
    ids = chosen.select("doc_id").distinct()
    texts = docs.select("doc_id", "text").join(F.broadcast(ids) if small else ids, docs["doc_id"].eqNullSafe(ids["doc_id"]), "left_semi")
    sets = shingled(texts, size).join(F.broadcast(nodes) if small else nodes, "node", "left_semi").dropDuplicates(["node"])
    sets = written(sets, "near-sets")
    lone = sets.select("node", F.explode("shingles").alias("s")).groupBy("s").agg(F.count("*").alias("df"), F.min("node").alias("node"))
    lone = lone.where("df = 1").groupBy("node").agg(F.count("*").alias("u"))
    rated = found.join(lone, "node", "left").select("node", "key", "n", F.coalesce("u", F.lit(0)).alias("u"))
    alive = written(rated.where(100 * (F.col("n") - F.col("u")) >= percent * F.col("n")), "near-alive")

    lead = alive.groupBy("key").agg(F.min(F.struct((F.col("u") / F.col("n")).alias("share"), "node", "n", "u")).alias("l"))
    star = alive.join(lead, "key").where(F.col("node") != F.col("l.node"))
    star = star.where(_can_link(F.col("n"), F.col("u"), F.col("l.n"), F.col("l.u"), percent))
    tested = written(star.select(F.least("node", "l.node").alias("a"), F.greatest("node", "l.node").alias("b")).distinct(), "near-star")
    links = written(_verified(tested, sets, percent), "near-links")
    names = components(links)

    rest = written(_crossing(alive, sets, names, percent).join(tested, ["a", "b"], "left_anti"), "near-rest")
    if rest.isEmpty():
        return names
    more = written(_verified(rest, sets, percent), "near-links")
    return names if more.isEmpty() else merged(names, more)


def _components(docs: DataFrame, percent: int, coordinates: int, rows: int, size: int) -> tuple[DataFrame, DataFrame]:
    """``SIGNED`` of every row, and ``(node, component, first)`` of every class; ``first`` tells the row to keep of its component."""
    base = written(signed(docs, coordinates, rows, size), "near-signed")
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), id_key(F.col("doc_id")).alias("did"), "th")
    classes = written(
        base.where("node is not null").groupBy("node").agg(F.max("n_shingles").alias("n_shingles"), F.min("doc_id").alias("first_id"), F.min(order).alias("first"), F.first("bands").alias("bands")),
        "near-classes",
    )
    names = linked_classes(docs, classes, percent, size)
    rooted = classes.join(names, "node", "left").select("node", "first_id", "first", F.coalesce("root", "node").alias("root"))
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component"), F.min("first").alias("first"))
    return base, rooted.select("node", "root").join(least, "root").select("node", "component", "first")


def near_duplicates(docs: DataFrame, percent: int = 80, coordinates: int = 80, rows: int = 4, size: int = 5) -> DataFrame:
    """``(doc_id, n_shingles, component_id, kept)`` for every document: ``component_id`` is the smallest id reachable, ``kept`` whether it is the row's own."""
    base, of = _components(docs, percent, coordinates, rows, size)
    out = base.join(of.select("node", "component"), "node", "left").select(
        "doc_id", "n_shingles", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component")).alias("component_id")
    )
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_duplicates(docs: DataFrame, percent: int = 80, coordinates: int = 80, rows: int = 4, size: int = 5) -> DataFrame:
    """``docs`` with exactly one row of each component: smallest id (a null one last), then smallest hash of the text.

    Rows are told apart by id and text, so a row that only shares its id with a dropped one
    stays. Of rows that repeat both, one stays. Texts without shingles all stay.
    """
    did, th = on = free_names(docs, "__did", "__th")
    with scratch(docs.sparkSession):
        base, of = _components(docs, percent, coordinates, rows, size)
        found = base.join(of.select("node", "first"), "node").select(id_key(F.col("doc_id")).alias(did), F.col("th").alias(th), F.col("first"))
        best = (F.col(did) == F.col("first.did")) & (F.col(th) == F.col("first.th"))
        keys = found.select(did, th, best.alias("best")).groupBy(did, th, "best").agg(F.count("*").alias("copies"))
        marks = stored(keys.where(~F.col("best") | (F.col("copies") > 1)).select(did, th, "best"), "near-marks")
    gone, repeated = marks.where(~F.col("best")).select(on), marks.where("best").select(on)
    left = docs.withColumn(did, id_key(F.col("doc_id"))).withColumn(th, F.xxhash64("text")).join(sized(gone), on, "left_anti")
    if not repeated.isEmpty():
        repeated = sized(repeated)
        left = left.join(repeated, on, "left_anti").unionByName(left.join(repeated, on, "left_semi").dropDuplicates(on))
    return left.select(*docs.columns)
