"""Quality by nearest-neighbour voting in a latent-semantic space.

A text is a bag of terms: its words (A-Z lower-cased, hashed), the shapes of its words
(letters and digits as classes, runs squeezed, marks kept) and how many of its words
repeat the word before, in steps of that share. Term weights are
``log(1 + count) * idf``. A singular value decomposition of the labelled sample gives
the latent space; labelled vectors are unit vectors there. Every document is
multiplied with all labelled vectors in blocks, exactly, and the ``neighbours``
nearest vote with weight ``similarity ** sharpness``.

Bounds: the sample holds at most ``max_labelled`` texts (those of least seeded hash
of their id), so the broadcast (``terms x rank`` and ``max_labelled x rank`` floats, a
few MB) does not grow with the input. Everything else covers whole texts of all rows
in one Arrow pass without a shuffle.

Defined cases: null, empty or blank text, and any text without a neighbour of positive
similarity, scores the mean label of the sample; with no labelled row at all every
score is 0.5; equal texts in the sample count once, with the mean of their labels; of neighbours
equally similar at the last place any may vote (the choice is fixed for a sample); repeated rows are scored each; very long
texts are counted whole, as one row of terms; extra columns pass through and ``quality_score`` is replaced; an empty table gives no rows.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

WORD_TERMS, SHAPE_TERMS = 6144, 2048
REPEAT_TERMS = 8
TERMS = WORD_TERMS + SHAPE_TERMS + REPEAT_TERMS
#: Words are many and each says little; shapes and repeats are few and say much.
WORD_WEIGHT, REPEAT_WEIGHT = 0.4, 12.0
_RUNS = re.compile(rb"(.)\1+")
_CLASSES = bytes(97 if 97 <= b < 123 or b >= 128 else 65 if 65 <= b < 91 else 48 if 48 <= b < 58 else b for b in range(256))


class TermIds(dict):
    """Word to its two term numbers packed in one integer; bounded."""

    def __init__(self, most: int = 400_000):
        import zlib

        super().__init__()
        self.most, self.crc = most, zlib.crc32

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        shape = _RUNS.sub(rb"\1", word.translate(_CLASSES))[:24]
        self[word] = k = (self.crc(word.lower()) % WORD_TERMS) * SHAPE_TERMS + self.crc(shape) % SHAPE_TERMS
        return k


def term_weights(texts: list[str | None], ids: TermIds) -> np.ndarray:
    """``log(1 + count)`` of every term, a row for each text."""
    rows = []
    for t in texts:
        w = (t or "").encode("utf-8", "surrogatepass").split()
        rows.append(np.fromiter(map(ids.__getitem__, w), np.int64, len(w)))
    sizes = [len(r) for r in rows]
    k = np.concatenate(rows) if rows else np.zeros(0, np.int64)
    base = np.repeat(np.arange(len(rows), dtype=np.int64) * TERMS, sizes)
    at = np.concatenate([base + k // SHAPE_TERMS, base + WORD_TERMS + k % SHAPE_TERMS])
    counts = np.bincount(at, minlength=len(rows) * TERMS).astype(np.float32)
    used = np.flatnonzero(counts)
    counts[used] = np.log1p(counts[used])
    out = counts.reshape(len(rows), TERMS)
    out[:, :WORD_TERMS] *= WORD_WEIGHT
    doc = base[1:] // TERMS
    again = np.bincount(doc[(k[1:] == k[:-1]) & (base[1:] == base[:-1])], minlength=len(rows))
    step = -(-again * (REPEAT_TERMS - 1) // np.maximum(sizes, 1))  # 0: no repeats; else the share in sevenths, upwards
    some = np.flatnonzero(np.array(sizes) > 0)
    out[some, WORD_TERMS + SHAPE_TERMS + step[some]] = REPEAT_WEIGHT
    return out


def _unit(x: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


class Neighbours:
    """The latent space, the labelled vectors in it, and their labels."""

    def __init__(self, texts: list[str], labels: list[float], rank: int = 48, neighbours: int = 25, sharpness: int = 8):
        merged: dict[str, list[float]] = {}
        for t, y in zip(texts, labels, strict=True):
            merged.setdefault(t, []).append(y)
        self.labels = np.array([sum(v) / len(v) for v in merged.values()], np.float32)
        self.neighbours, self.sharpness = neighbours, sharpness
        self.prior = float(self.labels.mean()) if len(self.labels) else 0.5
        if not merged:
            self.space, self.vectors = np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32)
            return
        x = term_weights(list(merged), TermIds())
        seen = (x > 0).sum(axis=0)
        idf = np.log((1 + len(x)) / (1 + seen)).astype(np.float32) + 1
        x = _unit(x * idf)
        values, left = np.linalg.eigh(x @ x.T)  # right singular vectors from the small side
        keep = np.argsort(-values)[: min(rank, len(x))]
        keep = keep[values[keep] > 1e-6]
        self.space = (idf[:, None] * (x.T @ left[:, keep]) / np.sqrt(values[keep])).astype(np.float32)
        self.vectors = _unit(x @ (self.space / idf[:, None]))

    def scores(self, weights: np.ndarray) -> np.ndarray:
        out = np.full(len(weights), self.prior)
        if not len(self.vectors):
            return out
        sim = _unit(weights @ self.space) @ self.vectors.T
        k = min(self.neighbours, sim.shape[1])
        near = np.argpartition(-sim, k - 1, axis=1)[:, :k]
        w = np.maximum(np.take_along_axis(sim, near, 1), 0).astype(np.float64) ** self.sharpness
        total = w.sum(axis=1)
        good = total > 0
        out[good] = ((w * self.labels[near]).sum(axis=1)[good] / total[good]).clip(0, 1)
        return out


def held_out(doc_id: Column) -> Column:
    """Rows that no label is learned from: crc32 of the id as text, mod 5, is 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, max_labelled: int = 2048, seed: int = 11) -> tuple[list[str], list[float]]:
    """At most ``max_labelled`` texts with their quality, none of them held out."""
    known = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = known.groupBy("doc_id").agg(F.avg("quality").alias("y")).orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(max_labelled)
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").orderBy("doc_id", "text").limit(max_labelled).collect()
    return [r["text"] for r in rows], [float(r["y"]) for r in rows]


def score_quality(docs: DataFrame, labels: DataFrame, max_labelled: int = 2048, step: int = 128) -> DataFrame:
    """``docs`` with ``quality_score`` (0 to 1) of every row's whole text."""
    model = docs.sparkSession.sparkContext.broadcast(Neighbours(*labelled_sample(docs, labels, max_labelled)))
    kept = docs.drop("quality_score")
    schema = T.StructType([*kept.schema.fields, T.StructField("quality_score", T.DoubleType())])

    def score(batches):
        from padgrad.llm.workers import tidy

        tidy("quality")
        ids = TermIds()
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                s = model.value.scores(term_weights(part.column("text").to_pylist(), ids))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(s, pa.float64())], names=[*part.schema.names, "quality_score"])

    return kept.mapInArrow(score, schema)
