"""Packing of token streams by an order-preserving dynamic program.

The documents stand in order of their ids in one stream. Windows of at most
``window`` tokens cover it; a cut is possible at every document end, at every
sentence end and, where neither is near, inside a sentence. The program minimises

    padding of every window + a fixed cost of each window + a penalty of each cut

where a window whose length is a power of two needs no padding. With
``cost(j) = min over i of cost(i) + window - (p[j] - p[i]) + ...`` the part that
depends on ``i`` is ``cost(i) + p[i]``, so a monotone queue over the last ``window``
tokens gives each transition in constant time; the few unpadded lengths are looked
up besides.

Spark: ids are made and packed in one Arrow pass over ranges of ``doc_id``. A range
is packed block by block (about ``block_tokens``); the last windows of a block are
given back to the next block, so memory is bounded and only the end of a range can
be ragged. A lost task is simply run again.

Defined cases: null or empty text is the end id alone; repeated ids are packed one
after the other, in order of their texts' hashes; a document longer than a window is cut, and one longer than a
block is packed as one block; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class PackCost:
    """Costs in tokens."""

    def __init__(self, window: int = 2048, sentence_cut: int = 4, hard_cut: int = 24, per_window: int = 16, hard_step: int = 32):
        self.window, self.sentence_cut, self.hard_cut, self.per_window, self.hard_step = window, sentence_cut, hard_cut, per_window, hard_step
        #: Lengths that need no padding; shorter powers of two save less than a window costs.
        self.unpadded = [2**k for k in range(7, window.bit_length()) if 2**k <= window]


def _distinct(x: np.ndarray) -> np.ndarray:
    x = np.sort(x)
    return x[np.append(True, x[1:] != x[:-1])]


def cut_points(total: int, doc_ends: np.ndarray, sentence_ends: np.ndarray, cost: PackCost) -> tuple[np.ndarray, np.ndarray]:
    """Possible cuts in ``[0, total]`` in order and the penalty of each."""
    soft = _distinct(np.concatenate([[0], doc_ends, sentence_ends]))
    soft = soft[soft <= total]
    if not len(soft) or soft[-1] != total:
        soft = np.append(soft, total)
    gaps = np.diff(soft)
    wide = np.flatnonzero(gaps > 2 * cost.hard_step)
    hard = [np.arange(soft[k] + cost.hard_step, soft[k + 1], cost.hard_step) for k in wide]
    ends = total - np.array(cost.unpadded, np.int64)
    hard.append(ends[ends > 0])
    points = _distinct(np.concatenate([soft, *hard]))
    fee = np.full(len(points), cost.hard_cut, np.int64)
    fee[np.searchsorted(points, sentence_ends[sentence_ends <= total])] = cost.sentence_cut
    fee[np.searchsorted(points, doc_ends[doc_ends <= total])] = 0
    fee[[0, -1]] = 0
    return points, fee


def best_cuts(points: np.ndarray, fee: np.ndarray, cost: PackCost) -> list[int]:
    """Indexes into ``points`` of the window borders, from 0 to the last, at least total cost."""
    n, w = len(points), cost.window
    # borders of unpadded windows: pairs (j, i) with p[j] - p[i] a power of two
    free: list[tuple | None] = [None] * n
    for size in cost.unpadded:
        at = np.searchsorted(points, points - size)
        hit = np.flatnonzero((points >= size) & (points[at] == points - size))
        for j, i in zip(hit.tolist(), at[hit].tolist(), strict=True):
            free[j] = (*free[j], i) if free[j] else (i,)
    p, c = points.tolist(), (fee + cost.per_window).tolist()
    f, back = [0] * n, [0] * n
    keys, queue = [0] * n, deque([0])
    for j in range(1, n):
        pj, low = p[j], p[j] - w
        while p[queue[0]] < low:
            queue.popleft()
        i = queue[0]
        best = keys[i] + w - pj
        if free[j]:
            for a in free[j]:
                if f[a] < best:
                    best, i = f[a], a
        f[j] = best = best + c[j]
        back[j] = i
        key = keys[j] = best + pj
        while queue and keys[queue[-1]] >= key:
            queue.pop()
        queue.append(j)
    borders = [n - 1]
    while borders[-1]:
        borders.append(back[borders[-1]])
    return borders[::-1]


class Packer:
    """Packs a stream of documents; ``flush`` gives the finished pieces."""

    def __init__(self, ends_sentence: np.ndarray, cost: PackCost, first_sequence: int, block_tokens: int):
        self.ends_sentence, self.cost, self.sequence, self.block = ends_sentence, cost, first_sequence, block_tokens
        self.docs: list[tuple[object, np.ndarray]] = []
        self.done, self.held = 0, 0  # ids of the first document that are packed; ids in hand

    def add(self, doc_id, ids: np.ndarray) -> bool:
        self.docs.append((doc_id, ids))
        self.held += len(ids)
        return self.held >= self.block

    def flush(self, last: bool) -> list[tuple]:
        if not self.docs:
            return []
        parts = [ids if k else ids[self.done :] for k, (_, ids) in enumerate(self.docs)]
        ids = np.concatenate(parts)
        stops = np.cumsum([len(x) for x in parts])
        sentence = np.flatnonzero(self.ends_sentence[ids]) + 1
        points, fee = cut_points(len(ids), stops, sentence, self.cost)
        borders = points[best_cuts(points, fee, self.cost)]
        if not last:  # the block's end was no real cut: the windows near it are chosen again with what follows
            keep = max(1, int(np.searchsorted(borders, len(ids) - 4 * self.cost.window, "right")) - 1)
            borders = borders[: keep + 1]
        end = int(borders[-1])
        begins = np.concatenate([[0], stops[:-1]])
        edges = _distinct(np.concatenate([borders, begins[begins < end]]))
        owner = np.searchsorted(stops, edges[:-1], "right")
        window = np.searchsorted(borders, edges[:-1], "right") - 1
        raw = ids[:end].astype("<u4").tobytes()
        out = []
        for a, b, d, s in zip(edges[:-1].tolist(), edges[1:].tolist(), owner.tolist(), window.tolist(), strict=True):
            doc_id, whole = self.docs[d]
            start = a - int(begins[d]) + (self.done if d == 0 else 0)
            out.append((doc_id, start, b - a, zlib.crc32(raw[4 * a : 4 * b]), len(whole), self.sequence + s, a - int(borders[s])))
        self.sequence += len(borders) - 1
        d = int(np.searchsorted(stops, end, "right"))
        self.done = end - int(begins[d]) + (self.done if d == 0 else 0) if d < len(self.docs) else 0
        self.docs, self.held = self.docs[d:], self.held - end
        return out


def sentence_end_flags(tok) -> np.ndarray:
    """For each id: does its text end a sentence or a line?"""
    from padgrad.llm.tokenizing import byte_chars

    newline = byte_chars()[10]
    flags = np.zeros(tok.get_vocab_size() + 1, bool)
    for token, i in tok.get_vocab().items():
        flags[i] = token[-1] in ".!?" or newline in token
    return flags


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int, cost: PackCost | None = None, block_tokens: int = 1 << 20) -> DataFrame:
    """Pieces of all documents of ``docs`` (``doc_id``, ``text``) in sequences: columns of ``PIECES``."""
    cost = cost or PackCost()

    def pack(batches):
        from pyspark import TaskContext

        from padgrad.llm.tokenizing import encoded_docs, opened
        from padgrad.llm.workers import tidy

        tidy(f"ids {tokenizer}")
        flags = sentence_end_flags(opened(tokenizer, True).tok)
        packer = Packer(flags, cost, TaskContext.get().partitionId() << 36, block_tokens)

        def batch(rows):
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
            return pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in cols], names=[x.split()[0] for x in PIECES.split(", ")])

        for b in batches:
            at = 0
            for ids, sizes in encoded_docs(b.column("text"), tokenizer, True, end_id):
                doc_ids = b.column("doc_id").slice(at, len(sizes)).to_pylist()
                at += len(sizes)
                for doc_id, one in zip(doc_ids, np.split(ids, np.cumsum(sizes)[:-1]), strict=True):
                    if packer.add(doc_id, one):
                        yield batch(packer.flush(False))
        while packer.docs:
            yield batch(packer.flush(True))

    ordered = docs.select("doc_id", "text", F.xxhash64("text").alias("th")).repartitionByRange("doc_id", "th").sortWithinPartitions("doc_id", "th").select("doc_id", "text")  # a frequent id has many ranges
    return ordered.mapInArrow(pack, PIECES)
