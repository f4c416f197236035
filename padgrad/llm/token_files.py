"""Token-id files of patched frame-of-reference blocks, their writer and reader.

File format ``PFB1`` (little-endian). Magic; then blocks; then the document table;
then the footer. A block holds up to ``BLOCK`` ids: ``min u32, count u16, width u8,
exceptions u16``; ``count`` values ``(id - min)`` cut to ``width`` bits, packed low bit
first; then the exceptions: position u16 each, and high bits u32 each. The width is
the least one that holds ``PERCENTILE`` percent of the block's values; values that
need more are the exceptions. The document table is doc_id i64 and ids u32 for each
document; a null id is NO_ID. The footer is the start of every block u64, then
``blocks u64, documents u64, ids u64, start of the table u64``.

Spark: documents are range-partitioned by id, so file k holds a contiguous range and
files in order hold all ids in ascending order. A task writes under a name of its own
attempt and renames at its end, so retried or speculative tasks leave one whole file.
Files go to the folder all executors share, by ``pyarrow.fs`` (file, hdfs, s3, gs).
Only the manifest (a row for each file) comes to the driver.

Defined cases: null or empty text is the end id alone; repeated ids keep a row each, in order of
their texts' hashes; a very long text is encoded whole and leaves in blocks; extra columns are ignored; an empty
table writes no file.
"""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from padgrad.llm.textcols import NO_ID

MAGIC, BLOCK, PERCENTILE = b"PFB1", 1024, 98
_HEAD, _FOOT = struct.Struct("<IHBH"), struct.Struct("<QQQQ")
MANIFEST = "part int, path string, docs long, ids long, bytes long"
DOC_ROWS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def _bit_width(v: np.ndarray) -> np.ndarray:
    """Bits that each value needs."""
    return np.where(v > 0, np.floor(np.log2(np.maximum(v, 1).astype(np.float64))) + 1, 0).astype(np.int64)


def encode_blocks(ids: np.ndarray) -> list[bytes]:
    """``ids`` (uint32) as blocks; all blocks but the last are full."""
    out: list[bytes] = []
    whole = len(ids) // BLOCK
    groups = [ids[: whole * BLOCK].reshape(whole, BLOCK)] if whole else []
    if len(ids) % BLOCK:
        groups.append(ids[whole * BLOCK :].reshape(1, -1))
    for rows in groups:
        n = rows.shape[1]
        low = rows.min(axis=1)
        v = (rows - low[:, None]).astype("<u4")
        rank = min(n - 1, -(-n * PERCENTILE // 100) - 1)
        width = _bit_width(np.partition(v, rank, axis=1)[:, rank])
        made: list[bytes] = [b""] * len(rows)
        for w in np.unique(width).tolist():
            where = np.flatnonzero(width == w)
            part = v[where]
            bits = np.unpackbits(part.view(np.uint8).reshape(len(where), n, 4), axis=2, bitorder="little")[:, :, :w]
            packed = np.packbits(bits.reshape(len(where), n * w), axis=1, bitorder="little")
            high = (part.astype(np.uint64) >> np.uint64(w)).astype("<u4")
            for k, b in enumerate(where.tolist()):
                at = np.flatnonzero(high[k])
                made[b] = _HEAD.pack(int(low[b]), n, w, len(at)) + packed[k].tobytes() + at.astype("<u2").tobytes() + high[k][at].tobytes()
        out += made
    return out


def decode_blocks(data: memoryview, starts: list[int]) -> np.ndarray:
    """The ids of the blocks that begin at ``starts`` of ``data``."""
    parts = []
    for at in starts:
        low, n, w, k = _HEAD.unpack_from(data, at)
        at += _HEAD.size
        size = -(-n * w // 8)
        v = np.zeros((n, 4), np.uint8)
        if w:
            bits = np.zeros((n, 32), np.uint8)
            bits[:, :w] = np.unpackbits(np.frombuffer(data, np.uint8, size, at), count=n * w, bitorder="little").reshape(n, w)
            v = np.packbits(bits, axis=1, bitorder="little")
        v = v.view("<u4")[:, 0].astype(np.uint64)
        at += size
        if k:
            where = np.frombuffer(data, "<u2", k, at)
            v[where] |= np.frombuffer(data, "<u4", k, at + 2 * k).astype(np.uint64) << np.uint64(w)
        parts.append((v + low).astype(np.uint32))
    return np.concatenate(parts) if parts else np.zeros(0, np.uint32)


class FileWriter:
    """Writes one file; ids are held for ``hold`` ids at most."""

    def __init__(self, sink, hold: int = 256 * BLOCK):
        self.sink, self.hold = sink, hold
        self.parts: list[np.ndarray] = []
        self.held, self.at, self.ids = 0, len(MAGIC), 0
        self.starts: list[int] = []
        self.docs: list[np.ndarray] = []
        self.sizes: list[np.ndarray] = []
        sink.write(MAGIC)

    def add(self, doc_ids: np.ndarray, sizes: np.ndarray, ids: np.ndarray) -> None:
        self.docs.append(doc_ids.astype("<i8"))
        self.sizes.append(sizes.astype("<u4"))
        self.parts.append(ids)
        self.held += len(ids)
        if self.held >= self.hold:
            self._put(self.held // BLOCK * BLOCK)

    def _put(self, n: int) -> None:
        ids = np.concatenate(self.parts) if self.parts else np.zeros(0, np.uint32)
        for block in encode_blocks(ids[:n]):
            self.starts.append(self.at)
            self.sink.write(block)
            self.at += len(block)
        self.ids += n
        self.parts, self.held = [ids[n:]], len(ids) - n

    def close(self) -> tuple[int, int, int]:
        """Documents, ids and bytes written."""
        self._put(self.held)
        docs = np.concatenate(self.docs) if self.docs else np.zeros(0, "<i8")
        sizes = np.concatenate(self.sizes) if self.sizes else np.zeros(0, "<u4")
        table = self.at
        tail = docs.tobytes() + sizes.tobytes() + np.array(self.starts, "<u8").tobytes() + _FOOT.pack(len(self.starts), len(docs), self.ids, table)
        self.sink.write(tail)
        return len(docs), self.ids, table + len(tail)


def read_file(data: bytes, step: int = 256):
    """Yields ``(doc_ids, sizes, ids)`` for runs of documents; ``step`` blocks are decoded at a time."""
    if data[:4] != MAGIC:
        raise ValueError("not a token file")
    n_blocks, n_docs, n_ids, table = _FOOT.unpack_from(data, len(data) - _FOOT.size)
    docs = np.frombuffer(data, "<i8", n_docs, table)
    sizes = np.frombuffer(data, "<u4", n_docs, table + 8 * n_docs).astype(np.int64)
    starts = np.frombuffer(data, "<u8", n_blocks, table + 12 * n_docs).tolist()
    view, stops = memoryview(data), np.cumsum(sizes)
    if n_docs and stops[-1] != n_ids:
        raise ValueError("document table and blocks disagree")
    rest, done, base = np.zeros(0, np.uint32), 0, 0  # ids not given yet, documents given, ids given
    for k in range(0, n_blocks, step):
        rest = np.concatenate([rest, decode_blocks(view, starts[k : k + step])])
        upto = int(np.searchsorted(stops, base + len(rest), "right"))
        if upto > done:
            n = int(stops[upto - 1]) - base
            yield docs[done:upto], sizes[done:upto], rest[:n]
            rest, base, done = rest[n:], base + n, upto


def _store(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_token_files(docs: DataFrame, folder: str, tokenizer: str, end_id: int, space_joins: bool) -> list[dict]:
    """Writes all documents; the manifest in file order, with ``base`` (ids in earlier files) added."""

    def write(batches):
        from pyspark import TaskContext

        from padgrad.llm.tokenizing import encoded_docs
        from padgrad.llm.workers import tidy

        tidy(f"ids {tokenizer}")
        part = TaskContext.get().partitionId()
        store, root = _store(folder)
        store.create_dir(root, recursive=True)
        name, attempt = f"{root}/ids-{part:06d}.pfb", f"{root}/.{part:06d}-{uuid.uuid4().hex}"
        writer = sink = None
        for b in batches:
            at = 0
            for ids, sizes in encoded_docs(b.column("text"), tokenizer, space_joins, end_id):
                if writer is None:
                    sink = store.open_output_stream(attempt)
                    writer = FileWriter(sink)
                doc_ids = b.column("doc_id").slice(at, len(sizes)).cast(pa.int64()).fill_null(NO_ID).to_numpy(zero_copy_only=False)
                at += len(sizes)
                writer.add(doc_ids, sizes, ids)
        if writer is not None:
            n_docs, n_ids, size = writer.close()
            sink.close()
            store.move(attempt, name)
            yield pa.RecordBatch.from_pylist([{"part": part, "path": name, "docs": n_docs, "ids": n_ids, "bytes": size}], schema=_schema(MANIFEST))

    ordered = docs.select("doc_id", "text", F.xxhash64("text").alias("th")).repartitionByRange("doc_id", "th").sortWithinPartitions("doc_id", "th").select("doc_id", "text")  # a frequent id has many ranges
    files = sorted((r.asDict() for r in ordered.mapInArrow(write, MANIFEST).collect()), key=lambda r: r["part"])
    base = 0
    for r in files:
        r["base"] = base
        base += r["ids"]
    return files


def _schema(ddl: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}
    return pa.schema([(x.split()[0], kinds[x.split()[1]]) for x in ddl.split(", ")])


def read_token_files(spark: SparkSession, folder: str, files: list[dict]) -> DataFrame:
    """``DOC_ROWS`` read back from the files: a document's ids are in ``[start, start + n_tokens)`` of all ids."""

    def read(batches):
        store, _ = _store(folder)
        for b in batches:
            for path, base in zip(b.column("path").to_pylist(), b.column("base").to_pylist(), strict=True):
                with store.open_input_file(path) as f:
                    data = f.read()
                for docs, sizes, ids in read_file(data):
                    raw, ends = ids.astype("<u4").tobytes(), np.cumsum(sizes)
                    begins = ends - sizes
                    crc = [zlib.crc32(raw[4 * a : 4 * z]) for a, z in zip(begins.tolist(), ends.tolist(), strict=True)]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(docs, pa.int64(), mask=docs == NO_ID), pa.array(begins + base), pa.array(sizes), pa.array(crc, pa.int64())], schema=_schema(DOC_ROWS)
                    )
                    base += len(ids)

    rows = [(r["path"], r["base"]) for r in files]
    listed = spark.createDataFrame(rows, "path string, base long").repartition(max(1, len(rows)))
    return listed.mapInArrow(read, DOC_ROWS)
