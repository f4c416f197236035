"""Sharing phase and coded answers as tables of residue lanes.

Two layouts. *Rows* are for large models: ``(device, i, bar, own)`` holds row i of a device's second moment
and first gradient, lane after lane in one array; encoding gathers the D rows of one i, so each
share crosses the network once whatever alpha is. *Cells* are long, ``(device, part, i, j, lane, v)`` with
``part`` ``xi`` for second moments (d x d) and ``delta`` for first gradients (d x c): all of it is SQL. Integers of the data are carried modulo
the lane primes, so wrapping never loses anything: pads are removed exactly, whatever
the order of sums. Devices' functions take a device's seed only through its pads;
the server's functions take answers and the master seed, never shares.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from padgrad.functions.fixedpoint import FRACTION, PRIMES, from_two_lanes, np_mod_matmul, quantise
from padgrad.functions.keys import DELTA, XI, device_seed, lane_of_digest, lane_pad, wide_digest


def prime_of(lane: Column, lanes: int) -> Column:
    return F.element_at(F.array(*[F.lit(p) for p in PRIMES[:lanes]]), lane + 1)


def to_lanes(cells: DataFrame, lanes: int) -> DataFrame:
    """``cells`` (``..., v`` BIGINT) with a row for each lane."""
    lane = F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))).alias("lane")
    out = cells.select("*", lane)
    return out.withColumn("v", F.pmod("v", prime_of(F.col("lane"), lanes)))


def pad_shares(cells: DataFrame, seed: str, lanes: int) -> DataFrame:
    """Devices' padded cells; ``part`` chooses the pad set."""
    p = prime_of(F.col("lane"), lanes)
    own = F.col("own_seed")
    pad = F.when(F.col("part") == XI, lane_pad(own, XI, F.col("i"), F.col("j"), F.col("lane"), p)).otherwise(lane_pad(own, DELTA, F.col("i"), F.col("j"), F.col("lane"), p))
    seeded = cells.withColumn("own_seed", device_seed(seed, F.col("device")))
    return to_lanes(seeded, lanes).withColumn("v", F.pmod(F.col("v") + pad, p)).drop("own_seed")


def key_cells(spark: SparkSession, seed: str, devices: int, d: int, c: int, lanes: int) -> DataFrame:
    """The server's pads as cells of the same shape, made from the seed."""
    one = spark.range(devices).select(F.col("id").cast("int").alias("device"))

    def block(part, cols):
        return one.select("device", F.lit(part).alias("part"), F.explode(F.sequence(F.lit(0), F.lit(d - 1))).alias("i")).select("*", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("j"))

    zero = block(XI, d).unionByName(block(DELTA, c)).withColumn("v", F.lit(0).cast("long"))
    return pad_shares(zero, seed, lanes)


def lane_code(spark: SparkSession, codes: list[np.ndarray]) -> DataFrame:
    """``(device, peer, lane, b)``: an encoder for each lane."""
    rows = [(int(i), int(j), lane, int(b[i, j])) for lane, b in enumerate(codes) for i, j in zip(*np.nonzero(b), strict=True)]
    return spark.createDataFrame(rows, "device int, peer int, lane int, b long")


def encode(cells: DataFrame, code: DataFrame, lanes: int) -> DataFrame:
    """What each device combines from its peers' cells: a broadcast join whose fan-out is summed before the shuffle."""
    p = prime_of(F.col("lane"), lanes)
    shares = cells.withColumnRenamed("device", "peer")
    joined = shares.join(F.broadcast(code), ["peer", "lane"])
    return joined.groupBy("device", "part", "i", "j", "lane").agg(F.sum(F.pmod(F.col("b") * F.col("v"), p)).alias("v")).withColumn("v", F.pmod("v", p))


def answers(coded: DataFrame, eps: DataFrame, lanes: int) -> DataFrame:
    """``(device, i, j, lane, v)``: ``C + Cbar eps`` of every device; ``eps``: ``(k, j, e)`` integers, small."""
    p = prime_of(F.col("lane"), lanes)
    bar = coded.where(F.col("part") == XI).withColumnRenamed("j", "k").join(F.broadcast(eps), "k")
    bar = bar.select("device", "i", "j", "lane", F.pmod(F.col("v") * F.pmod(F.col("e"), p), p).alias("v"))
    both = bar.unionByName(coded.where(F.col("part") == DELTA).select("device", "i", "j", "lane", "v"))
    return both.groupBy("device", "i", "j", "lane").agg(F.sum("v").alias("v")).withColumn("v", F.pmod("v", p))


def unpad(answered: DataFrame, key_answers: DataFrame, lanes: int) -> DataFrame:
    """The server subtracts what the pads alone would have answered."""
    p = prime_of(F.col("lane"), lanes)
    keys = key_answers.withColumnRenamed("v", "key")
    return answered.join(keys, ["device", "i", "j", "lane"]).withColumn("v", F.pmod(F.col("v") - F.col("key"), p)).drop("key")


def decode(clear: DataFrame, weights: list[np.ndarray], lanes: int) -> DataFrame:
    """``(i, j, lane, v)``: weighted sum over the devices that answered."""
    spark = clear.sparkSession
    rows = [(i, lane, int(a[i])) for lane, a in enumerate(weights) for i in range(len(a)) if a[i]]
    table = spark.createDataFrame(rows, "device int, lane int, a long")
    p = prime_of(F.col("lane"), lanes)
    joined = clear.join(F.broadcast(table), ["device", "lane"])
    return joined.groupBy("i", "j", "lane").agg(F.sum(F.pmod(F.col("a") * F.col("v"), p)).alias("v")).withColumn("v", F.pmod("v", p))


def signed_two_lanes(decoded: DataFrame) -> DataFrame:
    """``(i, j, v)``: integers from lanes 0 and 1."""
    wide = decoded.groupBy("i", "j").agg(F.max(F.when(F.col("lane") == 0, F.col("v"))).alias("r0"), F.max(F.when(F.col("lane") == 1, F.col("v"))).alias("r1"))
    return wide.select("i", "j", from_two_lanes(F.col("r0"), F.col("r1")).alias("v"))


ROWS = "device int, i int, bar array<long>, own array<long>"


def padded_rows(moments: DataFrame, seed: str, lanes: int = len(PRIMES), f: int = FRACTION, first: bool = True) -> DataFrame:
    """``ROWS`` of each device's padded moment and first gradient (at the zero model), at scales ``2^f`` and ``2^2f``.

    Without ``first`` the moments count as 0: the rows are the pads themselves, as the server makes them.
    """

    def digests(part, cells):
        return F.transform(cells, lambda _, j: wide_digest(F.col("own_seed"), part, F.col("i"), j))

    def lane_of(cells, pads, lane, sign, up):
        p = PRIMES[lane]

        def cell(v, j):
            pad = lane_of_digest(F.get(F.col(pads), j), lane, p)
            if not first:
                return pad
            return F.pmod(F.pmod(quantise(sign * v, 62, f), F.lit(p)) * F.lit(2**up % p) + pad, F.lit(p))

        return F.transform(cells, cell)

    seeded = moments.select("device", "i", "g", "h", device_seed(seed, F.col("device")).alias("own_seed"))
    hashed = seeded.select("device", "i", "g", "h", digests(XI, F.col("g")).alias("xi"), digests(DELTA, F.col("h")).alias("delta"))
    bar = F.concat(*[lane_of(F.col("g"), "xi", lane, 1, 0) for lane in range(lanes)])
    own = F.concat(*[lane_of(F.col("h"), "delta", lane, -1, f) for lane in range(lanes)])
    return hashed.select("device", "i", bar.alias("bar"), own.alias("own"))


def every_row(moments: DataFrame | None, devices: int, d: int, c: int, spark: SparkSession | None = None) -> DataFrame:
    """``moments`` with zeros for the rows of devices that own nothing: they share too, or the pads would not cancel."""
    spark = moments.sparkSession if moments is not None else spark
    grid = spark.range(devices).select(F.col("id").cast("int").alias("device"), F.explode(F.sequence(F.lit(0), F.lit(d - 1))).alias("i")).repartition("i")
    zero = [F.array_repeat(F.lit(0.0), n) for n in (d, c)]
    if moments is None:
        return grid.select("device", "i", zero[0].alias("g"), zero[1].alias("h"))
    return grid.join(moments, ["device", "i"], "left").select("device", "i", F.coalesce("g", zero[0]).alias("g"), F.coalesce("h", zero[1]).alias("h"))


def key_rows(spark: SparkSession, seed: str, devices: int, d: int, c: int, lanes: int = len(PRIMES)) -> DataFrame:
    """The server's pads in ``ROWS``."""
    return padded_rows(every_row(None, devices, d, c, spark), seed, lanes, first=False)


def _lists(rows: np.ndarray) -> pa.Array:
    n, w = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * w + 1, w), pa.int32()), pa.array(rows.ravel()))


def encode_rows(shares: DataFrame, codes: list[np.ndarray]) -> DataFrame:
    """``ROWS`` of what each device combines; ``codes`` has an encoder for each lane (D x D residues)."""
    shared = shares.sparkSession.sparkContext.broadcast([np.asarray(b, np.int64) for b in codes])
    devices, lanes = len(codes[0]), len(codes)

    def combine(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {"bar": [None] * devices, "own": [None] * devices}  # D rows
        for b in batches:
            for k, dev in enumerate(b.column("device").to_pylist()):
                for name, rows in held.items():
                    rows[dev] = b.column(name)[k].values.to_numpy()
        out = []
        for rows in held.values():
            width = next(len(r) for r in rows if r is not None) // lanes
            cells = np.stack([np.zeros(width * lanes, np.int64) if r is None else r for r in rows]).reshape(devices, lanes, width)
            out.append(np.stack([np_mod_matmul(code % p, cells[:, lane], p) for lane, (code, p) in enumerate(zip(shared.value, PRIMES, strict=False))], axis=1).reshape(devices, -1))
        yield pa.RecordBatch.from_arrays([pa.array(range(devices), pa.int32()), pa.array([key[0].as_py()] * devices, pa.int32()), *map(_lists, out)], names=["device", "i", "bar", "own"])

    return shares.groupBy("i").applyInArrow(combine, ROWS)


def row_answers(coded: DataFrame, eps: np.ndarray) -> DataFrame:
    """``(device, i, v)``: row i of ``C + Cbar eps``, lane after lane. ``eps`` (lanes, d, c) is broadcast: it is what the server sends."""
    shared = coded.sparkSession.sparkContext.broadcast(eps)
    lanes, d, c = eps.shape

    def answer(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                bar, own = (part.column(n).flatten().to_numpy().reshape(part.num_rows, lanes, -1) for n in ("bar", "own"))
                out = np.stack([(own[:, lane] + np_mod_matmul(bar[:, lane], shared.value[lane], PRIMES[lane])) % PRIMES[lane] for lane in range(lanes)], axis=1)
                yield pa.RecordBatch.from_arrays([part.column("device"), part.column("i"), _lists(out.reshape(part.num_rows, -1))], names=["device", "i", "v"])

    return coded.select("device", "i", "bar", "own").mapInArrow(answer, "device int, i int, v array<long>")


def share_bits(alpha: int, d: int, c: int, k: int) -> int:
    """Bits that a device sends in the sharing phase if each peer gets its own copy: symmetric second moment and gradient."""
    return (alpha - 1) * (d * (d + 1) // 2 + d * c) * k
