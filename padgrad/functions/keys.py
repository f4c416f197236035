"""One-time pads and seeded draws as deterministic column expressions.

Pads are never stored: a cell is a keyed hash of (seed, device, kind, i, j), so a
retried task makes the same cell, and the seed is all that is sent. A pad protects
one matrix once; a second data set needs a new seed.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from padgrad.functions.fixedpoint import K, fx_add, np_wrap, wrap

XI, DELTA = "xi", "delta"


def prf60(*parts: Column) -> Column:
    """60 uniform bits from SHA-256 of the parts."""
    digest = F.sha2(F.concat_ws(":", *[p.cast("string") for p in parts]), 256)
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("long")


def np_prf60(*parts) -> int:
    return int(hashlib.sha256(":".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def device_seed(master: str, device: Column) -> Column:
    """The seed that goes to a device in place of its pads."""
    return F.sha2(F.concat_ws(":", F.lit(master), F.lit("device"), device.cast("string")), 256)


def pad_cell(seed: str, device: Column, kind: str, i: Column, j: Column, k: int = K) -> Column:
    """A cell of a pad, uniform over the k-bit set. Pads of second moments are symmetric."""
    a, b = (F.least(i, j), F.greatest(i, j)) if kind == XI else (i, j)
    return wrap(F.pmod(prf60(F.lit(seed), device, F.lit(kind), a, b), F.lit(2**k)), k)


def np_pad(seed: str, device: int, kind: str, rows: int, cols: int, k: int = K) -> np.ndarray:
    out = np.empty((rows, cols), np.int64)
    for i in range(rows):
        for j in range(cols):
            a, b = (min(i, j), max(i, j)) if kind == XI else (i, j)
            out[i, j] = np_prf60(seed, device, kind, a, b) & ((1 << k) - 1)
    return np_wrap(out, k)


def np_fast_pad(seed: int, device: int, kind: str, rows: int, cols: int, bits: int) -> np.ndarray:
    """Pad from a counter-based generator, for large matrices in simulations."""
    g = np.random.Generator(np.random.Philox(key=[seed, 2 * device + (kind == XI)]))
    x = g.integers(0, 1 << bits, (rows, cols), dtype=np.int64)
    return np.triu(x) + np.triu(x, 1).T if kind == XI else x


def lane_pad(own_seed: Column, kind: str, i: Column, j: Column, lane: Column, prime: Column) -> Column:
    """A pad cell modulo a lane's prime (bias below 2^-28) from the device's own seed (``device_seed``): no device can make another's pads."""
    a, b = (F.least(i, j), F.greatest(i, j)) if kind == XI else (i, j)
    return F.pmod(prf60(own_seed, F.lit(kind), a, b, lane), prime)


def wide_digest(own_seed: Column, kind: str, i: Column, j: Column) -> Column:
    """512 bits for a cell, enough for all lanes at once (``lane_of_digest``)."""
    a, b = (F.least(i, j), F.greatest(i, j)) if kind == XI else (i, j)
    return F.sha2(F.concat_ws(":", own_seed, F.lit(kind), a.cast("string"), b.cast("string")), 512)


def lane_of_digest(digest: Column, lane: int, prime: int) -> Column:
    """The pad of a lane: its own 60 bits of the digest modulo the prime."""
    return F.pmod(F.conv(F.substring(digest, 15 * lane + 1, 15), 16, 10).cast("long"), F.lit(prime))


def apply_pad(secret: Column, pad: Column, k: int = K) -> Column:
    return fx_add(secret, pad, k)


def retrieve(scaled_share: Column, scaled_pad: Column, k: int = K) -> Column:
    """Public multiple of the secret from those of share and pad; off by 2^-f at most unless the share wrapped."""
    return wrap(scaled_share - scaled_pad, k)


def uniform(*parts: Column) -> Column:
    """A draw in (0, 1)."""
    return (prf60(*parts).cast("double") + 0.5) / float(2**60)


def lehmer(state: Column) -> Column:
    """Fast generator for tests only."""
    return F.pmod(F.lit(48271).cast("long") * state, F.lit(2147483647))


def uniformity(shares, column: str = "share", k: int = K, buckets: int = 64):
    """Bucket counts of shares over their whole range, for a chi-square test against the uniform law."""
    width = 2**k // buckets
    b = F.floor((F.col(column) + F.lit(2 ** (k - 1))) / F.lit(width)).cast("int")
    return shares.groupBy(b.alias("bucket")).agg(F.count("*").alias("n"))
