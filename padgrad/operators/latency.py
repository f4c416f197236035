"""Latency of devices: computation, setup, links, sharing and epochs.

Draws are keyed hashes of (seed, epoch, device, kind), so tables do not depend on
partitioning and SQL engines can check them. ``np_epoch_times`` draws the same laws in
numpy for long simulations.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from padgrad.functions.keys import uniform
from padgrad.sources.devices import CLASS_RATES, DOWN_RATE, FAILURE, HEADER, SERVER_RATE, UP_RATE

CODED, MINIBATCH, MOMENT = "coded", "minibatch", "moment"
BATCH = 480


def mac_count(scheme: str, d: int, c: int, batch: int = BATCH, alpha: int = 1) -> int:
    """Multiply-accumulates of a device in an epoch (``encode``: once, in the sharing phase)."""
    if scheme in (CODED, MOMENT):
        return d * d * c
    if scheme == MINIBATCH:
        return 2 * batch * d * c
    if scheme == "encode":
        return alpha * (d * d + d * c)
    raise ValueError(scheme)


def message_bits(d: int, c: int, k: int) -> int:
    """A model or gradient of k-bit numbers; conventional schemes send 32-bit ones."""
    return d * c * k


def compute_time(rho: float, tau: Column) -> Column:
    return F.lit(float(rho)) / tau


def setup_time(rho: float, tau: Column, u: Column) -> Column:
    """Exponential with half the deterministic computation as mean: rate 2 tau / rho."""
    return -F.ln(u) / (2 * tau / F.lit(float(rho)))


def transmissions(u: Column, p: Column) -> Column:
    """Geometric number of sends until the first success."""
    return F.greatest(F.lit(1.0), F.ceil(F.ln(u) / F.ln(p)).cast("double"))


def link_time(sends: Column, bits: float, rate: Column) -> Column:
    return sends * F.lit(bits * (1 + HEADER)) / rate


def sample(fleet: DataFrame, epochs: int, rho: float, bits: float, seed: str) -> DataFrame:
    """``(epoch, device, class, comp_s, setup_s, up_s, down_s, total_s)``."""
    base = fleet.withColumn("epoch", F.explode(F.sequence(F.lit(1), F.lit(epochs))))

    def u(kind):
        return uniform(F.lit(seed), F.col("epoch"), F.col("device"), F.lit(kind))

    out = base.select(
        "epoch", "device", "class", compute_time(rho, F.col("tau")).alias("comp_s"), setup_time(rho, F.col("tau"), u("setup")).alias("setup_s"),
        link_time(transmissions(u("up"), F.col("p_fail")), bits, F.col("gamma_u")).alias("up_s"),
        link_time(transmissions(u("down"), F.col("p_fail")), bits, F.col("gamma_d")).alias("down_s"),
    )
    return out.withColumn("total_s", F.col("comp_s") + F.col("setup_s") + F.col("up_s") + F.col("down_s"))


def fastest(latency: DataFrame, keep: int) -> DataFrame:
    """The ``keep`` first devices of every epoch, with ``place`` (1-based; ties by device)."""
    w = Window.partitionBy("epoch").orderBy("total_s", "device")
    return latency.withColumn("place", F.row_number().over(w)).where(F.col("place") <= keep)


def epoch_time(latency: DataFrame, keep: int) -> DataFrame:
    """``(epoch, seconds)``: the ``keep``-th smallest time; the largest for conventional schemes."""
    return fastest(latency, keep).groupBy("epoch").agg(F.max("total_s").alias("seconds"))


def sharing_phase(fleet: DataFrame, alphas: list[int], d: int, c: int, k: int, seed: str, upload: str = "per_peer") -> DataFrame:
    """``(alpha, device, share_s, encode_s)``: sending padded matrices, receiving the peers', and encoding them."""
    one = (d * (d + 1) // 2 + d * c) * k * (1 + HEADER)
    base = fleet.withColumn("alpha", F.explode(F.array(*[F.lit(a) for a in alphas])))
    peers = F.col("alpha") - 1

    def u(kind):
        return uniform(F.lit(seed), F.col("alpha"), F.col("device"), F.lit(kind))

    copies = peers if upload == "per_peer" else F.least(peers, F.lit(1))
    up = copies * transmissions(u("share-up"), F.col("p_fail")) * F.lit(float(one)) / F.col("gamma_u")
    down = peers * transmissions(u("share-down"), F.col("p_fail")) * F.lit(float(one)) / F.col("gamma_d")
    work = F.col("alpha") * F.lit(float(d * d + d * c)) / F.col("tau")
    encode = work - F.ln(u("encode")) * work / 2
    return base.select("alpha", "device", F.greatest(up, down).alias("share_s"), encode.alias("encode_s"))


def parity_upload(rates: np.ndarray, rows: int, d: int, c: int, k: int, seed: int) -> float:
    """When the slowest device has sent its parity rows: every device sends all ``rows`` of d + c numbers, and has combined its examples for them."""
    g = np.random.Generator(np.random.Philox(seed))
    n = len(rates)
    return float((rows * (d + c) * k * (1 + HEADER) / UP_RATE * g.geometric(1 - FAILURE, n)).max())


def parity_server_time(rows: int, d: int, c: int) -> float:
    """The server's gradient on parity rows in an epoch."""
    return 2 * rows * d * c / SERVER_RATE


def server_time(devices: int, alpha: int, d: int, c: int) -> float:
    """Unpadding and decoding at the server's rate."""
    answers = devices - alpha + 1
    return (answers * d * d * c + answers * d * c) / SERVER_RATE


def class_rates(devices: int) -> np.ndarray:
    """Rates of a fleet in the proportions 10 : 5 : 5 : 5, fastest devices first."""
    cut = np.array([0.4, 0.6, 0.8, 1.0]) * devices
    return np.array([CLASS_RATES[int(np.searchsorted(cut, i, "right"))] for i in range(devices)])


def np_epoch_times(rates: np.ndarray, epochs: int, rho: float, bits: float, seed: int) -> np.ndarray:
    """``(epochs, devices)`` total times."""
    g = np.random.Generator(np.random.Philox(seed))
    size = (epochs, len(rates))
    work = rho / rates
    wire = bits * (1 + HEADER)
    links = g.geometric(1 - FAILURE, size) * wire / UP_RATE + g.geometric(1 - FAILURE, size) * wire / DOWN_RATE
    return work + g.exponential(1, size) * work / 2 + links


def np_sharing_time(rates: np.ndarray, alpha: int, d: int, c: int, k: int, seed: int, upload: str = "per_peer") -> float:
    """When the slowest device has shared and encoded."""
    if alpha == 1:
        return 0.0
    g = np.random.Generator(np.random.Philox(seed))
    one = (d * (d + 1) // 2 + d * c) * k * (1 + HEADER)
    copies = alpha - 1 if upload == "per_peer" else 1
    n = len(rates)
    share = np.maximum(copies * one / UP_RATE * g.geometric(1 - FAILURE, n), (alpha - 1) * one / DOWN_RATE * g.geometric(1 - FAILURE, n))
    work = mac_count("encode", d, c, alpha=alpha) / rates
    return float((share + work + g.exponential(1, n) * work / 2).max())


def geometric_mean_sends(p: float) -> float:
    return 1 / (1 - p)


def sends_from_uniform(u: float, p: float) -> int:
    return max(1, math.ceil(math.log(u) / math.log(p)))
