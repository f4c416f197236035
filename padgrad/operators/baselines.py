"""Baselines: what coded descent is compared with.

All work on moments of devices (or of (device, batch) pairs), made in one Spark pass, and
on ``times`` (epochs x D). Results are ``TrainResult`` with a trace of elapsed seconds.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from padgrad.functions.keys import uniform
from padgrad.operators.moments import HELD, _blocks, _part, added_parts, collect_moments, max_eigen, mirrored
from padgrad.operators.training import TrainResult, schedule, step, train_coded


def _run(theta, epochs, gradient, seconds, lam, mu, evaluate, every, offset=0.0) -> TrainResult:
    elapsed, trace = offset, []
    for e in range(1, epochs + 1):
        theta = step(theta, gradient(e, theta) + lam * theta, mu(e))
        elapsed += seconds(e)
        if evaluate and (e % every == 0 or e == 1):
            trace.append({"epoch": e, "elapsed_s": elapsed, **evaluate(theta)})
    return TrainResult(theta, trace, {"elapsed_s": elapsed})


def train_central(g, h, m, epochs, lam=9e-6, mu=None, evaluate=None, every=1) -> TrainResult:
    """Gradient descent on all rows at one place."""
    gs, hs = g.sum(axis=0), h.sum(axis=0)
    return _run(np.zeros(hs.shape), epochs, lambda e, t: (gs @ t - hs) / m, lambda e: 0.0, lam, mu or schedule(), evaluate, every)


def train_conventional(g, h, counts, times, lam=9e-6, mu=None, batches=1, dtype="float64", evaluate=None, every=1) -> TrainResult:
    """Waits for every device. With ``batches`` > 1, entry ``b`` of axis 1 of ``g``, ``h``, ``counts`` is a mini-batch and epochs take them in turn."""
    if batches == 1:
        g, h, counts = g[:, None], h[:, None], np.asarray(counts)[:, None]
    sums = [(g[:, b].astype(dtype), h[:, b].astype(dtype), float(np.asarray(counts)[:, b].sum())) for b in range(batches)]

    def gradient(e, theta):
        gb, hb, n = sums[(e - 1) % batches]
        parts = gb @ theta.astype(dtype) - hb
        return parts.sum(axis=0, dtype=dtype).astype(float) / max(n, 1.0)

    return _run(np.zeros(h.shape[2:]), len(times), gradient, lambda e: float(times[e - 1].max()), lam, mu or schedule(), evaluate, every)


def train_drop_slowest(g, h, counts, times, keep, lam=9e-6, mu=None, evaluate=None, every=1) -> TrainResult:
    """Only the ``keep`` fastest devices count in an epoch, weighted by their rows. Biased if rows are not alike."""
    counts = np.asarray(counts, float)

    def gradient(e, theta):
        rows = np.argsort(times[e - 1], kind="stable")[:keep]
        return (g[rows] @ theta - h[rows]).sum(axis=0) / max(counts[rows].sum(), 1.0)

    return _run(np.zeros(h.shape[1:]), len(times), gradient, lambda e: float(np.sort(times[e - 1])[keep - 1]), lam, mu or schedule(), evaluate, every)


def train_fedavg(g, h, counts, times, keep, local_steps=5, lam=9e-6, mu=None, evaluate=None, every=1) -> TrainResult:
    """Devices take ``local_steps`` of their own; models of the ``keep`` fastest are averaged by rows.

    A device's step is at most what its own curvature bears, else local steps diverge.
    """
    mu, counts = mu or schedule(), np.asarray(counts, float)
    most = [1.9 / max(max_eigen(gi[None], max(n, 1.0)), 1e-12) for gi, n in zip(g, counts, strict=True)]
    theta, elapsed, trace = np.zeros(h.shape[1:]), 0.0, []
    for e in range(1, len(times) + 1):
        rows = [i for i in np.argsort(times[e - 1], kind="stable")[:keep] if counts[i] > 0]
        models = []
        for i in rows:
            t = theta
            for _ in range(local_steps):
                t = step(t, (g[i] @ t - h[i]) / counts[i] + lam * t, min(mu(e), most[i]))
            models.append(t)
        theta = np.average(models, axis=0, weights=counts[rows]) if models else theta
        elapsed += float(np.sort(times[e - 1])[keep - 1])
        if evaluate and (e % every == 0 or e == 1):
            trace.append({"epoch": e, "elapsed_s": elapsed, **evaluate(theta)})
    return TrainResult(theta, trace, {"elapsed_s": elapsed})


#: Examples that are combined with each other.
PARITY_BLOCK = 1024


def parity_moments(examples: DataFrame, d: int, c: int, delta: float, miss: np.ndarray, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """``Xp'Xp`` and ``Xp'Yp`` of random normal combinations of weighted examples, scaled to their expectation ``sum miss x'[x, y]``.

    Example of device i weighs ``sqrt(miss[i])``. Each run of ``PARITY_BLOCK`` rows of a partition gives
    ``delta`` times as many parity rows, so there are ``delta m`` in all (the leakage) while draws grow as m. Draws are keyed by the
    run's first id. Only products of parity rows, d x (d + c) numbers a task, leave a task and they are
    added block by block, so neither parity rows nor their sum over the data ever come together.
    """
    spread = np.sqrt(np.asarray(miss, float))
    size = max(8, min(PARITY_BLOCK, HELD // (d + c)))

    def combine(batches):
        total, held, left = np.zeros((d, d + c)), [], 0

        def fold(ids, xy):
            rows = max(1, round(delta * len(ids)))
            w = np.random.Generator(np.random.Philox(key=[seed, int(ids[0]) % 2**63])).standard_normal((rows, len(ids)))
            p = w @ xy
            return p[:, :d].T @ p / rows

        for b in batches:
            for at in range(0, b.num_rows, size):
                part = b.slice(at, size)
                ids = part.column("row_id").fill_null(0).to_numpy()
                dev = part.column("device").to_numpy()
                xy = np.hstack([np.asarray(part.column("x").flatten(), float).reshape(-1, d), np.asarray(part.column("y").flatten(), float).reshape(-1, c)])
                held.append((ids, xy * spread[dev][:, None]))
                left += len(ids)
                if left >= size:
                    ids, xy = (np.concatenate(v) for v in zip(*held, strict=True))
                    total += fold(ids[:size], xy[:size])
                    held, left = [(ids[size:], xy[size:])], left - size
        if left:
            total += fold(*(np.concatenate(v) for v in zip(*held, strict=True)))
        yield from (_part(0, k, t) for k, t in _blocks(total, True))

    parts = examples.select("row_id", "device", "x", "y").mapInArrow(combine, "device int, block int, t array<double>")
    g, h = collect_moments(mirrored(added_parts(parts), d, c), 1, d, c)
    return g[0], h[0]


def parity_cells(examples: DataFrame, rows: int, miss: Column, seed: str = "parity") -> DataFrame:
    """``(row, j, v)``: ``rows`` parity rows over all examples with keyed draws, for small tables and SQL engines (draws: rows times m)."""
    u1, u2 = (uniform(F.lit(seed), F.lit(t), F.col("row_id"), F.col("row")) for t in "ab")
    drawn = examples.select("row_id", "x", F.sqrt(miss).alias("s"), F.explode(F.sequence(F.lit(0), F.lit(rows - 1))).alias("row"))
    drawn = drawn.withColumn("w", F.col("s") * F.sqrt(-2 * F.ln(u1)) * F.cos(2 * np.pi * u2)).select("row", "w", F.posexplode("x").alias("j", "a"))
    return drawn.groupBy("row", "j").agg(F.sum(F.col("w") * F.col("a")).alias("v"))


def deadline(times: np.ndarray, delta: float) -> tuple[float, np.ndarray]:
    """A deadline that a share ``1 - delta`` of all answers meets, and each device's chance to miss it."""
    t = float(np.quantile(times, max(0.0, 1 - delta)))
    return t, (times > t).mean(axis=0)


def train_parity(g, h, m, times, parity, limit, lam=9e-6, mu=None, evaluate=None, every=1, offset=0.0, server_s=0.0) -> TrainResult:
    """Parity at the server: devices that meet the deadline count themselves, parity stands for the expected rest.

    ``offset`` is the upload of parity rows before the first epoch, ``server_s`` the server's work on them in each; it
    runs beside the devices', so an epoch lasts as long as the longer of both.
    """
    pg, ph = parity

    def gradient(e, theta):
        rows = times[e - 1] <= limit
        return ((g[rows] @ theta - h[rows]).sum(axis=0) + pg @ theta - ph) / m

    return _run(np.zeros(h.shape[1:]), len(times), gradient, lambda e: max(float(limit), server_s), lam, mu or schedule(), evaluate, every, offset)


def parity_leakage(delta: float, m: int) -> float:
    """Parity rows over all raw rows."""
    return math.ceil(delta * m) / m


def train_stale(g, h, m, times, max_lag=5, keep=None, lam=9e-6, mu=None, evaluate=None, every=1) -> TrainResult:
    """Late devices add the gradient they made at an older model, up to ``max_lag`` epochs old."""
    devices = len(g)
    keep = keep or max(1, devices // 2)
    theta, elapsed, trace, mu = np.zeros(h.shape[1:]), 0.0, [], mu or schedule()
    held = [g[i] @ theta - h[i] for i in range(devices)]
    age = np.zeros(devices, int)
    for e in range(1, len(times) + 1):
        order = np.argsort(times[e - 1], kind="stable")
        rows = set(order[:keep].tolist()) | set(np.flatnonzero(age >= max_lag).tolist())
        elapsed += float(times[e - 1][sorted(rows)].max())
        for i in range(devices):
            age[i] = 0 if i in rows else age[i] + 1
            if i in rows:
                held[i] = g[i] @ theta - h[i]
        theta = step(theta, sum(held) / m + lam * theta, mu(e))
        if evaluate and (e % every == 0 or e == 1):
            trace.append({"epoch": e, "elapsed_s": elapsed, **evaluate(theta)})
    return TrainResult(theta, trace, {"elapsed_s": elapsed})


def train_uncoded(g, h, m, times, **options) -> TrainResult:
    """alpha = 1: the identity code, every device is waited for."""
    return train_coded(g, h, m, 1, times, **options)


def train_replicated(g, h, m, times, **options) -> TrainResult:
    """alpha = D: every device holds everything, the first answer is enough."""
    return train_coded(g, h, m, len(g), times, **options)
