"""Coded gradient descent.

The server is the driver: it holds the model (d x c) and emits the change ``eps`` from the
first model. Devices answer ``C + Cbar eps``; the first D - alpha + 1 answers are unpadded and
decoded to the sum of all gradients. Modes of arithmetic:

* ``literal``: k-bit fixed point, each product floored, sums wrapped. A share that
  wrapped gives a wrong answer unless its multiplier is an integer; wraps are counted.
* ``lifted``: integers are carried modulo five 31-bit primes and never floored; the
  scale goes after the pads. Exact answers, real decode weights.
* ``field``: the code too lives in the prime fields, so the decoded sum is exact.
* ``clear``: doubles without pads (isolates what padding costs).

``engine="local"`` runs epochs in numpy on the collected moments (D d (d + c) numbers, which
do not grow with the data). ``engine="spark"`` keeps coded tables partitioned by
device and reads only those of the devices that answered.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from padgrad.functions.fixedpoint import FRACTION, K, PRIMES, np_lane_matmul, np_lanes, np_lanes_to_float, np_matmul, np_mod_matmul, np_mul, np_quantise, np_wrap
from padgrad.functions.keys import DELTA, XI, np_fast_pad
from padgrad.operators import sharing
from padgrad.operators.gradcode import Undecodable, build_encoder, decode_vector, field_decode_vector, field_encoder, quantise_code
from padgrad.shared import drop_path, fresh_path

MODES = ("clear", "literal", "lifted", "field")


@dataclass
class TrainResult:
    theta: np.ndarray
    trace: list[dict] = field(default_factory=list)
    notes: dict = field(default_factory=dict)


def schedule(mu0: float = 6.0, drops: dict[int, float] | None = None):
    """Step size by epoch (1-based): multiplied at each epoch of ``drops``."""
    drops = {200: 0.8, 350: 0.8} if drops is None else drops

    def mu(epoch: int) -> float:
        out = mu0
        for at, factor in drops.items():
            out *= factor if epoch >= at else 1.0
        return out

    return mu


def step(theta: np.ndarray, gradient: np.ndarray, mu: float) -> np.ndarray:
    return theta - mu * gradient


class CodedDevices:
    """Sharing phase and answers in numpy, for one mode of arithmetic."""

    def __init__(self, g: np.ndarray, first: np.ndarray, alpha: int, mode: str = "lifted", seed: int = 1, k: int = K, f: int = FRACTION, kind: str = "nullspace"):
        if mode not in MODES:
            raise ValueError(f"mode must be one of {MODES}")
        self.D, self.d, self.c, self.alpha, self.mode, self.k, self.f = len(g), g.shape[1], first.shape[2], alpha, mode, k, f
        self.wraps = self.coded_wraps = 0
        self._weights: dict[frozenset, object] = {}
        if mode == "field":
            self.codes = [field_encoder(self.D, alpha, p, seed) for p in PRIMES]
        else:
            b = build_encoder(self.D, alpha, seed, kind)
            self.mantissa, self.b = (None, b) if mode == "clear" else quantise_code(b, k, f)
        getattr(self, f"_share_{mode}")(g, first, seed)

    def _pads(self, seed: int, bits: int):
        xi = [np_fast_pad(seed, i, XI, self.d, self.d, bits) for i in range(self.D)]
        delta = [np_fast_pad(seed, i, DELTA, self.d, self.c, bits) for i in range(self.D)]
        return np.stack(xi), np.stack(delta)

    def _share_clear(self, g, first, seed):
        self.bar = np.tensordot(self.b, g, 1)
        self.own = np.tensordot(self.b, first, 1)

    def _share_literal(self, g, first, seed):
        xi, delta = (np_wrap(x, self.k) for x in self._pads(seed, self.k))
        x, y = np_quantise(g, self.k, self.f), np_quantise(first, self.k, self.f)
        phi, psi = np_wrap(x + xi, self.k), np_wrap(y + delta, self.k)
        self.wraps = int((phi != x + xi).sum() + (psi != y + delta).sum())
        self.bar, self.own = self._combine(phi), self._combine(psi)
        self.key_bar, self.key_own = self._combine(xi), self._combine(delta)
        # a coded moment and its coded pad that wrapped apart: the product with the model then differs by a multiple that is no multiple of 2^k
        apart = self.bar - self.key_bar
        self.coded_wraps = int((apart != np_wrap(apart, self.k)).sum())

    def _combine(self, parts):
        out = np.zeros((self.D, *parts.shape[1:]), np.int64)
        for i in range(self.D):
            for j in np.flatnonzero(self.mantissa[i]):
                out[i] = np_wrap(out[i] + np_mul(np.full(parts.shape[1:], self.mantissa[i, j]), parts[j], self.k, self.f), self.k)
        return out

    def _share_lanes(self, g, first, seed, codes):
        """Shares, coded pairs and coded pads lane by lane; gradients enter at twice the scale, as products will have."""
        x = np_lanes(np_quantise(g, 62, self.f))
        y = np_lanes(np_quantise(first, 62, self.f).astype(object) << self.f)
        self.bar, self.own, self.key_bar, self.key_own = [], [], [], []
        for lane, p in enumerate(PRIMES):
            xi, delta = (v % p for v in self._pads(seed + 7919 * lane, 62))
            code = (codes[lane] % p)[None]

            def sums(t, code=code, p=p):
                return np_lane_matmul(code, (t % p).reshape(1, self.D, -1), (p,))[0].reshape(t.shape)

            self.bar.append(sums(x[lane] + xi).astype(float))  # residues below 2^31, ready to be multiplied
            self.own.append(sums(y[lane] + delta))
            self.key_bar.append(sums(xi).astype(float))
            self.key_own.append(sums(delta))

    def _share_lifted(self, g, first, seed):
        self._share_lanes(g, first, seed, [self.mantissa] * len(PRIMES))

    def _share_field(self, g, first, seed):
        self._share_lanes(g, first, seed, self.codes)

    def _lane_parts(self, rows: list[int], eps: np.ndarray) -> np.ndarray:
        """Answers of ``rows`` without their pads: (lanes, rows, d, c). Answers and pads are multiplied apart, as devices and server do."""
        e, out = np_lanes(eps), []
        for lane, p in enumerate(PRIMES):
            flat = [np_mod_matmul(m[lane][rows].reshape(-1, self.d), e[lane], p).reshape(-1, self.d, self.c) for m in (self.bar, self.key_bar)]
            out.append((self.own[lane][rows] + flat[0] - self.key_own[lane][rows] - flat[1]) % p)
        return np.stack(out)

    def gradient_sum(self, change: np.ndarray, arrived) -> np.ndarray:
        """Sum of all device gradients at first model + ``change`` from the answers of ``arrived``."""
        rows = sorted(int(i) for i in arrived)
        if len(rows) < self.D - self.alpha + 1:
            raise Undecodable(f"{len(rows)} answers; {self.D - self.alpha + 1} are needed")
        key = frozenset(rows)
        if key not in self._weights:
            self._weights[key] = [field_decode_vector(b, rows, p) for b, p in zip(self.codes, PRIMES, strict=True)] if self.mode == "field" else decode_vector(self.b, rows, 1e-6 if self.mode == "clear" else 1e-2)
        a = self._weights[key]
        if self.mode == "clear":
            return sum(a[i] * (self.own[i] + self.bar[i] @ change) for i in rows)
        eps = np_quantise(change, self.k, self.f)
        if self.mode == "literal":
            total = np.zeros((self.d, self.c))
            for i in rows:
                answer = np_wrap(self.own[i] + np_matmul(self.bar[i], eps, self.k, self.f), self.k)
                pad = np_wrap(self.key_own[i] + np_matmul(self.key_bar[i], eps, self.k, self.f), self.k)
                total += a[i] * np_wrap(answer - pad, self.k) / 2.0**self.f
            return total
        parts = self._lane_parts(rows, eps)
        if self.mode == "lifted":
            return np.tensordot(a[rows], np_lanes_to_float(parts) / 2.0 ** (3 * self.f), 1)
        total = np.stack([(a[lane][rows][:, None, None] * parts[lane] % p).sum(axis=0) % p for lane, p in enumerate(PRIMES)])
        return np_lanes_to_float(total) / 2.0 ** (2 * self.f)


def quantised_model(change: np.ndarray, f: int = FRACTION) -> np.ndarray:
    """The change as it is sent: rounded to f fraction bits."""
    return np_quantise(change, 62, f) / 2.0**f


def train_coded(g, h, m, alpha, times, lam=9e-6, mu=None, epochs=None, mode="lifted", seed=1, evaluate=None, every=1, offset=0.0, server_s=0.0, tol=0.0, local_steps=1, theta0=None, kind="nullspace", k=K, f=FRACTION) -> TrainResult:
    """Coded descent on device moments ``g``, ``h`` of ``m`` examples; ``times`` is ``(epochs, D)``, ``server_s`` what the server adds to an epoch."""
    if local_steps != 1:
        raise ValueError("coded descent allows one local epoch between two updates")
    mu = mu or schedule()
    theta = np.zeros(h.shape[1:]) if theta0 is None else np.array(theta0, float)
    start = theta.copy()
    devices = CodedDevices(g, g @ theta - h, alpha, mode, seed, k, f, kind)
    keep = len(g) - alpha + 1
    elapsed, trace, notes = offset, [], {}
    for e in range(1, (epochs or len(times)) + 1):
        order = np.argsort(times[e - 1], kind="stable")[:keep]
        elapsed += float(times[e - 1][order[-1]]) + server_s
        change = theta - start
        if mode != "clear":
            if not np.abs(change).max() < 2.0 ** (k - 1 - f):  # only wraps of literal shares lead here
                notes["left_type_at"] = e
                break
            change = quantised_model(change, f)
            theta = start + change
        nxt = step(theta, devices.gradient_sum(change, order) / m + lam * theta, mu(e))
        moved = float(np.abs(nxt - theta).max())
        theta = nxt
        if evaluate and (e % every == 0 or e == 1):
            trace.append({"epoch": e, "elapsed_s": elapsed, **evaluate(theta)})
        if moved <= tol:
            break
    return TrainResult(theta, trace, {"wraps": devices.wraps, "coded_wraps": devices.coded_wraps, "elapsed_s": elapsed, **notes})


class CodedTables:
    """Sharing phase and answers on tables in lanes, for models too large for the driver.

    ``moments`` are the devices' (``MOMENTS``). Padded shares are encoded once; coded pairs and the server's coded
    pads are written by device. An answer reads only the folders of the devices that answered; d c decoded
    cells reach the driver. The lanes must hold the widest number, which is checked.
    """

    def __init__(self, moments: DataFrame, devices: int, alpha: int, shape: tuple[int, int], seed: str = "pad", code_seed: int = 1):
        from padgrad.plans.planner import lanes_suffice

        self.spark, self.devices, self.alpha, (self.d, self.c) = moments.sparkSession, devices, alpha, shape
        if not lanes_suffice(self.d):
            raise ValueError("the residue lanes are too narrow for this many features")
        mantissa, self.b = quantise_code(build_encoder(devices, alpha, code_seed))
        codes = [mantissa % p for p in PRIMES]
        self.path, self.keys = fresh_path(self.spark, "coded"), fresh_path(self.spark, "coded-keys")
        shares = sharing.padded_rows(sharing.every_row(moments, devices, self.d, self.c), seed)
        pads = sharing.key_rows(self.spark, seed, devices, self.d, self.c)
        for rows, path in ((shares, self.path), (pads, self.keys)):
            sharing.encode_rows(rows, codes).write.partitionBy("device").parquet(path)

    def _answered(self, path: str, rows: list[int], eps: np.ndarray) -> DataFrame:
        return sharing.row_answers(self.spark.read.schema(sharing.ROWS).parquet(path).where(F.col("device").isin(rows)), eps)

    def gradient_cells(self, change: np.ndarray, order) -> DataFrame:
        """``(i, j, v)``: the sum of all device gradients at the first model + ``change``, from the first D - alpha + 1 of ``order``."""
        rows, c, scale = [int(i) for i in order[: self.devices - self.alpha + 1]], self.c, 2.0 ** (3 * FRACTION)
        if len(rows) < self.devices - self.alpha + 1:
            raise Undecodable(f"{len(rows)} answers; {self.devices - self.alpha + 1} are needed")
        a = decode_vector(self.b, rows, 1e-2)
        eps = np_lanes(np_quantise(change, 62, FRACTION))

        def plain(batches):
            for part in batches:
                lanes = (part.column("v").flatten().to_numpy() - part.column("key").flatten().to_numpy()).reshape(-1, len(PRIMES), c)
                out = np_lanes_to_float(np.stack([lanes[:, k] % p for k, p in enumerate(PRIMES)])) / scale * part.column("a").to_numpy()[:, None]
                yield pa.RecordBatch.from_arrays([part.column("i"), pa.array(list(out), pa.list_(pa.float64()))], names=["i", "v"])

        weights = F.element_at(F.array(*[F.lit(float(v)) for v in a]), F.col("device") + 1)  # D numbers
        keys = self._answered(self.keys, rows, eps).withColumnRenamed("v", "key")
        clear = self._answered(self.path, rows, eps).join(keys, ["device", "i"]).withColumn("a", weights)
        cells = clear.select("i", "v", "key", "a").mapInArrow(plain, "i int, v array<double>").select("i", F.posexplode("v").alias("j", "v"))
        return cells.groupBy("i", "j").agg(F.sum("v").alias("v"))

    def gradient_sum(self, change: np.ndarray, order) -> np.ndarray:
        total = np.zeros((self.d, self.c))
        for r in self.gradient_cells(change, order).toLocalIterator():  # d c cells
            total[r["i"], r["j"]] = r["v"]
        return total

    def drop(self) -> None:
        for path in (self.path, self.keys):
            drop_path(self.spark, path)


def train_coded_spark(moments: DataFrame, devices: int, alpha: int, m: int, shape: tuple[int, int], orders: list[list[int]], lam: float, mu, seed: str = "pad", evaluate=None) -> TrainResult:
    """Coded descent with ``CodedTables``; ``orders`` has the devices by arrival, for each epoch."""
    tables, theta, trace = CodedTables(moments, devices, alpha, shape, seed), np.zeros(shape), []
    for e, order in enumerate(orders, 1):
        theta = quantised_model(theta)
        theta = step(theta, tables.gradient_sum(theta, order) / m + lam * theta, mu(e))
        if evaluate:
            trace.append({"epoch": e, **evaluate(theta)})
    tables.drop()
    return TrainResult(theta, trace)
