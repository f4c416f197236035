"""Cyclic gradient codes: encoders, decoders, their checks and their Spark tables.

Row i of the encoder B has the cyclic support i .. i + alpha - 1 and says what device i
combines; any D - alpha + 1 rows combine to the all-ones row. Codes are built on the
driver (D is a few hundred at most) and broadcast: a code has at most D^2 entries.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from padgrad.functions.fixedpoint import FRACTION, np_quantise


class Undecodable(ValueError):
    """Too few answers for the code."""


def support(d: int, alpha: int, row: int) -> list[int]:
    return [(row + s) % d for s in range(alpha)]


def cyclic_support(spark: SparkSession, d: int, alpha: int) -> DataFrame:
    """``(device, slot, peer)``: whose shares a device combines."""
    _check(d, alpha)
    slots = F.explode(F.sequence(F.lit(0), F.lit(alpha - 1))).alias("slot")
    base = spark.range(d).select(F.col("id").cast("int").alias("device"), slots)
    return base.withColumn("peer", F.pmod(F.col("device") + F.col("slot"), F.lit(d)))


def _check(d: int, alpha: int) -> None:
    if not 1 <= alpha <= d:
        raise ValueError("alpha must lie between 1 and the number of devices")


def build_encoder(d: int, alpha: int, seed: int = 0, kind: str = "nullspace") -> np.ndarray:
    """Encoder of kind ``nullspace`` (any alpha), ``blocks`` (alpha divides D) or ``circulant``."""
    _check(d, alpha)
    if alpha == 1:
        return np.eye(d)
    if alpha == d:
        return np.ones((d, d))
    if kind == "blocks":
        return _blocks(d, alpha)
    if kind == "circulant":
        return _circulant(d, alpha)
    best, least = None, math.inf
    rng = np.random.default_rng(seed)
    for _ in range(4):  # the draw with the smallest decode weights is kept
        b = _nullspace(d, alpha, rng)
        size = max(np.abs(decode_vector(b, rng.choice(d, d - alpha + 1, replace=False))).sum() for _ in range(24))
        if size < least:
            best, least = b, size
    return best


def _nullspace(d: int, alpha: int, rng) -> np.ndarray:
    """Rows in the null space of a random matrix whose rows sum to zero, so all-ones lies in the row span too."""
    h = rng.standard_normal((alpha - 1, d))
    h[:, -1] = -h[:, :-1].sum(axis=1)
    b = np.zeros((d, d))
    for i in range(d):
        s = support(d, alpha, i)
        b[i, i] = 1.0
        b[i, s[1:]] = -np.linalg.solve(h[:, s[1:]], h[:, i])
    return b


def _blocks(d: int, alpha: int) -> np.ndarray:
    """Fractional repetition: groups of alpha devices all hold the sum of their group."""
    if d % alpha:
        raise ValueError("blocks need alpha to divide the number of devices")
    return np.kron(np.eye(d // alpha), np.ones((alpha, alpha)))


def _circulant(d: int, alpha: int) -> np.ndarray:
    """Shifts of one polynomial with alpha - 1 roots among the D-th roots of unity, closed under conjugation."""
    if (d % 2) != (alpha % 2):
        raise ValueError("a real circulant code needs D and alpha both odd or both even")
    roots = []
    middle = alpha - 1
    if d % 2 == 0:  # an odd number of roots: -1 is one of them
        roots.append(-1.0 + 0j)
        middle -= 1
    start = (d - 1) // 2 if d % 2 else d // 2 - 1
    for k in range(middle // 2):
        z = np.exp(2j * np.pi * (start - k) / d)
        roots += [z, z.conjugate()]
    first = np.real(np.poly(roots))
    b = np.zeros((d, d))
    for i in range(d):
        b[i, support(d, alpha, i)] = first
    return b


def decode_vector(b: np.ndarray, arrived, tolerance: float = 1e-6) -> np.ndarray:
    """Weights a (zero outside ``arrived``) with a B = all-ones. A quantised B needs a wider tolerance: it meets that only about."""
    rows = np.array(sorted(arrived))
    if not len(rows):
        raise Undecodable("no answers")
    a, *_ = np.linalg.lstsq(b[rows].T, np.ones(b.shape[1]), rcond=None)
    if np.abs(a @ b[rows] - 1).max() > tolerance:
        raise Undecodable("these answers do not combine to the sum")
    out = np.zeros(b.shape[0])
    out[rows] = a
    return out


def straggler_patterns(d: int, alpha: int) -> int:
    return math.comb(d, alpha - 1)


def build_decoder(spark: SparkSession, b: np.ndarray, alpha: int, limit: int = 100_000) -> DataFrame:
    """``(pattern_id, device, coef)`` for all patterns, solved in parallel; refused above ``limit`` patterns."""
    d = len(b)
    count = straggler_patterns(d, alpha)
    if count > limit:
        raise ValueError(f"{count} patterns; use decode_vector for the patterns that occur")
    shared = spark.sparkContext.broadcast(b)

    def solve(batches):
        import pandas as pd

        for frame in batches:
            rows = []
            for p in frame["id"]:
                arrived = unrank(int(p), d, d - alpha + 1)
                a = decode_vector(shared.value, arrived)
                rows += [(int(p), int(i), float(a[i])) for i in arrived]
            yield pd.DataFrame(rows, columns=["pattern_id", "device", "coef"])

    return spark.range(count).mapInPandas(solve, "pattern_id long, device int, coef double")


def unrank(index: int, n: int, size: int) -> list[int]:
    """The subset of ``range(n)`` of that place in lexicographic order."""
    out, x = [], 0
    while size:
        here = math.comb(n - x - 1, size - 1)
        if index < here:
            out.append(x)
            size -= 1
        else:
            index -= here
        x += 1
    return out


def pattern_rows(spark: SparkSession, d: int, alpha: int, runs: int = 8) -> DataFrame:
    """``(pattern_id, device)``: every set of answers that decodes, enumerated by a table function in parallel runs."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="pattern_id long, device int")
    class Patterns:
        def eval(self, first: int, last: int, n: int, size: int):
            for index in range(first, last):
                for device in unrank(index, n, size):
                    yield index, device

    total = straggler_patterns(d, alpha)
    spark.udtf.register("straggler_patterns", Patterns)
    step = max(1, -(-total // runs))
    spark.range(0, total, step).createOrReplaceTempView("pattern_runs")
    return spark.sql(f"SELECT p.* FROM pattern_runs r, LATERAL straggler_patterns(r.id, least(r.id + {step}, {total}), {d}, {d - alpha + 1}) p")


def encoder_table(spark: SparkSession, b: np.ndarray) -> DataFrame:
    """``(device, peer, coef)`` of the non-zero entries."""
    rows = [(int(i), int(j), float(b[i, j])) for i, j in zip(*np.nonzero(b), strict=True)]
    return spark.createDataFrame(rows, "device int, peer int, coef double")


def verify_code(code_a: DataFrame, code_b: DataFrame) -> DataFrame:
    """``(pattern_id, peer, value)``: entries of A B, all of them 1 for a sound code."""
    joined = code_a.join(F.broadcast(code_b.withColumnRenamed("coef", "b")), "device")
    return joined.groupBy("pattern_id", "peer").agg(F.sum(F.col("coef") * F.col("b")).alias("value"))


def table_conditioning(spark: SparkSession, b: np.ndarray, alpha: int) -> DataFrame:
    """``(patterns, residual, largest, weight_sum)``: the worst over all straggler patterns, solved and checked in parallel."""
    code_a = build_decoder(spark, b, alpha)
    off = verify_code(code_a, encoder_table(spark, b)).agg(F.max(F.abs(F.col("value") - 1)).alias("residual"))
    sizes = code_a.groupBy("pattern_id").agg(F.max(F.abs("coef")).alias("largest"), F.sum(F.abs("coef")).alias("total"))
    sizes = sizes.agg(F.count("*").alias("patterns"), F.max("largest").alias("largest"), F.max("total").alias("weight_sum"))
    return sizes.crossJoin(off)  # one row each


def quantise_code(b: np.ndarray, k: int = 48, f: int = FRACTION) -> tuple[np.ndarray, np.ndarray]:
    """Mantissas of B and the numbers they stand for; decoders are solved against the latter."""
    m = np_quantise(b, k, f)
    return m, m / 2.0**f


def conditioning(b: np.ndarray, alpha: int, samples: int = 200, seed: int = 0) -> dict[str, float]:
    """Worst residual and decode weights over sampled (or all, if few) patterns."""
    d, rng = len(b), np.random.default_rng(seed)
    size = d - alpha + 1
    patterns = itertools.combinations(range(d), size) if straggler_patterns(d, alpha) <= samples else (rng.choice(d, size, replace=False) for _ in range(samples))
    worst = {"residual": 0.0, "largest": 0.0, "sum": 0.0}
    for p in patterns:
        a = decode_vector(b, p)
        worst["residual"] = max(worst["residual"], float(np.abs(a @ b - 1).max()))
        worst["largest"], worst["sum"] = max(worst["largest"], float(np.abs(a).max())), max(worst["sum"], float(np.abs(a).sum()))
    return worst


# --- codes over a prime field: A B = 1 holds exactly -----------------------------------------


def _solve_mod(m: list[list[int]], y: list[int], p: int) -> list[int]:
    """A solution of m x = y modulo p by elimination; free unknowns are 0."""
    rows = [[v % p for v in r] + [t % p] for r, t in zip(m, y, strict=True)]
    n, pivots, r = len(m[0]) if m else 0, [], 0
    for c in range(n):
        lead = next((k for k in range(r, len(rows)) if rows[k][c]), None)
        if lead is None:
            continue
        rows[r], rows[lead] = rows[lead], rows[r]
        inverse = pow(rows[r][c], -1, p)
        rows[r] = [v * inverse % p for v in rows[r]]
        for k in range(len(rows)):
            if k != r and rows[k][c]:
                t = rows[k][c]
                rows[k] = [(v - t * w) % p for v, w in zip(rows[k], rows[r], strict=True)]
        pivots.append(c)
        r += 1
    if any(row[-1] for row in rows[r:]):
        raise Undecodable("these answers do not combine to the sum")
    x = [0] * n
    for k, c in enumerate(pivots):
        x[c] = rows[k][-1]
    return x


def field_encoder(d: int, alpha: int, prime: int, seed: int = 0) -> np.ndarray:
    """Encoder with entries modulo ``prime``."""
    _check(d, alpha)
    if alpha == 1:
        return np.eye(d, dtype=np.int64)
    if alpha == d:
        return np.ones((d, d), np.int64)
    rng = np.random.default_rng(seed)
    h = rng.integers(1, prime, (alpha - 1, d)).astype(object)
    h[:, -1] = (-h[:, :-1].sum(axis=1)) % prime
    b = np.zeros((d, d), np.int64)
    for i in range(d):
        s = support(d, alpha, i)
        x = _solve_mod([[int(h[r, j]) for j in s[1:]] for r in range(alpha - 1)], [-int(h[r, i]) for r in range(alpha - 1)], prime)
        b[i, s] = [1, *x]
    return b


def field_decode_vector(b: np.ndarray, arrived, prime: int) -> np.ndarray:
    rows = sorted(arrived)
    x = _solve_mod([[int(b[i, j]) for i in rows] for j in range(b.shape[1])], [1] * b.shape[1], prime)
    out = np.zeros(len(b), np.int64)
    out[rows] = x
    return out
