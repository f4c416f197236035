"""Fixed-point numbers as BIGINT mantissas, and exact residue lanes.

A number of the type (k, f) is a mantissa in ``[-2^(k-1), 2^(k-1))`` scaled by ``2^-f``.
Column functions stay in whole-stage code; ``np_*`` twins do the same on arrays.
Products need 96 bits at k = 48, so both factors are split into limbs of f bits; that
holds for 2f <= 48 and k - f <= 31, and is checked.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

K, FRACTION = 48, 24
#: The five largest primes below 2^31, one for each residue lane.
PRIMES = (2147483647, 2147483629, 2147483587, 2147483579, 2147483563)


def fx_bounds(k: int = K, f: int = FRACTION) -> dict[str, float]:
    """Least and greatest number, range and resolution of the type."""
    return {"least": -(2.0 ** (k - 1 - f)), "greatest": (2 ** (k - 1) - 1) * 2.0**-f, "range": 2.0 ** (k - f), "resolution": 2.0**-f}


def quantise(c: Column, k: int = K, f: int = FRACTION, rounding: str = "nearest") -> Column:
    """Mantissa of a double; null stays null, NaN and numbers outside the type raise."""
    scaled = c.cast("double") * float(2**f)
    m = F.floor(scaled) if rounding == "floor" else F.floor(scaled + 0.5)
    inside = (m >= -(2 ** (k - 1))) & (m < 2 ** (k - 1)) & ~F.isnan(c.cast("double"))
    return F.when(c.isNull(), F.lit(None).cast("long")).when(inside, m.cast("long")).otherwise(F.raise_error(F.lit("outside the fixed-point type")).cast("long"))


def quantise_vector(c: Column, k: int = K, f: int = FRACTION, rounding: str = "nearest") -> Column:
    return F.transform(c, lambda x: quantise(x, k, f, rounding))


def dequantise(c: Column, f: int = FRACTION) -> Column:
    return c / float(2**f)


def wrap(c: Column, k: int = K) -> Column:
    """Integer modulo 2^k into the signed set."""
    half = 2 ** (k - 1)
    return F.pmod(c + F.lit(half), F.lit(2**k)) - F.lit(half)


def fx_add(a: Column, b: Column, k: int = K) -> Column:
    return wrap(a + b, k)


def _need_limbs(k: int, f: int) -> None:
    if not (k - f <= 31 and 2 * f <= 48):
        raise ValueError("limb products need k - f <= 31 and f <= 24")


def fx_mul(a: Column, b: Column, k: int = K, f: int = FRACTION) -> Column:
    """``floor(a b 2^-f)`` wrapped; no step leaves 63 bits."""
    _need_limbs(k, f)
    mask = F.lit(2**f - 1)
    ah, al, bh, bl = F.shiftright(a, f), a.bitwiseAND(mask), F.shiftright(b, f), b.bitwiseAND(mask)
    top = F.shiftleft(wrap(ah * bh, k - f), f)  # multiples of 2^k vanish in the wrap below
    return wrap(top + wrap(ah * bl, k) + wrap(al * bh, k) + F.shiftright(al * bl, f), k)


def fx_scale(public: Column, share: Column, k: int = K, f: int = FRACTION) -> Column:
    """Public number times secret share: the only product the scheme needs."""
    return fx_mul(public, share, k, f)


def fx_dot(a: Column, b: Column, k: int = K, f: int = FRACTION) -> Column:
    """Wrapped sum of the products of two mantissa arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: fx_mul(x, y, k, f)), F.lit(0).cast("long"), lambda acc, x: fx_add(acc, x, k))


def to_lane(c: Column, prime: int) -> Column:
    return F.pmod(c, F.lit(prime))


def lane_mul(a: Column, b: Column, prime: int) -> Column:
    """Product of two residues below 2^31."""
    return F.pmod(a * b, F.lit(prime))


def from_two_lanes(r0: Column, r1: Column) -> Column:
    """Signed integer below 2^61 in size from its residues modulo the first two primes."""
    p, q = PRIMES[:2]
    m = p * q
    x = r0 + F.lit(p) * F.pmod(F.pmod(r1 - r0, F.lit(q)) * F.lit(pow(p, -1, q)), F.lit(q))
    return F.when(x > m // 2, x - F.lit(m)).otherwise(x)


def np_wrap(x: np.ndarray, k: int = K) -> np.ndarray:
    half = 1 << (k - 1)
    return ((x + half) & ((1 << k) - 1)) - half


def np_quantise(x: np.ndarray, k: int = K, f: int = FRACTION) -> np.ndarray:
    m = np.floor(np.asarray(x, float) * 2.0**f + 0.5)
    if not np.all((m >= -(2.0 ** (k - 1))) & (m < 2.0 ** (k - 1))):
        raise ValueError("outside the fixed-point type")
    return m.astype(np.int64)


def np_mul(a: np.ndarray, b: np.ndarray, k: int = K, f: int = FRACTION) -> np.ndarray:
    _need_limbs(k, f)
    mask = (1 << f) - 1
    ah, al, bh, bl = a >> f, a & mask, b >> f, b & mask
    return np_wrap((np_wrap(ah * bh, k - f) << f) + np_wrap(ah * bl, k) + np_wrap(al * bh, k) + ((al * bl) >> f), k)


def np_matmul(a: np.ndarray, b: np.ndarray, k: int = K, f: int = FRACTION) -> np.ndarray:
    """Wrapped matrix product of mantissas: every product is floored by itself, sums of them stay below 2^63."""
    out = np.zeros((a.shape[0], b.shape[1]), np.int64)
    for j in range(0, a.shape[1], 64):
        out = np_wrap(out + np_mul(a[:, j : j + 64, None], b[None, j : j + 64], k, f).sum(axis=1), k)
    return out


def np_lanes(x: np.ndarray, primes=PRIMES) -> np.ndarray:
    """Residues of integers (any size, also Python integers), a lane each in front."""
    return np.stack([np.asarray(x % p, dtype=np.int64) for p in primes])


def np_lane_matmul(a: np.ndarray, b: np.ndarray, primes=PRIMES) -> np.ndarray:
    """Matrix products lane by lane; ``a`` (lanes first) may be float64 already."""
    return np.stack([np_mod_matmul(a[lane], b[lane], p) for lane, p in enumerate(primes)])


def np_mod_matmul(x: np.ndarray, y: np.ndarray, p: int) -> np.ndarray:
    """``x @ y mod p`` of residues: ``y`` is split into 16-bit halves, so float64 sums of 32 products stay exact."""
    x, c = np.asarray(x, float), y.shape[1]
    halves = np.hstack([y >> 16, y & 0xFFFF]).astype(float)
    total = np.zeros((x.shape[0], 2 * c), np.int64)
    for at in range(0, x.shape[1], 32):  # 32 products of 31 and 16 bits stay below 2^53
        total += (x[:, at : at + 32] @ halves[at : at + 32]).astype(np.int64) % p
    total %= p
    return ((total[:, :c] << 16) % p + total[:, c:]) % p


def np_lanes_to_float(r: np.ndarray, primes=PRIMES) -> np.ndarray:
    """Signed integers from residues, as doubles (relative error of one rounding a lane).

    Mixed-radix digits are below 2^31, so all steps stay in int64; a negative number is read from its
    opposite, whose upper digits are zero.
    """

    def digits(r):
        out: list[np.ndarray] = []
        for lane, p in enumerate(primes):
            x = np.zeros_like(r[0])
            radix = 1
            for d, q in zip(out, primes, strict=False):
                x = (x + d * radix) % p
                radix = radix * q % p
            out.append((r[lane] - x) % p * pow(radix, -1, p) % p)
        return out

    plus = digits(r)
    minus = digits(np.stack([(p - r[lane]) % p for lane, p in enumerate(primes)]))
    negative = plus[-1] > primes[-1] // 2
    value, radix = np.zeros(r.shape[1:]), 1.0
    for a, b, p in zip(plus, minus, primes, strict=True):
        value = value + np.where(negative, b, a) * radix
        radix *= p
    return np.where(negative, -value, value)


def np_from_lanes(r: np.ndarray, primes=PRIMES) -> np.ndarray:
    """Signed Python integers from residues (Garner's mixed radix)."""
    x, m = r[0].astype(object), primes[0]
    for lane in range(1, len(primes)):
        p = primes[lane]
        step = ((r[lane].astype(object) - x) * pow(m, -1, p)) % p
        x, m = x + m * step, m * p
    return np.where(x > m // 2, x - m, x)
