"""Word shingles as sorted 64-bit hashes, and circulant MinHash bands (Arrow side)."""

from __future__ import annotations

import numpy as np

_P = np.uint64(0x9E3779B97F4A7C15)
_A, _B = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers (a fixed pseudo-random permutation)."""
    x = (x ^ (x >> np.uint64(33))) * _A
    x = (x ^ (x >> np.uint64(29))) * _B
    return x ^ (x >> np.uint64(32))


class WordHashes(dict):
    """Word to 64-bit hash, cached; cleared when it holds ``most`` words."""

    def __init__(self, most: int = 120_000):
        import xxhash

        super().__init__()
        self.most, self.of = most, xxhash.xxh3_64_intdigest

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        self[word] = h = self.of(word)
        return h


def shingle_sets(texts: list[str | None], words: WordHashes, size: int = 5) -> list[np.ndarray]:
    """Each text's distinct shingles, sorted. Fewer than ``size`` words: the whole sequence is one; none: empty."""
    split = [(t or "").encode("utf-8", "surrogatepass").lower().split() for t in texts]
    out = []
    for w in split:
        n = len(w)
        if not n:
            out.append(np.zeros(0, np.uint64))
            continue
        h = np.fromiter(map(words.__getitem__, w), np.uint64, n)
        k = min(size, n)
        s = h[: n - k + 1].copy()
        for j in range(1, k):
            s = s * _P + h[j : n - k + 1 + j]
        out.append(np.unique(mix(s + np.uint64(k))))
    return out


def signature(sets: list[np.ndarray], coordinates: int) -> np.ndarray:
    """Circulant MinHash of non-empty sets, a row each.

    The universe is all 64-bit integers. One permutation scatters the shingles, a
    second one, shifted circularly by k, gives coordinate k.
    """
    flat = mix(np.concatenate(sets))
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    out = np.empty((len(sets), coordinates), np.uint64)
    for k in range(coordinates):
        z = (flat - np.uint64(k)) * _P
        z ^= z >> np.uint64(32)
        z *= _A
        z ^= z >> np.uint64(29)
        out[:, k] = np.minimum.reduceat(z, starts)
    return out


def band_keys(sig: np.ndarray, rows: int) -> np.ndarray:
    """One 64-bit key for each band of ``rows`` coordinates; the band's number is part of it."""
    n, k = sig.shape
    key = np.tile(np.arange(1, k // rows + 1, dtype=np.uint64), (n, 1))
    for j in range(rows):
        key = mix(key * _P + sig[:, j::rows][:, : k // rows])
    return key.view(np.int64)
