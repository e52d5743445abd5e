"""64-bit hashes of words, shared by the operators that work on word sequences."""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15
#: A random 64-bit value for each byte.
_BYTES = np.random.default_rng(20).integers(0, 2**64, 256, dtype=np.uint64)
_SOLID = np.array([b not in b" \t\n\x0b\x0c\r" for b in range(256)])
_kept: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base to the powers 0 .. n-1, modulo 2^64; kept up to a bound."""
    have = _kept.get(base)
    if have is None or len(have) < n:
        size = max(1024, 1 << (n - 1).bit_length())
        have = np.full(size, base, np.uint64)
        have[0] = 1
        have = np.cumprod(have, dtype=np.uint64)
        if size <= 1 << 18:
            _kept[base] = have
    return have[:n]


class Ranges:
    """Hashes of any range of a sequence of 64-bit values, from sums of the scaled values."""

    def __init__(self, h: np.ndarray, base: int):
        n = len(h) + 1
        self.back = powers(pow(base, -1, 1 << 64), n)
        self.sums = np.zeros(n, np.uint64)
        np.cumsum(h * powers(base, n)[:-1], out=self.sums[1:])

    def __call__(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return mix((self.sums[hi] - self.sums[lo]) * self.back[lo] + (hi - lo).astype(np.uint64))


def word_hashes(raw: bytes) -> np.ndarray:
    """A hash of each word of a text (bytes between the six white-space bytes), equal on every machine.

    Two different words meet with a chance of about 2^-64: each byte stands for a random value.
    """
    b = np.frombuffer(raw, np.uint8)
    solid = np.zeros(len(b) + 2, np.int8)
    solid[1:-1] = _SOLID[b]
    edges = np.flatnonzero(solid[1:] != solid[:-1])
    return Ranges(_BYTES[b], _BASE)(edges[0::2], edges[1::2])


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def places(n: int, seed: int) -> np.ndarray:
    """n fixed odd multipliers."""
    return np.random.default_rng(seed).integers(1, 2**63, n, dtype=np.uint64) << np.uint64(1) | np.uint64(1)


def windows(hashes: np.ndarray, n: int, seed: int = 1) -> np.ndarray:
    """A hash of each run of n words, order included."""
    count = len(hashes) - n + 1
    if count <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(count, np.uint64)
    for k, m in enumerate(places(n, seed)):
        out += hashes[k : k + count] * m
    return mix(out)
