"""Vectorised 64-bit hashes of byte ranges, the same in every worker."""

from __future__ import annotations

import numpy as np

#: An odd multiplier, its inverse modulo 2**64, and the finaliser's constants.
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE and INVERSE to the powers 0..n-1, grown as longer texts come."""
    if len(_powers[0]) < n:
        size = max(n, 1 << 16) * 2
        for k, b in enumerate((BASE, INVERSE)):
            with np.errstate(over="ignore"):
                _powers[k] = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(size - 1, b, np.uint64))])
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(30))) * _M1
        h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


class Ranges:
    """Hashes of any byte ranges of one text from running sums."""

    def __init__(self, data: bytes) -> None:
        n = len(data)
        up, self.down = powers(n + 1)
        self.sums = np.zeros(n + 1, np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum((np.frombuffer(data, np.uint8).astype(np.uint64) + np.uint64(1)) * up[:n], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64) * _M1)
