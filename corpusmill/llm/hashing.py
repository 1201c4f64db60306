"""Word shingles, set digests and bit maps, the same in every worker."""

from __future__ import annotations

import hashlib

import numpy as np

from corpusmill.functions.hashing import BASE, INVERSE, Ranges, mix, powers  # noqa: F401  operators take them from here

_SPACES = bytes(b + 32 if 65 <= b <= 90 else 32 if 9 <= b <= 13 else b for b in range(256))


def shingle_set(raw: bytes | None, size: int = 5) -> np.ndarray:
    """Sorted hashes of the distinct word shingles: A-Z folded, words split at ASCII white space, a shorter text is one shingle."""
    words = (raw or b"").translate(_SPACES).split()
    if not words:
        return np.empty(0, np.uint64)
    line = b" ".join(words)
    ranges = Ranges(line)
    if len(words) < size:
        return ranges.of(np.array([0]), np.array([len(line)]))
    gaps = np.flatnonzero(np.frombuffer(line, np.uint8) == 32)
    start, end = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(line)]])
    return np.unique(ranges.of(start[: len(words) - size + 1], end[size - 1 :]))


def set_digest(tokens: np.ndarray) -> bytes:
    return hashlib.blake2b(tokens.tobytes(), digest_size=16).digest()


class Bits:
    """A bit map of fixed size: which hashes may be in a set."""

    def __init__(self, log_bits: int, packed: bytes | None = None) -> None:
        self.shift = np.uint64(64 - log_bits)
        self.map = np.frombuffer(packed, np.uint8).copy() if packed else np.zeros(1 << (log_bits - 3), np.uint8)

    def _at(self, h: np.ndarray):
        for k in (h, mix(h + np.uint64(1))):
            slot = k >> self.shift
            yield (slot >> np.uint64(3)).astype(np.int64), np.uint8(1) << (slot & np.uint64(7)).astype(np.uint8)

    def add(self, h: np.ndarray) -> None:
        for byte, bit in self._at(h):
            np.bitwise_or.at(self.map, byte, bit)

    def has(self, h: np.ndarray) -> np.ndarray:
        out = np.ones(len(h), bool)
        for byte, bit in self._at(h):
            out &= (self.map[byte] & bit) > 0
        return out
