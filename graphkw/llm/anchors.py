"""Rolling fingerprints of byte strings and content-chosen anchors among them."""

from __future__ import annotations

import numpy as np

from .sketches import mix

#: Fixed odd multiplier of the polynomial fingerprints, and its inverse modulo 2**64.
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.ones(1, np.uint64)
    step = np.array([base], np.uint64)
    while len(out) < n:
        out = np.concatenate([out, out * step])
        step = step * step
    return out[:n]


class Fingerprints:
    """64-bit fingerprints of any substring of ``data`` (prefix sums of a polynomial modulo 2**64, scrambled)."""

    def __init__(self, data: bytes):
        raw = np.frombuffer(data, np.uint8)
        self.inverse = _powers(_INVERSE, len(raw) + 1)
        self.sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(mix(raw.astype(np.uint64) + np.uint64(1)) * _powers(_BASE, len(raw)), out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.inverse[start] + (end - start).astype(np.uint64))

    def all(self, size: int) -> np.ndarray:
        """Of every substring of ``size`` bytes."""
        return mix((self.sums[size:] - self.sums[:-size]) * self.inverse[: len(self.sums) - size] + np.uint64(size))


def window_argmin(values: np.ndarray, size: int) -> np.ndarray:
    """Place of the first least value (by its upper 40 bits) in every run of ``size`` values; at most 2**24 values."""
    n, low = len(values), np.uint64((1 << 24) - 1)
    v = np.concatenate([(values & ~low) | np.arange(n, dtype=np.uint64), np.full(-n % size, np.iinfo(np.uint64).max, np.uint64)])
    blocks = v.reshape(-1, size)
    left = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    right = np.minimum.accumulate(blocks, axis=1).ravel()
    count = n - size + 1
    return (np.minimum(left[:count], right[size - 1 : size - 1 + count]) & low).astype(np.int64)
