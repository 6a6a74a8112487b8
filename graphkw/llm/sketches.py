"""Shingle sets and fast similarity sketches."""

from __future__ import annotations

import numpy as np
import xxhash

_FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordHashes(dict):
    """Word bytes to 64-bit hashes that are the same on every machine; forgets all when full."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 500_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def shingle_set(text: str | None, size: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct hashes of the text's ``size``-word shingles (fewer words: the whole sequence; none: empty)."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else ()
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    n = min(size, len(words))
    key = np.full(len(words) - n + 1, n, np.uint64)
    for k in range(n):
        key = mix(key + h[k : k + len(key)])
    return np.unique(key)


def fast_sketch(items: np.ndarray, bins: int) -> np.ndarray:
    """A similarity sketch of ``bins`` (a power of two) coordinates of a non-empty set.

    Round r < bins throws every item into a hashed bin, round bins + b throws all
    into bin b; a bin keeps its least (round, hash). So every bin fills by the
    last round, most sets after a few, and later rounds can't change filled bins.
    """
    shift = np.uint64(bins.bit_length() - 1)
    low = np.uint64(bins - 1)
    round_bits = np.uint64(64 - 2 * bins.bit_length())
    out, done = np.full(bins, _FULL), 0
    while done < 2 * bins:
        step = min(2 * bins - done, max(1, 1024 // len(items)))
        rounds = np.arange(done, done + step, dtype=np.uint64)
        v = mix(items[None, :] + (rounds[:, None] + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))
        bin_ = np.where(rounds[:, None] < bins, v & low, rounds[:, None] - np.uint64(bins))
        value = (rounds[:, None] << round_bits) | (v >> (shift + np.uint64(64) - round_bits - shift))
        np.minimum.at(out, bin_.ravel().astype(np.int64), value.ravel())
        done += step
        if (out != _FULL).all():
            break
    return out


def bands(sketch: np.ndarray, count: int) -> np.ndarray:
    """One 64-bit key for each of ``count`` bands of neighbouring coordinates."""
    rows = sketch.reshape(count, -1)
    key = mix(np.arange(1, count + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    for k in range(rows.shape[1]):
        key = mix(key ^ rows[:, k])
    return key
