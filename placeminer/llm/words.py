"""Words and shingles of texts as numpy hashes, for kernels that run inside tasks.

A word is a maximal run of bytes other than blank, tab, LF, VT, FF, CR; a shingle is five words in a row.
Hashes have 64 bits and are keyed by position, so equal shingles always meet and unequal ones
meet with a chance of 2**-64 a pair.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash

#: Odd multipliers of the five positions of a shingle, made by a rule.
MULTIPLIERS = [np.uint64(xxhash.xxh64_intdigest(f"position {i}") | 1) for i in range(5)]
#: Memoised words per task, and the length up to which words are.
MEMO = 1 << 16
SHORT = 64


class WordHashes(dict):
    """word bytes -> signed 64-bit hash, memoised within a bound."""

    def __init__(self, memo: int = MEMO):
        super().__init__()
        self.memo = memo

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        h = h - (1 << 64) if h >> 63 else h
        if len(self) < self.memo and len(word) <= SHORT:
            self[word] = h
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words)).view(np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit numbers."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    return x * np.uint64(0xD6E8FEB86659FD93)


def windows(h: np.ndarray, width: int = 5) -> np.ndarray:
    """Hashes of all windows of ``width`` <= 5 words; empty if there are fewer words."""
    n = len(h) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = h[:n] * MULTIPLIERS[0]
    for i in range(1, width):
        out = out + h[i : i + n] * MULTIPLIERS[i]
    return mixed(out + np.uint64(width))


def shingles(h: np.ndarray) -> np.ndarray:
    """Hashes of the distinct five-word shingles, sorted; the whole sequence if there are fewer words."""
    return np.unique(windows(h, min(5, len(h)))) if len(h) else np.empty(0, np.uint64)


def slices(batch: pa.RecordBatch, rows: int = 512) -> Iterator[pa.RecordBatch]:
    """Parts of a batch, so that few texts are Python objects at once."""
    for i in range(0, len(batch), rows):
        yield batch.slice(i, rows)


Kernel = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def tidy(kernel: Kernel) -> Kernel:
    """A kernel that hands its memory back when its task ends; workers stay for later tasks, and idle ones add up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from kernel(batches)
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except (OSError, AttributeError):  # another C library: nothing to hand back
            pass

    return run
