"""Texts as flat numpy arrays: words, their hashes and hashes of runs of words, without a Python object for each word.

Hashes are polynomials modulo 2**64 with odd bases over mixed 64-bit letters, so a run's hash is a difference of prefix
sums times a power of the inverse base. Two seeds of the letters give two independent hashes where 64 bits are not enough.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

PIECE = 1 << 21  # bytes of text handled at once
_cache: dict = {}
_white = np.zeros(256, bool)
_white[[32, 9, 10, 11, 12, 13]] = True
_fold = np.arange(256, dtype=np.uint8)
_fold[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


BASE = 0x9B97D68D3A1F5C2B


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """Powers of the base, kept for the life of a worker: one table and one of inverses, whatever the seeds."""
    key = inverse
    if key not in _cache or len(_cache[key]) < n:
        b = BASE
        if inverse:
            b = pow(b, -1, 1 << 64)
        size = 1 << max(10, int(n - 1).bit_length())
        out = np.full(size, b, np.uint64)
        out[0] = 1
        with np.errstate(over="ignore"):
            _cache[key] = np.multiply.accumulate(out)
    return _cache[key][:n]


def letters(seed: int) -> np.ndarray:
    return mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))


class Runs:
    """Hashes of any run of a sequence of 64-bit values."""

    def __init__(self, values: np.ndarray, salt: int):
        n = len(values)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum((values + np.uint64(salt)) * powers(n), out=self.sums[1:])

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * powers(len(self.sums), True)[start])


class Words:
    """Words [^\\x20\\x09-\\x0D]+ of many texts: start and end byte, document of each, and first word of each document."""

    def __init__(self, texts: list[bytes], fold: bool = False):
        raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        self.raw = _fold[raw] if fold else raw
        ink = ~_white[self.raw]
        edge = np.flatnonzero(ink[1:] != ink[:-1]) + 1
        if len(ink) and ink[0]:
            edge = np.concatenate([[0], edge])
        self.start, self.end = edge[::2], edge[1::2]
        self.doc_at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1)])
        self.first = np.searchsorted(self.start, self.doc_at)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(len(texts)), self.count)

    def hashes(self, seed: int) -> np.ndarray:
        return Runs(letters(seed)[self.raw], seed)(self.start, self.end)

    def windows(self, k: int) -> np.ndarray:
        """First words of all runs of k words inside one document."""
        at = np.arange(len(self.start) - k + 1) if len(self.start) >= k else np.zeros(0, np.int64)
        return at[self.doc[at] == self.doc[at + k - 1]] if len(at) else at

    def windows_of(self, docs_windows: np.ndarray) -> np.ndarray:
        return np.bincount(self.doc[docs_windows], minlength=len(self.count))


def parts(texts: list[bytes], most: int = PIECE):
    """Index ranges of texts with about `most` bytes each."""
    first = size = 0
    for i, t in enumerate(texts):
        if i > first and size + len(t) > most:
            yield first, i
            first, size = i, 0
        size += len(t)
    if texts:
        yield first, len(texts)


def as_bytes(col: pa.Array) -> list[bytes]:
    return [x or b"" for x in col.cast(pa.binary()).to_pylist()]
