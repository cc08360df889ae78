"""Vectorised word and shingle hashing of many texts at once (numpy, no loop over words).

Each byte has a random 64-bit value; a word's hash is the sum of its bytes' values times powers of an odd base, taken
from one running sum over the chunk, then mixed. Two different words share a hash with a chance of about 2**-63.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

U = np.uint64
_rng = np.random.Generator(np.random.PCG64(20240607))
BYTE_VALUES = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
BASE = int(_rng.integers(2**61, 2**62)) * 4 + 1
INVERSE = pow(BASE, -1, 2**64)
SHINGLE = U(0x9E3779B97F4A7C15)
BLANK = np.zeros(256, bool)
BLANK[[9, 10, 11, 12, 13, 32]] = True
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
CHUNK_BYTES = 1 << 20
_powers: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i for i < n; grown on need and kept by the worker."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, CHUNK_BYTES + 4096)
        _powers[:] = [np.cumprod(np.concatenate([[U(1)], np.full(size - 1, U(b), np.uint64)]), dtype=np.uint64) for b in (BASE, INVERSE)]
    return _powers[0][:n], _powers[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U(33))
    h *= U(0xFF51AFD7ED558CCD)
    h ^= h >> U(33)
    h *= U(0xC4CEB9FE1A85EC53)
    h ^= h >> U(33)
    return h


def chunks_of_bytes(texts, limit: int = CHUNK_BYTES) -> Iterator[list[bytes]]:
    """An Arrow column of binary values (null: empty) in lists of about limit bytes; a longer text stands alone."""
    held, size = [], 0
    for t in texts:
        b = t.as_py() or b""
        if held and size + len(b) > limit:
            yield held
            held, size = [], 0
        held.append(b)
        size += len(b) + 1
    if held:
        yield held


def running(data: np.ndarray) -> np.ndarray:
    """Running sums by which span_hash gets the hash of any span of bytes or of 64-bit values."""
    p, _ = powers(len(data) + 1)
    s = np.zeros(len(data) + 1, np.uint64)
    v = BYTE_VALUES[data] if data.dtype == np.uint8 else data.copy()
    v *= p[: len(data)]
    np.cumsum(v, out=s[1:])
    return s


def span_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    _, inv = powers(len(sums))
    h = sums[end] - sums[start]
    h *= inv[start]
    return h


class Words:
    """Words of several texts: starts, ends (bytes in data), hashes; words of text i are first[i]:first[i + 1]."""

    def __init__(self, texts: list[bytes], lower: bool = True):
        sizes = np.array([len(t) for t in texts], np.int64)
        self.at = np.concatenate([[0], np.cumsum(sizes + 1)])
        raw = b"\n".join(texts) + b"\n"
        self.data = np.frombuffer(raw.translate(LOWER) if lower else raw, np.uint8)
        edge = np.diff(np.concatenate([[True], BLANK[self.data]]).view(np.int8))
        self.starts, self.ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        self.hashes = mix(span_hash(running(self.data), self.starts, self.ends))
        self.first = np.searchsorted(self.starts, self.at)

    def shingles(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(hash, word at which it starts, bounds by text) of all k-word shingles; a shorter text has its whole sequence as one."""
        n, h = np.diff(self.first), self.hashes
        per = np.where(n >= k, n - k + 1, np.minimum(n, 1))
        bounds = np.concatenate([[0], np.cumsum(per)])
        at = np.arange(bounds[-1]) - np.repeat(bounds[:-1] - self.first[:-1], per)
        padded = np.concatenate([h, np.zeros(k, np.uint64)])
        acc = np.zeros(len(at), np.uint64)
        for j in range(k):
            acc = mix(acc * SHINGLE + padded[at + j])
        for i in np.flatnonzero((n > 0) & (n < k)):
            one = np.full(1, n[i], np.uint64)
            for x in h[self.first[i] : self.first[i + 1]]:
                one = mix(one * SHINGLE + x)
            acc[bounds[i]] = one[0]
        return acc, at, bounds
