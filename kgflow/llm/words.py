"""Words of whole Arrow columns as numpy arrays: no Python object per word.

Texts are handled in chunks of ``CHUNK`` bytes (a longer single text is a chunk of its own).
In a chunk, word boundaries come from a byte table, word hashes from a polynomial prefix sum
over the bytes, and hashes of k consecutive words from one over the word hashes, all modulo
2**64 with odd bases, so that a power can be divided out.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

LIBC = ctypes.CDLL(None)

CHUNK = 1 << 20
U = np.uint64
#: Fixed odd multipliers of the hash functions.
BYTE_BASE, WORD_BASE = U(0x9E3779B97F4A7C13), U(0xD6E8FEB86659FD93)
MIX_A, MIX_B = U(0xFF51AFD7ED558CCD), U(0xC4CEB9FE1A85EC53)

BYTE_CODES = np.random.default_rng(20260101).integers(1, 2**63, 256, dtype=np.uint64) | U(1)

#: Bytes that belong to words: all but ASCII white space.
NONSPACE = np.ones(256, bool)
NONSPACE[[0x20, *range(0x09, 0x0E)]] = False
#: Bytes that belong to words: ASCII digits and letters, and all of non-ASCII characters.
ALNUM = np.zeros(256, bool)
ALNUM[0x30:0x3A] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True
#: Lower-cases A-Z only.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def trim() -> None:
    """Give freed memory back to the system: workers live on between tasks, and share an executor's memory."""
    pa.default_memory_pool().release_unused()
    if hasattr(LIBC, "malloc_trim"):
        LIBC.malloc_trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> U(33))
    x *= MIX_A
    x ^= x >> U(33)
    x *= MIX_B
    x ^= x >> U(33)
    return x


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and its inverse, i < n, modulo 2**64."""
    have = _powers.get(int(base))
    if have is None or len(have[0]) < n:
        size = max(n, 1 << 16)
        both = []
        for b in (int(base), pow(int(base), -1, 1 << 64)):
            p = np.full(size, U(b))
            p[0] = 1
            both.append(np.cumprod(p, dtype=np.uint64))
        have = (both[0], both[1])
        if size <= 2 * CHUNK:
            _powers[int(base)] = have
    return have


@dataclass
class Chunk:
    """Texts lo .. hi-1 of an Arrow column."""

    lo: int
    hi: int
    buf: np.ndarray  # bytes of all texts
    at: np.ndarray  # byte offsets of the texts, one more than texts
    start: np.ndarray  # of words, in buf
    end: np.ndarray
    first: np.ndarray  # index of each text's first word, one more than texts

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(self.hi - self.lo), self.counts())

    def hashes(self, *prefixes: int) -> np.ndarray:
        """64-bit hash of every word; with prefixes, of (words, 1 + prefixes) words and their first so many bytes."""
        n = len(self.buf)
        pw, inv = powers(BYTE_BASE, n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum(BYTE_CODES[self.buf] * pw[:n], out=total[1:])
        base, back = total[self.start], inv[self.start]
        whole = mix((total[self.end] - base) * back)
        if not prefixes:
            return whole
        cut = [mix(((total[np.minimum(self.end, self.start + k)] - base) * back) ^ U(k)) for k in prefixes]
        return np.stack([whole, *cut], 1)

    def word(self, i: int) -> bytes:
        return self.buf[self.start[i] : self.end[i]].tobytes()


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null is empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = col.fill_null("")
    _, offsets, data = col.buffers()
    at = np.frombuffer(offsets, np.int64 if pa.types.is_large_string(col.type) else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), at


def chunks(col: pa.Array, inside: np.ndarray = NONSPACE, lower: bool = False, most: int = CHUNK) -> Iterator[Chunk]:
    if not len(col):
        return
    data, at = column_bytes(col)
    lo = 0
    while lo < len(col):
        hi = max(lo + 1, int(np.searchsorted(at, at[lo] + most, "right")) - 1)
        buf = data[at[lo] : at[hi]]
        if lower:
            buf = LOWER[buf]
        own = at[lo : hi + 1] - at[lo]
        isin = np.zeros(len(buf) + 2, bool)
        isin[1:-1] = inside[buf]
        edge = own[1:-1]
        begins = isin[1:-1] & ~isin[:-2]
        begins[edge[edge < len(buf)]] = isin[1:-1][edge[edge < len(buf)]]
        ends = isin[1:-1] & ~isin[2:]
        inner = edge[edge > 0] - 1
        ends[inner] = isin[1:-1][inner]
        start = np.flatnonzero(begins)
        yield Chunk(lo, hi, buf, own, start, np.flatnonzero(ends) + 1, np.searchsorted(start, own))
        lo = hi
    trim()


def window_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of every k consecutive entries of h (len(h) - k + 1 of them)."""
    n = len(h)
    if n < k:
        return np.zeros(0, np.uint64)
    pw, inv = powers(WORD_BASE, n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(h * pw[:n], out=total[1:])
    return mix((total[k:] - total[:-k]) * inv[: n - k + 1])


def windows(c: Chunk, k: int, h: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, text index in the chunk, word position) of every k-word window inside one text."""
    h = c.hashes() if h is None else h
    keys = window_hashes(h, k)
    if not len(keys):
        return keys, np.zeros(0, np.int64), np.zeros(0, np.int64)
    own = c.owners()
    ok = own[: len(keys)] == own[k - 1 :]
    own = own[: len(keys)][ok]
    return keys[ok], own, np.flatnonzero(ok) - c.first[own]


class Lookup:
    """Position of hashes in a small list of keys; most misses end at a table of key prefixes."""

    BITS = U(20)

    def __init__(self, keys: np.ndarray):
        self.order = np.argsort(keys, kind="stable")
        self.keys = keys[self.order]
        self.seen = np.zeros(1 << int(self.BITS), bool)
        self.seen[(keys >> (U(64) - self.BITS)).astype(np.int64)] = True

    def found(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(where in h, which key) of all hashes that are keys; of equal keys the first."""
        at = np.flatnonzero(self.seen[(h >> (U(64) - self.BITS)).astype(np.int64)])
        if not len(at) or not len(self.keys):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        spot = np.minimum(np.searchsorted(self.keys, h[at]), len(self.keys) - 1)
        ok = self.keys[spot] == h[at]
        return at[ok], self.order[spot[ok]]
