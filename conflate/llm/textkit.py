"""Vectorised text handling for Arrow batches: words, word hashes and word-window hashes.

All functions work on whole texts.  A batch is cut into pieces of whole documents of about ``CHUNK_BYTES``
so that the arrays beside it stay small; one document longer than that is a piece of its own.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 18

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15 | 1)
_INV = _U(pow(int(_BASE), -1, 1 << 64))
_STEP = _U(0xD1342543DE82EF95)
_STEP_INV = _U(pow(int(_STEP), -1, 1 << 64))

#: Bytes of words split at blanks only (space, tab, line feed, vertical tab, form feed, carriage return).
BLANK_SPLIT = np.ones(256, bool)
BLANK_SPLIT[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False

#: Bytes of words made of letters and digits; every byte of a non-ASCII character counts as a letter.
ALNUM = np.zeros(256, bool)
ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True

_powers: dict[str, np.ndarray] = {}
_libc = ctypes.CDLL(None) if hasattr(ctypes.CDLL(None), "malloc_trim") else None


def _power(kind: str, base: np.uint64, n: int) -> np.ndarray:
    have = _powers.get(kind)
    if have is None or len(have) < n:
        size = max(n, CHUNK_BYTES + 4096)
        have = np.full(size, base, _U)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if size <= 4 * CHUNK_BYTES:
            _powers[kind] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Scramble 64-bit values so that any bits of them can be used alone."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def _give_back() -> None:
    """Hand free memory to the system: idle workers of earlier stages share the executor with the next."""
    pa.default_memory_pool().release_unused()
    if _libc is not None:
        _libc.malloc_trim(0)


def pieces(col: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes of text each; free memory goes back to the system after the last."""
    if len(col) == 0:
        return
    ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(col), 0), dtype=np.int64))
    lo = 0
    while lo < len(col):
        base = ends[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, base + limit, "right")))
        yield lo, hi
        lo = hi
    _give_back()


def raw(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in a row, and offsets of length n + 1; null counts as empty."""
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    col = pc.fill_null(col, "").cast(pa.large_string())
    _, off, data = col.buffers()
    offsets = np.frombuffer(off, np.int64, len(col) + 1, col.offset * 8)
    if data is None or offsets[-1] == offsets[0]:
        return np.zeros(0, np.uint8), offsets - offsets[0]
    return np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]], offsets - offsets[0]


class Words:
    """The words of the texts of one piece: byte ranges, document index and 64-bit hash of each."""

    def __init__(self, col: pa.Array, inside: np.ndarray = BLANK_SPLIT, fold: bool = False):
        if fold:
            col = pc.utf8_lower(pc.fill_null(col, "").cast(pa.large_string()))
        self.data, self.offsets = raw(col)
        n = len(self.data)
        self.n_docs = len(self.offsets) - 1
        is_word = inside[self.data]
        left = np.zeros(n + 1, bool)
        left[1:] = is_word
        left[self.offsets] = False
        right = np.zeros(n + 1, bool)
        right[:n] = is_word
        right[self.offsets] = False
        self.start = np.flatnonzero(is_word & ~left[:n])
        self.end = np.flatnonzero(is_word & ~right[1:]) + 1
        self.doc = np.searchsorted(self.offsets, self.start, "right") - 1
        self.first = np.searchsorted(self.start, self.offsets)  # of each document, and the end
        total = np.zeros(n + 1, _U)
        np.cumsum((self.data.astype(_U) + _U(1)) * _power("byte", _BASE, n), out=total[1:])
        inv = _power("byte_inv", _INV, n + 1)
        self.hash = mix((total[self.end] - total[self.start]) * inv[self.start])

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def windows(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """First word and hash of every run of ``size`` words within one document."""
        n = len(self.hash)
        if n < size:
            return np.zeros(0, np.int64), np.zeros(0, _U)
        total = np.zeros(n + 1, _U)
        np.cumsum(self.hash * _power("word", _STEP, n), out=total[1:])
        at = np.flatnonzero(self.doc[: n - size + 1] == self.doc[size - 1 :])
        return at, mix((total[at + size] - total[at]) * _power("word_inv", _STEP_INV, n)[at] + _U(size))

    def shingles(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Document and hash of every run of ``size`` words; a shorter text gives one run of all its words."""
        at, h = self.windows(size)
        d = self.doc[at]
        short = np.flatnonzero((self.counts() < size) & (self.counts() > 0))
        if len(short):
            whole = np.array([int(mix(np.bitwise_xor.reduce(mix(self.hash[a:b] + np.arange(b - a, dtype=_U)), keepdims=True))[0]) for a, b in zip(self.first[short], self.first[short + 1])], _U)
            d, h = np.concatenate([d, short]), np.concatenate([h, whole])
            order = np.argsort(d, kind="stable")
            d, h = d[order], h[order]
        return d, h

    def text(self, i: int, j: int) -> list[bytes]:
        """Words i to j - 1 as bytes."""
        buf = self.data.tobytes() if not hasattr(self, "_bytes") else self._bytes
        self._bytes = buf
        return [buf[a:b] for a, b in zip(self.start[i:j], self.end[i:j])]


def signed(x: np.ndarray) -> np.ndarray:
    """Hashes as Spark's long."""
    return x.view(np.int64)


def ranges(lengths: np.ndarray) -> np.ndarray:
    """0..l-1 for each length l, one after the other."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - lengths, lengths)
