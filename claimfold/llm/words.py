"""Vectorised word segmentation and hashing over Arrow text columns.

A *word* is a maximal run of bytes outside ASCII space, tab, line feed, vertical
tab, form feed and carriage return, i.e. the class ``[^\\x20\\x09-\\x0D]+``.  As
those six are single-byte characters in UTF-8, cutting bytes equals cutting code
points.  A null text counts as an empty one.  Nothing here loops over words in
Python: a batch is one byte array, and hashes come from wrapping prefix sums.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; a longer single text still goes in one piece.
CHUNK_BYTES = 1 << 20

_MASK = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers (shift, xor, odd multipliers)."""
    x = np.array(x, dtype=np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """``base ** 0 .. base ** (n - 1)`` modulo 2**64, kept for the next call."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, 1 << 16), base & _MASK, dtype=np.uint64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        _powers[base] = have
    return have[:n]


def chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about `limit` bytes of text each, at least one row long."""
    sizes = np.asarray(pc.binary_length(column).fill_null(0))
    ends = np.cumsum(sizes)
    start = 0
    while start < len(sizes):
        floor = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, floor + limit, side="right")))
        yield start, stop
        start = stop


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All texts as one byte array with a blank between them, and each text's start.

    starts[i] .. starts[i + 1] - 1 is text i; its last byte is the added blank.
    """
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    sizes = np.diff(offsets)
    data = column.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    starts = np.zeros(len(sizes) + 1, dtype=np.int64)
    np.cumsum(sizes + 1, out=starts[1:])
    out = np.full(starts[-1], 0x20, dtype=np.uint8)
    keep = np.ones(starts[-1], dtype=bool)
    keep[starts[1:] - 1] = False
    out[keep] = raw
    return out, starts


class Words:
    """Words of a column: byte spans, owners and 64-bit hashes."""

    def __init__(self, column: pa.Array, lower: bool = False, separators: np.ndarray = _SPACE):
        self.raw, self.doc_start = text_bytes(column)
        self.bytes = _LOWER[self.raw] if lower else self.raw
        inside = np.zeros(len(self.bytes) + 1, dtype=bool)
        inside[1:] = ~separators[self.bytes]
        if len(self.doc_start) > 1:
            inside[self.doc_start[1:]] = False  # the added blank, whatever `separators` holds
        turn = np.flatnonzero(inside[1:] != inside[:-1])
        self.start, self.end = turn[0::2], turn[1::2]
        #: first[i] .. first[i + 1] - 1 are the words of text i.
        self.first = np.searchsorted(self.start, self.doc_start)
        self.n_docs = len(self.doc_start) - 1
        self.count = np.diff(self.first)

    def hashes(self) -> np.ndarray:
        """One well-mixed 64-bit hash for each word, equal for equal bytes."""
        return self.span_hashes(self.start, self.end)

    def span_hashes(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        n = len(self.bytes)
        if not hasattr(self, "_sums"):
            self._sums = np.zeros(n + 1, dtype=np.uint64)
            np.cumsum(_BYTE[self.bytes] * powers(_BASE, n), out=self._sums[1:])
        flat = (self._sums[end] - self._sums[start]) * powers(_INVERSE, n + 1)[start]
        return mix64(flat + (end - start).astype(np.uint64))

    def owner(self) -> np.ndarray:
        """The text each word belongs to."""
        return np.repeat(np.arange(self.n_docs), self.count)


def rolling(hashes: np.ndarray, width: int, seed: int = 1) -> np.ndarray:
    """Hash of the `width` hashes that start at each place; the last width - 1 places are left out."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = np.zeros(n, dtype=np.uint64)
    for i in range(width):
        out += hashes[i : i + n] * np.uint64(pow(_BASE ^ (seed * 2 << 8), i + seed, 1 << 64))
    return mix64(out)


def window_owner(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """First word and owner of every window of `width` words that stays inside its text."""
    per = np.maximum(words.count - width + 1, 0)
    owner = np.repeat(np.arange(words.n_docs), per)
    within = np.arange(per.sum()) - np.repeat(np.cumsum(per) - per, per)
    return words.first[:-1][owner] + within, owner
