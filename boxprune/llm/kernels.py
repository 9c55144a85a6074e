"""Vectorised text kernels: words, lines and windows of a batch of texts as flat numpy arrays.

A batch is one byte buffer with text offsets. Words are maximal runs of bytes other than
space and 0x09-0x0D; every hash is a 64-bit polynomial over a random byte table, taken from prefix
sums modulo 2^64, then mixed. All functions work on whole texts.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_LIBC = ctypes.CDLL(None)
_RNG = np.random.Generator(np.random.PCG64(20240607))
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
_FOLDED = _BYTE.copy()
_FOLDED[65:91] = _BYTE[97:123]
_STEP = 0x9E3779B97F4A7C15 | 1
_BACK = pow(_STEP, -1, 2**64)
_LANES = _RNG.integers(1, 2**63, 64, dtype=np.uint64) * U(2) + U(1)

WHITE = np.zeros(256, bool)
WHITE[[32, 9, 10, 11, 12, 13]] = True

#: Text bytes worked on at once; a longer single text is taken alone.
SLICE_BYTES = 1_500_000

_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    """Powers of base; those of one slice are kept."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        steps = np.full(max(n, SLICE_BYTES + 1), base, np.uint64)
        steps[0] = 1
        have = np.multiply.accumulate(steps)
        _powers[base] = have[: SLICE_BYTES + 1].copy()
    return have[:n]


def release() -> None:
    """Give memory that a finished task no longer needs back to the system; workers live on for further tasks."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(_LIBC, "malloc_trim", None)
    if trim is not None:
        trim(0)


def mix(h: np.ndarray) -> np.ndarray:
    h = h.astype(np.uint64, copy=True)
    h ^= h >> U(30)
    h *= U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


class Texts:
    """Some consecutive texts of an Arrow string column; null counts as empty."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data, self.offsets, self.n = data, offsets, len(offsets) - 1

    def words(self, folded: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """start, end, text number and hash of each word."""
        data = self.data
        inner = ~WHITE[data]
        first, last = inner.copy(), inner.copy()
        first[1:] &= ~inner[:-1]
        last[:-1] &= ~inner[1:]
        cuts = self.offsets[1:-1]
        cuts = cuts[(cuts > 0) & (cuts < len(data))]
        first[cuts] |= inner[cuts]
        last[cuts - 1] |= inner[cuts - 1]
        start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
        of = np.searchsorted(self.offsets, start, side="right") - 1
        return start, end, of, self.span_hash(start, end, folded)

    def span_hash(self, start: np.ndarray, end: np.ndarray, folded: bool = False) -> np.ndarray:
        """Hashes of spans that follow one another; a long text is taken by runs of spans, which gives the same hashes."""
        if len(self.data) > 2 * SLICE_BYTES and len(start) > 1:
            out, i = np.empty(len(start), np.uint64), 0
            while i < len(start):
                j = max(i + 1, int(np.searchsorted(end, start[i] + SLICE_BYTES, side="right")))
                part = Texts(self.data[start[i] : end[j - 1]], np.array([0, end[j - 1] - start[i]]))
                out[i:j] = part._hash(start[i:j] - start[i], end[i:j] - start[i], folded)
                i = j
            return out
        return self._hash(start, end, folded)

    def _hash(self, start: np.ndarray, end: np.ndarray, folded: bool) -> np.ndarray:
        sums = np.zeros(len(self.data) + 1, np.uint64)
        np.cumsum((_FOLDED if folded else _BYTE)[self.data] * _power(_STEP, len(self.data)), out=sums[1:])
        back = _power(_BACK, len(self.data) + 1)
        return mix((sums[end] - sums[start]) * back[start] + (end - start).astype(np.uint64))

    def count(self, flags: np.ndarray) -> np.ndarray:
        """Number of set bytes of each text."""
        if len(flags) > 2 * SLICE_BYTES:  # few texts
            return np.array([np.count_nonzero(flags[a:b]) for a, b in zip(self.offsets[:-1], self.offsets[1:], strict=True)], np.int64)
        sums = np.zeros(len(self.data) + 1, np.int64)
        np.cumsum(flags, out=sums[1:])
        return sums[self.offsets[1:]] - sums[self.offsets[:-1]]


def slices(column: pa.Array) -> Iterator[tuple[int, Texts]]:
    """Cut a string column into runs of texts of about SLICE_BYTES; gives each run's first row."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_utf8())
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if not n:
        return
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + SLICE_BYTES, side="right")) - 1)
        to = min(to, n)
        yield at, Texts(raw[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
        at = to


def windows(of: np.ndarray, hashes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """First word number and hash of each run of k words inside one text."""
    n = len(of) - k + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    at = np.flatnonzero(of[:n] == of[k - 1 :])
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h += hashes[j : j + n] * _LANES[j]
    return at, mix(h[at] + U(k))


def shingle_sets(texts: Texts, k: int, folded: bool) -> tuple[np.ndarray, np.ndarray]:
    """Text number and hash of each distinct k-word shingle, sorted by both; shorter texts give
    their whole word sequence as one shingle, texts without words give none."""
    _, _, of, h = texts.words(folded)
    at, sh = windows(of, h, k)
    own = of[at]
    counts = np.bincount(of, minlength=texts.n)
    firsts = np.concatenate([[0], np.cumsum(counts)])[:-1]
    for m in range(1, k):
        short = np.flatnonzero(counts == m)
        if len(short):
            s = np.zeros(len(short), np.uint64)
            for j in range(m):
                s += h[firsts[short] + j] * _LANES[j]
            own, sh = np.concatenate([own, short]), np.concatenate([sh, mix(s + U(m))])
    order = np.lexsort((sh, own))
    own, sh = own[order], sh[order]
    keep = np.ones(len(own), bool)
    keep[1:] = (own[1:] != own[:-1]) | (sh[1:] != sh[:-1])
    return own[keep], sh[keep]


def as_long(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)
