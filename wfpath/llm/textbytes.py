"""Vectorised work on batches of texts: words, hashes of words and of windows.

A word is a maximal run of bytes outside \\x20 and \\x09-\\x0D.  Those bytes are ASCII, so
segmenting UTF-8 bytes gives the same words as segmenting code points.  Texts are handled in
slices of about ``SLICE`` bytes, so memory follows the slice (or the longest text), not the batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE = 1 << 20
PIECE = 1 << 19
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
U64 = np.uint64


def _inverse(odd: int) -> int:
    return pow(odd, -1, 1 << 64)


class Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int) -> None:
        self.base, self.up, self.down = base, np.ones(1, U64), np.ones(1, U64)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 1 << 16)
            for name, b in (("up", self.base), ("down", _inverse(self.base))):
                steps = np.full(size, b, U64)
                steps[0] = 1
                setattr(self, name, np.multiply.accumulate(steps))
        return self.up[:n], self.down[:n]


_BYTES, _WORDS, _WORDS2 = Powers(0x9E3779B97F4A7C15), Powers(0xC2B2AE3D27D4EB4F), Powers(0xD6E8FEB86659FD93)
_TABLE = np.random.default_rng(20).integers(1, 1 << 63, 256, dtype=np.int64).astype(U64) | U64(1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def texts_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and the offsets of its rows; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = column.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Row ranges [a, b) of about ``most`` bytes each; a longer text stands alone."""
    a, n = 0, len(offsets) - 1
    while a < n:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + most, "right")) - 1)
        yield a, b
        a = b


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each text the index of its first word (one more at the end)."""
    n = len(data)
    if n == 0:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    inside = ~_SPACE[data]
    cut = np.zeros(n + 1, bool)
    cut[offsets[offsets < n]] = True
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | cut[1:n]
    ends = inside.copy()
    ends[:-1] &= ~inside[1:] | cut[1:n]
    starts = np.flatnonzero(begins)
    return starts, np.flatnonzero(ends) + 1, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
    """A 64-bit hash of each word, the same wherever it stands."""
    out = np.empty(len(starts), U64)
    at = 0
    while at < len(starts):
        origin = int(starts[at])
        to = max(at + 1, int(np.searchsorted(ends, origin + PIECE, "right")))
        part = data[origin : int(ends[to - 1])]
        up, down = _BYTES.to(len(part) + 1)
        sums = np.zeros(len(part) + 1, U64)
        np.cumsum(_TABLE[_LOWER[part] if lower else part] * up[:-1], out=sums[1:])
        s, e = starts[at:to] - origin, ends[at:to] - origin
        out[at:to] = mix((sums[e] - sums[s]) * down[s] + (e - s).astype(U64))
        at = to
    return out


def rolling(hashes: np.ndarray, size: int, second: bool = False) -> np.ndarray:
    """Hashes of all windows of ``size`` neighbours, also of those that cross from one text into the next."""
    n = len(hashes)
    if n < size:
        return np.zeros(0, U64)
    up, down = (_WORDS2 if second else _WORDS).to(n + 1)
    sums = np.zeros(n + 1, U64)
    np.cumsum(hashes * up[:n], out=sums[1:])
    return mix((sums[size:] - sums[:-size]) * down[: n - size + 1])


def spans(hashes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of the ranges [start, end) of a sequence of hashes."""
    up, down = _WORDS2.to(len(hashes) + 1)
    sums = np.zeros(len(hashes) + 1, U64)
    np.cumsum(hashes * up[: len(hashes)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(U64))


def inside(first: np.ndarray, size: int) -> np.ndarray:
    """The starts from which ``size`` neighbours lie within one text; ``first`` holds the texts' bounds."""
    counts = np.maximum(np.diff(first) - size + 1, 0)
    ends = np.cumsum(counts)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(first[:-1] - (ends - counts), counts)


def windows(hashes: np.ndarray, first: np.ndarray, size: int, second: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all windows of ``size`` words that lie within one text, and the index of each one's first word."""
    at = inside(first, size)
    return rolling(hashes, size, second)[at], at


def runs_of_minima(grams: np.ndarray, at: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Neighbouring starts (of ``at``) whose windows of ``width`` grams have the same minimum: value, first start, number.

    Equal windows have equal minima, so windows that are equal are in runs of the same value.
    """
    if not len(at):
        return np.zeros(0, U64), at, at
    low = sliding_min(grams, width)[at]
    new = np.flatnonzero(np.r_[True, (low[1:] != low[:-1]) | (np.diff(at) != 1)])
    return low[new], at[new], np.diff(np.r_[new, len(at)])


def byte_grams(data: np.ndarray, size: int) -> np.ndarray:
    """Hashes of all ``size``-byte strings of ``data``, in slices so that the powers stay bounded."""
    n = len(data) - size + 1
    if n <= 0:
        return np.zeros(0, U64)
    out = np.empty(n, U64)
    for a in range(0, n, PIECE):
        b = min(n, a + PIECE)
        part = data[a : b + size - 1]
        up, down = _BYTES.to(len(part) + 1)
        sums = np.zeros(len(part) + 1, U64)
        np.cumsum(_TABLE[part] * up[:-1], out=sums[1:])
        out[a:b] = mix((sums[size:] - sums[:-size]) * down[: b - a])
    return out


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """The minimum of each window of ``width`` neighbours."""
    n = len(x) - width + 1
    if n <= 0:
        return x[:0]
    padded = np.full(-(-len(x) // width) * width, np.iinfo(x.dtype).max, x.dtype)
    padded[: len(x)] = x
    rows = padded.reshape(-1, width)
    before = np.minimum.accumulate(rows, axis=1).ravel()
    after = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(after[:n], before[width - 1 : width - 1 + n])


def merged(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of intervals as maximal disjoint intervals; touching ones join."""
    if len(starts) == 0:
        return starts, ends
    order = np.argsort(starts, kind="stable")
    s, e = starts[order], np.maximum.accumulate(ends[order])
    new = np.flatnonzero(np.r_[True, s[1:] > e[:-1]])
    return s[new], e[np.r_[new[1:] - 1, len(s) - 1]]
