"""Vectorised text primitives shared by the text operators.

Everything here works on one Arrow string column at a time and touches whole texts: a column is viewed as one UTF-8 byte
buffer plus offsets, words are found with byte masks, and word, shingle and n-gram identities are 64-bit hashes that are computed for
all words of a block at once. A span's hash is a sum of one pseudo-random number for each (place, value), so that no text,
however regular, makes two spans meet more often than chance does (a polynomial modulo 2^64 would: Thue-Morse words).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

_BASE = np.uint64(0x9E3779B97F4A7C15)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE_CODE = np.random.default_rng(20240229).integers(0, 1 << 64, 256, dtype=np.uint64)
_PLACES = 1 << 12


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (the SplitMix64 output function)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_PLACE_CODE = mix64(np.arange(1, _PLACES + 1, dtype=np.uint64) * _BASE)


def _places(at: np.ndarray) -> np.ndarray:
    """The code of each place in a span: from a table, computed only for spans longer than it."""
    if int(at.max()) >= _PLACES:
        return mix64((at + 1).astype(np.uint64) * _BASE)
    return _PLACE_CODE[at]


def utf8_view(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; nulls count as empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    if len(column) == 0 or data is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(column) + 1, dtype=np.int64)
    ends = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, dtype=np.uint8)[ends[0] : ends[-1]], ends - ends[0]


def blocks(column: pa.Array, limit: int = 1 << 21) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of whole texts of about `limit` bytes (one longer text makes a block): first row, end row, bytes, offsets."""
    data, offsets = utf8_view(column)
    first, n = 0, len(offsets) - 1
    while first < n:
        last = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        last = min(n, max(first + 1, last))
        yield first, last, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
        first = last


@dataclass
class Words:
    """Words of a block: byte start, byte end, row in the block and hash of each; row_at: first word of each row, then the end."""

    start: np.ndarray
    end: np.ndarray
    row_at: np.ndarray
    code: np.ndarray

    @property
    def row(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.row_at) - 1), np.diff(self.row_at))


def lowered(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def spans_of(member: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of `member` bytes that do not cross a text's end: starts, ends, first run of each text (then the end)."""
    n = len(member)
    before = np.zeros(n, dtype=bool)
    after = np.zeros(n, dtype=bool)
    if n:
        before[1:] = member[:-1]
        after[:-1] = member[1:]
        inner = offsets[(offsets > 0) & (offsets < n)]
        before[inner] = False
        after[inner - 1] = False
    start = np.flatnonzero(member & ~before)
    end = np.flatnonzero(member & ~after) + 1
    return start, end, np.searchsorted(start, offsets)


def span_sums(values: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of spans of values (random unsigned 64-bit codes), independent of where the spans stand. Spans do not overlap."""
    if not len(start):
        return np.zeros(0, dtype=np.uint64)
    low, high = int(start[0]), int(end[-1])
    # values between spans get places as well; no difference of sums holds them
    place = np.arange(low, high, dtype=np.int32) - np.repeat(start.astype(np.int32), np.diff(np.append(start, high)))
    x = _places(place)
    x ^= values[low:high]
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0x94D049BB133111EB)
    sums = np.zeros(len(x) + 1, dtype=np.uint64)
    np.cumsum(x, out=sums[1:])
    return mix64(sums[end - low] - sums[start - low] + (end - start).astype(np.uint64))


def span_codes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans, independent of where the spans stand."""
    return span_sums(_BYTE_CODE[data], start, end)


def words_of(data: np.ndarray, offsets: np.ndarray) -> Words:
    """Maximal runs of bytes other than space and 0x09-0x0D, hashed with A-Z in lower case."""
    start, end, row_at = spans_of(~_SPACE[data], offsets)
    return Words(start, end, row_at, span_codes(lowered(data), start, end))


def shingle_sets(words: Words, width: int) -> list[np.ndarray]:
    """For each row the sorted distinct hashes of its `width`-word shingles; a shorter row is one shingle, an empty row none."""
    code, n = words.code, len(words.code)
    if n >= width:
        rolled = np.zeros(n - width + 1, dtype=np.uint64)
        for k in range(width):
            rolled = rolled * _BASE + code[k : n - width + 1 + k]
        rolled = mix64(rolled + np.uint64(width))
    out = []
    for a, b in zip(words.row_at[:-1].tolist(), words.row_at[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(rolled[a : b - width + 1]))
        elif b > a:
            whole = np.zeros(1, dtype=np.uint64)
            for k in range(a, b):
                whole = whole * _BASE + code[k]
            out.append(mix64(whole + np.uint64(b - a)))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out
