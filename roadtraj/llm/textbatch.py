"""Vectorised words and hashes of Arrow text batches.

Words are the maximal runs of bytes other than space and 0x09-0x0D. All hashing
is a polynomial over 64-bit words, taken from prefix sums, so a batch costs a
few array passes whatever the number of words.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SPACES = b" \t\n\v\f\r"
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[list(SPACES)] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_BLOCK = 1 << 20
_BASE = 0x9E3779B97F4A7C15 | 5
_MASK = (1 << 64) - 1


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the 64 output bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


BYTE_VALUES = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_TABLES: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n; the base is odd."""
    have = _TABLES.get(base)
    if have is None or len(have[0]) < n:
        size = max(n, 1024)
        up, down = np.full(size, base, np.uint64), np.full(size, pow(base, -1, 1 << 64), np.uint64)
        up[0] = down[0] = 1
        have = _TABLES[base] = (np.multiply.accumulate(up), np.multiply.accumulate(down))
    return have[0][:n], have[1][:n]


@dataclass
class Words:
    """Words of a batch: bytes ``data``, word bounds, first word of each document (one more at the end)."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def document(self) -> np.ndarray:
        """The document of each word."""
        return np.repeat(np.arange(len(self.first) - 1), self.counts())

    def position(self) -> np.ndarray:
        """The index of each word in its document."""
        return np.arange(len(self.start)) - np.repeat(self.first[:-1], self.counts())


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column and the offsets of its rows; a null counts as an empty text."""
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) if len(column) else np.zeros(1, np.int64)
    body = column.buffers()[2] if len(column) else None
    data = np.frombuffer(body, np.uint8)[offsets[0] : offsets[-1]] if body is not None and body.size else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def words_of(column: pa.Array) -> Words:
    data, offsets = text_bytes(column)
    inside = ~IS_SPACE[data]
    before, after = np.zeros(len(data), bool), np.zeros(len(data), bool)
    before[1:], after[:-1] = inside[:-1], inside[1:]
    edges = offsets[(offsets > 0) & (offsets < len(data))]
    before[edges] = False
    after[edges - 1] = False
    start = np.flatnonzero(inside & ~before)
    return Words(data, start, np.flatnonzero(inside & ~after) + 1, np.searchsorted(start, offsets))


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of data[start:end]; sums run over blocks, so memory follows the number of words."""
    at_start, at_end, total = np.zeros(len(start), np.uint64), np.zeros(len(end), np.uint64), 0
    up, down = powers(_BASE, min(_BLOCK, max(len(data), 1)))
    for lo in range(0, len(data), _BLOCK):
        part = BYTE_VALUES[data[lo : lo + _BLOCK]]
        part *= up[: len(part)]
        sums = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part, out=sums[1:])
        sums *= np.uint64(pow(_BASE, lo, 1 << 64))
        sums += np.uint64(total)
        for at, where in ((at_start, start), (at_end, end)):
            i, j = np.searchsorted(where, [lo, lo + len(part)], side="right") if where is end else np.searchsorted(where, [lo, lo + len(part)])
            at[i:j] = sums[where[i:j] - lo]
        total = int(sums[-1])
    scale = np.array([pow(_BASE, -b * _BLOCK, 1 << 64) for b in range(len(data) // _BLOCK + 1)], np.uint64)
    return mix64((at_end - at_start) * down[start % _BLOCK] * scale[start // _BLOCK] + (end - start).astype(np.uint64))


def run_hashes(values: np.ndarray, starts: np.ndarray, length: int, base: int = 0xD6E8FEB86659FD93) -> np.ndarray:
    """Hashes of values[s:s+length] for each start s; ``values`` are 64-bit hashes."""
    up, down = powers(base, len(values) + 1)
    sums = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * up[:-1], out=sums[1:])
    return mix64((sums[starts + length] - sums[starts]) * down[starts])


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Cut batches at rows so that each piece has about ``most`` bytes of text (a longer text stands alone)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        _, offsets = text_bytes(batch.column(column))
        lo = 0
        while lo < batch.num_rows:
            hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + most, side="right")) - 1)
            yield batch.slice(lo, hi - lo)
            lo = hi


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of the ranges start, start+1, ... of the given lengths."""
    total = int(lengths.sum())
    ends = np.cumsum(lengths)
    return np.arange(total) - np.repeat(ends - lengths, lengths) + np.repeat(starts, lengths)


def joined_words(words: Words, keep: np.ndarray | None = None) -> tuple[memoryview, np.ndarray]:
    """Kept words of each document joined by one space: all bytes, and each document's bounds in them."""
    start, end, document = words.start, words.end, words.document()
    if keep is not None:
        start, end, document = start[keep], end[keep], document[keep]
    lengths = end - start + 1
    out = words.data[np.minimum(ragged(start, lengths), max(len(words.data) - 1, 0))] if len(start) else np.zeros(0, np.uint8)
    ends = np.cumsum(lengths)
    if len(start):
        out[ends - 1] = 32
    n = len(words.first) - 1
    per = np.bincount(document, minlength=n)
    last = np.concatenate([[0], np.cumsum(per)])
    stops = np.concatenate([[0], ends])
    bounds = np.stack([stops[last[:-1]], stops[last[1:]] - (per > 0)], axis=1)
    return memoryview(np.ascontiguousarray(out)), bounds
