"""Words and word shingles of whole texts as 64-bit hashes, computed over the bytes of an Arrow column.

A word is a run of bytes other than 0x20 and 0x09-0x0D, with A-Z lower-cased. Word hashes are differences of one
prefix sum of a polynomial in the bytes, so that the cost per byte does not depend on word or document lengths.
Equal words always have equal hashes. Different ones collide with a chance of about 2**-64 for a pair.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from . import workers

# Odd 64-bit multipliers of the polynomial and of the mixing steps.
BASE = 0x9E3779B97F4A7C15
MIX_1 = 0xBF58476D1CE4E5B9
MIX_2 = 0x94D049BB133111EB

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_CHUNK = 512 << 10
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit values; a bijection."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(MIX_1)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(MIX_2)
    return x ^ (x >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, up to n."""
    if len(_powers[0]) < n + 1:
        for k, b in enumerate((BASE, pow(BASE, -1, 1 << 64))):
            steps = np.full(n + 1, b, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a string column and the n+1 offsets of its rows; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64 if wide else np.int32, len(column) + 1 + column.offset)[column.offset :].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data, offsets


def slices(batches: Iterator[pa.RecordBatch], rows: int = 2000, size: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """:func:`workers.slices` of a task that keeps no tables."""
    workers.begin("words")
    return workers.slices(batches, rows, size)


def word_chunks(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first row, end row, word hashes, row of each word) for runs of whole rows of about half a megabyte."""
    data, offsets = text_buffers(column)
    first, n = 0, len(offsets) - 1
    while first < n:
        end = max(first + 1, int(np.searchsorted(offsets, offsets[first] + _CHUNK, "right")) - 1)
        own = offsets[first : end + 1] - offsets[first]
        low = _LOWER[data[offsets[first] : offsets[end]]]
        size = len(low)
        if size == 0:
            yield first, end, np.zeros(0, np.uint64), np.zeros(0, np.int64)
            first = end
            continue
        solid = ~_SPACE[low]
        edge = np.zeros(size + 1, bool)  # a row begins here
        edge[own] = True
        before = np.empty(size, bool)
        before[0], before[1:] = False, solid[:-1]
        after = np.empty(size, bool)
        after[-1], after[:-1] = False, solid[1:]
        starts = np.flatnonzero(solid & (~before | edge[:-1]))
        ends = np.flatnonzero(solid & (~after | edge[1:])) + 1
        power, inverse = _power_tables(size)
        total = np.zeros(size + 1, np.uint64)
        np.cumsum((low.astype(np.uint64) + np.uint64(1)) * power[:size], out=total[1:])
        value = (total[ends] - total[starts]) * inverse[starts]
        rows = np.searchsorted(own, starts, "right") - 1
        yield first, end, mix(value ^ ((ends - starts).astype(np.uint64) << np.uint64(40))), rows + first
        first = end


def word_counts(column: pa.Array) -> np.ndarray:
    """Number of words of each row."""
    out = np.zeros(len(column), np.int64)
    for first, end, _, rows in word_chunks(column):
        out[first:end] = np.bincount(rows - first, minlength=end - first)
    return out


def distinct_words(column: pa.Array) -> Iterator[np.ndarray]:
    """Sorted distinct word hashes of each row, in row order."""
    for first, end, words, rows in word_chunks(column):
        cuts = np.searchsorted(rows, np.arange(first, end + 1))
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            yield np.unique(words[a:b])


def _combine(words: np.ndarray, width: int, count: int) -> np.ndarray:
    out = np.full(count, width * 0x51_7C_C1_B7, np.uint64)
    for k in range(width):
        out = mix(out * np.uint64(BASE) + words[k : k + count])
    return out


def shingle_sets(column: pa.Array, width: int = 5) -> Iterator[np.ndarray]:
    """Sorted distinct hashes of the word shingles of each row, in row order.

    A row with fewer than ``width`` words has its whole sequence as one shingle; without words its set is empty.
    """
    for first, end, words, rows in word_chunks(column):
        cuts = np.searchsorted(rows, np.arange(first, end + 1))
        whole = _combine(words, width, len(words) - width + 1) if len(words) >= width else np.zeros(0, np.uint64)
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            if b - a >= width:
                yield np.unique(whole[a : b - width + 1])
            elif b > a:
                yield _combine(words[a:b], b - a, 1)
            else:
                yield np.zeros(0, np.uint64)
