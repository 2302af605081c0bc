"""Vectorised words and 64-bit hashes over Arrow string columns.

A column is handled as one byte buffer with offsets, in chunks of a bounded
number of bytes, so the cost per word is a few array operations and memory does
not depend on the batch.  All arithmetic is modulo 2**64.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: White space of the word and line rules: space, and tab to carriage return.
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_BASE = 0x9E3779B97F4A7C15 | 1
_WINDOW_BASES = (0xD6E8FEB86659FD93, 0xA0761D6478BD642F | 1)
_BYTE_CODES = np.random.default_rng(20240501).integers(1, 2**63, 256, dtype=np.int64).astype(np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser: spreads every input bit over the word."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=12)
def _powers_up_to(base: int, bits: int) -> np.ndarray:
    steps = np.full(1 << bits, base, dtype=np.uint64)
    steps[0] = 1
    return np.multiply.accumulate(steps)


def powers(base: int, n: int) -> np.ndarray:
    """base**0 … base**(n-1); kept for sizes up to 2**22."""
    bits = max(10, int(n).bit_length())
    if bits > 22:
        return _powers_up_to.__wrapped__(base, bits)[:n]
    return _powers_up_to(base, bits)[:n]


def inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = pc.fill_null(col, "")
    if not pa.types.is_large_string(col.type):
        col = col.cast(pa.large_string())
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    buffers = col.buffers()
    offsets = np.frombuffer(buffers[1], dtype=np.int64)[col.offset : col.offset + len(col) + 1]
    data = np.frombuffer(buffers[2], dtype=np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(col: pa.Array, limit: int = 1 << 18) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of pieces of about ``limit`` bytes; a longer text is a piece of its own."""
    data, offsets = column_bytes(col)
    n, at = len(offsets) - 1, 0
    while at < n:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield at, end, data[offsets[at] : offsets[end]], offsets[at : end + 1] - offsets[at]
        at = end


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, first): byte spans of all words, and for row r its words are first[r] … first[r+1]-1."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    word = ~SPACE[data]
    row = np.zeros(len(data) + 1, dtype=bool)
    row[offsets] = True
    row[-1] = True
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1] | row[1:-1]
    last[:-1] &= ~word[1:] | row[1:-1]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return start, end, np.searchsorted(start, offsets).astype(np.int64)


def span_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each span; equal bytes have equal hashes wherever they stand."""
    total = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum(_BYTE_CODES[data] * powers(_BASE, len(data)), out=total[1:])
    shift = powers(inverse(_BASE), len(data) + 1)
    return mix((total[end] - total[start]) * shift[start] + (end - start).astype(np.uint64))


def run_hashes(words: np.ndarray, start: np.ndarray, end: np.ndarray, lane: int = 0) -> np.ndarray:
    """A 64-bit hash of each run words[start:end] of word hashes; ``lane`` 0 or 1 chooses independent functions."""
    base = _WINDOW_BASES[lane]
    total = np.zeros(len(words) + 1, dtype=np.uint64)
    np.cumsum(words * powers(base, len(words)), out=total[1:])
    shift = powers(inverse(base), len(words) + 1)
    return mix((total[end] - total[start]) * shift[start] + (end - start).astype(np.uint64))


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
