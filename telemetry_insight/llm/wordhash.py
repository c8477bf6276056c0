"""Vectorised words and rolling hashes over Arrow text columns.

Words are runs of anything but ASCII white space. A word's hash is a polynomial
over its bytes modulo 2**64, mixed; a window's hash is a Rabin-Karp polynomial
over word hashes, taken from prefix sums. Two different windows share a 64-bit
hash with a chance of about 2**-64.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa

BYTE_BASE = np.uint64(0x9E3779B97F4A7C55)
WORD_BASE = np.uint64(0xD1342543DE82EF95)
_SLICE = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads every input bit."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


@cache
def _powers(base: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    def run(x: int) -> np.ndarray:
        out = np.full(size, x, np.uint64)
        out[0] = 1
        return np.multiply.accumulate(out)

    return run(base), run(pow(base, -1, 1 << 64))


def powers(base: np.uint64, size: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i below size at least."""
    return _powers(int(base), 1 << max(12, int(size).bit_length()))


_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_GAP = np.zeros(256, bool)
_GAP[[32, 9, 10, 11, 12, 13]] = True
#: Also ASCII punctuation, for words without it.
_PUNCTUATED = _GAP.copy()
_PUNCTUATED[[i for i in range(33, 127) if not chr(i).isalnum()]] = True


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column; null counts as empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.chunk(0) if texts.num_chunks else pa.array([], pa.string())
    texts = texts.cast(pa.large_binary() if not pa.types.is_string(texts.type) else pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("" if pa.types.is_large_string(texts.type) else b"")
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def _piece(raw: np.ndarray, offsets: np.ndarray, lower: bool, punctuation: bool) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of some rows and the number of words of each."""
    rows = len(offsets) - 1
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(rows, np.int64)
    gap = (_PUNCTUATED if punctuation else _GAP)[raw]
    first = ~gap
    edge = np.zeros(len(raw) + 1, bool)
    edge[offsets[:-1]] = True
    begins = first.copy()
    begins[1:] &= gap[:-1] | edge[1:-1]
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(rows, np.int64)
    up, down = powers(BYTE_BASE, len(raw))
    terms = (_FOLD[raw] if lower else raw).astype(np.uint64)
    terms += np.uint64(1)
    terms *= up[: len(raw)]
    terms[gap] = 0
    hashes = np.add.reduceat(terms, starts) * down[starts]
    counts = np.diff(np.searchsorted(starts, offsets))
    return mix(hashes), counts


def word_hashes(texts: pa.Array, lower: bool = False, punctuation: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words in row order, and the row pointer (rows + 1 entries) into them. punctuation: ASCII punctuation parts words too."""
    raw, offsets = buffers(texts)
    rows = len(offsets) - 1
    found, counts, at = [], [], 0
    while at < rows:  # slices of about a MB keep the 8-byte arrays in cache
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + _SLICE, "right")) - 1)
        to = min(to, rows)
        h, n = _piece(raw[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at], lower, punctuation)
        found.append(h)
        counts.append(n)
        at = to
    ends = np.zeros(rows + 1, np.int64)
    if rows:
        np.cumsum(np.concatenate(counts), out=ends[1:])
    return (np.concatenate(found) if found else np.zeros(0, np.uint64)), ends


def windows(words: np.ndarray, ends: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rolling hashes of `width` words within rows: hashes, index of the first word, row pointer into the hashes."""
    counts = np.maximum(np.diff(ends) - width + 1, 0)
    ptr = np.zeros(len(ends), np.int64)
    np.cumsum(counts, out=ptr[1:])
    total = int(ptr[-1])
    if not total:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), ptr
    index = np.arange(total, dtype=np.int64) + np.repeat(ends[:-1] - ptr[:-1], counts)
    up, down = powers(WORD_BASE, len(words) + 1)
    sums = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * up[: len(words)], out=sums[1:])
    return mix((sums[index + width] - sums[index]) * down[index]), index, ptr


def slices(batch: pa.RecordBatch, column: str = "text", size: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """A batch in slices of about `size` bytes of a text column, one row at least: the 8-byte arrays over its words stay small."""
    texts = batch.column(column)
    offsets = np.frombuffer(texts.buffers()[1], np.int64 if pa.types.is_large_string(texts.type) else np.int32)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    at = 0
    while at < len(texts):
        to = max(at + 1, int(np.searchsorted(offsets, int(offsets[at]) + size, "right")) - 1)
        to = min(to, len(texts))
        yield batch.slice(at, to - at)
        at = to
