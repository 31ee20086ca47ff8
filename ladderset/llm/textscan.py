"""Vectorised text kernels shared by the corpus operators.

Everything here works on whole Arrow batches: a string column is viewed as one byte buffer plus
offsets, and words, lines and shingles are found, hashed and counted with numpy over that buffer.
A word is a maximal run of bytes that are not ASCII white space (``[^\\x20\\x09-\\x0D]+``); since
UTF-8 never uses those bytes inside a longer character, bytes and code points agree on it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_U = np.uint64
_BYTE_CODES = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) | _U(1)
_STEP = _U(0x9E3779B97F4A7C15)


def _powers(n: int) -> np.ndarray:
    out = np.empty(n, np.uint64)
    out[0] = 1
    out[1:] = _U(6364136223846793005)
    return np.multiply.accumulate(out)


_POWER = _powers(1 << 12)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit values (the splitmix finaliser)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> _U(30)
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def buffer_of(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string or binary column; null rows are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):  # pyarrow keeps a chunked array when there are no rows
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if column.null_count:
        column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    column = column.cast(pa.large_binary())
    if not len(column):
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.empty(0, np.uint8)
    return buf, off - off[0]


def slices(off: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Row ranges of at most `most` bytes each (a longer single row makes a range of its own)."""
    lo, rows = 0, len(off) - 1
    while lo < rows:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + most, "right")) - 1)
        yield lo, hi
        lo = hi


@dataclass
class Words:
    """Words of a batch: byte ranges [start, end) and the row of each; `first` has the index of each row's first word."""

    start: np.ndarray
    end: np.ndarray
    row: np.ndarray
    first: np.ndarray


def words_of(buf: np.ndarray, off: np.ndarray) -> Words:
    rows = len(off) - 1
    if not len(buf):
        e = np.empty(0, np.int64)
        return Words(e, e, e, np.zeros(rows + 1, np.int64))
    black = ~SPACE[buf]
    edge = np.zeros(len(buf) + 1, bool)
    edge[off] = True
    opens = black.copy()
    opens[1:] &= ~black[:-1] | edge[1:-1]
    closes = black
    closes[:-1] &= ~black[1:] | edge[1:-1]
    start, end = np.flatnonzero(opens), np.flatnonzero(closes) + 1
    first = np.searchsorted(start, off)
    row = np.repeat(np.arange(rows), np.diff(first))
    return Words(start, end, row, first)


def range_hash(buf: np.ndarray, start: np.ndarray, end: np.ndarray, step: int = 1 << 20) -> np.ndarray:
    """64-bit hash of each byte range (ranges ascend and do not overlap; empty ones hash to 0)."""
    global _POWER
    out = np.zeros(len(start), np.uint64)
    some = np.flatnonzero(end > start)
    if not len(some):
        return out
    s, e = start[some].astype(np.int64), end[some].astype(np.int64)
    length = e - s
    if (top := int(length.max())) > len(_POWER):
        _POWER = _powers(1 << top.bit_length())
    got = np.empty(len(s), np.uint64)
    total = np.concatenate([[0], np.cumsum(length)])
    lo = 0
    while lo < len(s):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + step, "right")) - 1)
        n, base = length[lo:hi], total[lo:hi] - total[lo]
        inside = np.arange(total[hi] - total[lo]) - np.repeat(base, n)
        at = inside + np.repeat(s[lo:hi], n)
        got[lo:hi] = np.add.reduceat(_BYTE_CODES[buf[at]] * _POWER[inside], base)
        lo = hi
    out[some] = mix(got + length.astype(np.uint64) * _STEP)
    return out


def window_hash(word: np.ndarray, row: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word windows that stay inside one row, and the index of each one's first word."""
    n = len(word) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    inside = np.flatnonzero(row[:n] == row[k - 1 :])
    h = np.zeros(len(inside), np.uint64)
    for j in range(k):
        h = mix(h * _STEP + word[inside + j] + _U(j + 1))
    return h, inside


def unique_per_row(row: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, value) pairs, ordered by row and then value."""
    if not len(row):
        return row, value
    order = np.lexsort((value, row))
    r, v = row[order], value[order]
    keep = np.ones(len(r), bool)
    keep[1:] = (r[1:] != r[:-1]) | (v[1:] != v[:-1])
    return r[keep], v[keep]


def per_row_sum(flags: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Number of set byte flags between each row's offsets."""
    total = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
    return total[off[1:]] - total[off[:-1]]


def shingle_sets(buf: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct k-word shingle hashes of each row, as (row, hash) ordered by both.

    Words are compared with A-Z lowered. A row with fewer than k words has its whole word sequence as
    the one shingle; a row without words has none.
    """
    low = LOWER[buf]
    w = words_of(low, off)
    h = range_hash(low, w.start, w.end)
    value, at = window_hash(h, w.row, k)
    row = w.row[at]
    count = np.diff(w.first)
    if (short := np.flatnonzero((count > 0) & (count < k))).size:
        seq = np.zeros(len(short), np.uint64)
        for j in range(k - 1):
            has = count[short] > j
            seq[has] = mix(seq[has] * _STEP + h[w.first[short[has]] + j] + _U(j + 1))
        seq = mix(seq + count[short].astype(np.uint64) * _U(0xD1B54A32D192ED03))
        row, value = np.concatenate([row, short]), np.concatenate([value, seq])
    return unique_per_row(row, value)
