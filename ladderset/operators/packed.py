"""Packed runs: many short integers in each word, handled a word at a time.

A 64-bit lane holds k fields of f bits below a test bit, k a power of two, lowest field first; a word is one
lane or a power of two of them. A run is a sorted, duplicate-free sequence of values in consecutive words; the
unused fields at its end hold the reserved all-ones value, which sorts last. Kernels work on matrices of
lanes, one run per row, so one numpy operation advances every run of a batch. Words of several lanes are merged
as a whole: reversed, compared and sorted across their lanes. `Ops` counts operations on whole words, each
kernel by the number of its steps, which grows with the logarithm of a word's fields.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

from ..plans.choose import fields_per_word

U = np.uint64


@dataclass
class Ops:
    """Word operations, words read and kernel calls, for words of `lanes` 64-bit lanes."""

    lanes: int = 1
    word_ops: float = 0
    words_read: float = 0
    calls: int = 0

    def spend(self, size: int, lo: Layout, per_log: int, fixed: int) -> None:
        """A kernel over `size` lanes, whose steps are a multiple of log k and some more; k is the fields of a whole word."""
        log_k = lo.log_k + self.lanes.bit_length() - 1
        self.word_ops += -(-size // self.lanes) * (per_log * log_k + fixed)
        self.calls += 1

    def read(self, size: int) -> None:
        self.words_read += -(-size // self.lanes)


class Layout:
    """Constants of words with f-bit entries."""

    def __init__(self, f: int):
        self.f, self.g, self.k = f, f + 1, fields_per_word(f)
        self.log_k = self.k.bit_length() - 1
        self.low = U(sum(1 << (self.g * i) for i in range(self.k)))
        self.test = self.low << U(f)
        self.entry = self.test - self.low
        self.none = U((1 << f) - 1)
        self.used = self.test | self.entry
        # for a distance of 2^b fields, the fields whose index has bit b clear
        self.halves = [U(sum(((1 << self.g) - 1) << (self.g * i) for i in range(self.k) if not i >> b & 1)) for b in range(self.log_k)]

    def shift(self, fields: int) -> np.uint64:
        return U(self.g * fields)

    def words(self, n: int) -> int:
        return max(1, -(-n // self.k))


@lru_cache(maxsize=64)
def layout(f: int) -> Layout:
    return Layout(f)


def pack(values: np.ndarray, f: int) -> np.ndarray:
    """Words of a matrix of values, one run per row; pad rows with the reserved value 2^f - 1."""
    lo = layout(f)
    rows, n = values.shape
    full = np.full((rows, lo.words(n) * lo.k), lo.none, np.uint64)
    full[:, :n] = values
    parts = full.reshape(rows, -1, lo.k)
    out = np.zeros(parts.shape[:2], np.uint64)
    for i in range(lo.k):
        out |= parts[:, :, i] << lo.shift(i)
    return out


def unpack(words: np.ndarray, f: int) -> np.ndarray:
    """All fields of the words, reserved ones included."""
    lo = layout(f)
    out = np.stack([(words >> lo.shift(i)) & lo.none for i in range(lo.k)], axis=-1)
    return out.reshape(words.shape[0], -1)


def pack_run(values: np.ndarray, f: int) -> np.ndarray:
    return pack(np.asarray(values, np.uint64)[None, :], f)[0]


def unpack_run(words: np.ndarray, f: int) -> np.ndarray:
    v = unpack(np.asarray(words, np.uint64)[None, :], f)[0]
    return v[v != layout(f).none]


def at_least(x: np.ndarray, y: np.ndarray, lo: Layout) -> np.ndarray:
    """Entry masks of the fields in which x >= y."""
    t = ((x | lo.test) - y) & lo.test
    return t - (t >> U(lo.f))


def low_high(x: np.ndarray, y: np.ndarray, lo: Layout) -> tuple[np.ndarray, np.ndarray]:
    m = at_least(x, y, lo)
    swap = (x ^ y) & m
    return x ^ swap, y ^ swap


def reverse(x: np.ndarray, lo: Layout) -> np.ndarray:
    for b, half in enumerate(lo.halves):
        s = lo.shift(1 << b)
        x = ((x & half) << s) | ((x >> s) & half)
    return x


def sweep(x: np.ndarray, lo: Layout) -> np.ndarray:
    """Sorts words that rise and then fall: compare and exchange at distances k/2 .. 1."""
    for b in reversed(range(lo.log_k)):
        s, half = lo.shift(1 << b), lo.halves[b]
        a, c = low_high(x & half, (x >> s) & half, lo)
        x = a | (c << s)
    return x


def _reverse_words(x: np.ndarray, lo: Layout) -> np.ndarray:
    return reverse(x, lo)[:, ::-1]


def _sweep_words(x: np.ndarray, lo: Layout) -> np.ndarray:
    """sweep() over words of several lanes (axis 1): distances of whole lanes first."""
    rows, lanes = x.shape
    d = lanes // 2
    while d:
        parts = x.reshape(rows, -1, 2, d)
        x = np.stack(low_high(parts[:, :, 0], parts[:, :, 1], lo), axis=2).reshape(rows, lanes)
        d //= 2
    return sweep(x, lo)


def _words(a: np.ndarray, lanes: int, lo: Layout) -> np.ndarray:
    """A matrix of lanes as (rows, words, lanes), with one reserved word at the end."""
    rows, width = a.shape
    full = np.full((rows, (-(-width // lanes) + 1) * lanes), lo.entry, np.uint64)
    full[:, :width] = a
    return full.reshape(rows, -1, lanes)


def merge(a: np.ndarray, b: np.ndarray, f: int, ops: Ops | None = None) -> np.ndarray:
    """Merges the runs of two matrices, row by row; equal values stay side by side."""
    lo, lanes = layout(f), ops.lanes if ops else 1
    rows, size = a.shape[0], a.size + b.size
    a, b = _words(a, lanes, lo), _words(b, lanes, lo)
    total, line = a.shape[1] + b.shape[1] - 2, np.arange(rows)
    out = np.empty((rows, total, lanes), np.uint64)
    i = np.zeros(rows, np.int64)
    j = np.zeros(rows, np.int64)

    def take() -> np.ndarray:
        """The next word, from the run whose head is smaller."""
        x, y = a[line, i], b[line, j]
        left = ((x[:, 0] & lo.none) <= (y[:, 0] & lo.none)) & (i < a.shape[1] - 1) | (j >= b.shape[1] - 1)
        i[left] += 1
        j[~left] += 1
        return np.where(left[:, None], x, y)

    carry = take() if total else None
    for w in range(total - 1):
        first, second = low_high(carry, _reverse_words(take(), lo), lo)
        out[:, w], carry = _sweep_words(first, lo), _sweep_words(second, lo)
    if total:
        out[:, -1] = carry
    if ops:
        ops.read(size)
        ops.spend(size, lo, 15, 8)
    return out.reshape(rows, -1)


def same_as_left(z: np.ndarray, lo: Layout) -> np.ndarray:
    """Test bits of the fields that equal the field before them (across words of a run)."""
    before = (z << lo.shift(1)) & lo.used
    before[:, 1:] |= z[:, :-1] >> lo.shift(lo.k - 1)
    before[:, :1] |= ~z[:, :1] & lo.none  # nothing stands before the first field
    differs = (((z ^ before) & lo.entry | lo.test) - lo.low) & lo.test
    return differs ^ lo.test


def compact(z: np.ndarray, vacant: np.ndarray, f: int, ops: Ops | None = None) -> np.ndarray:
    """Moves the fields that aren't marked vacant (test bits) to the front, order kept; reserved values fill the rest."""
    lo = layout(f)
    gone = vacant >> U(f)
    fill = vacant - gone
    x = z & lo.entry & ~fill
    moves = gone.copy()
    for b in range(lo.log_k):  # vacancies up to and with each field, by doubling
        moves += (moves << lo.shift(1 << b)) & lo.used
    moves &= lo.entry & ~fill
    live = lo.low & ~gone
    for b in range(lo.log_k):
        go = (moves >> U(b)) & live
        who = (go << U(lo.g)) - go if lo.g < 64 else go
        s = lo.shift(1 << b)
        x, moves, live = (x & ~who) | ((x & who) >> s), (moves & ~who) | ((moves & who) >> s), (live & ~go) | (go >> s)
    if lo.k == 1:
        x = np.where(gone != 0, U(0), x)
    count = np.bitwise_count(lo.low & ~gone).astype(np.int64)
    at = np.cumsum(count, axis=1) - count
    rows, width = z.shape
    out = np.zeros((rows, width + 1), np.uint64)
    line = np.repeat(np.arange(rows), width).reshape(rows, width)
    word, off = at // lo.k, at % lo.k
    np.bitwise_or.at(out, (line, word), x << (off * lo.g).astype(np.uint64))
    spills = off + count > lo.k
    np.bitwise_or.at(out, (line[spills], word[spills] + 1), x[spills] >> ((lo.k - off[spills]) * lo.g).astype(np.uint64))
    total = count.sum(1)
    # reserved values behind the last field
    held = np.clip(total[:, None] - np.arange(width + 1) * lo.k, 0, lo.k)
    tail = np.where(held >= lo.k, U(0), (lo.entry >> (held * lo.g).astype(np.uint64) << (held * lo.g).astype(np.uint64)) if lo.k > 1 else lo.entry)
    out = (out & lo.used) | (tail & lo.entry)
    if ops:
        ops.spend(rows * width, lo, 13, 8)
    return out[:, : max(1, int(-(-int(total.max(initial=0)) // lo.k)))]


def _reserved(z: np.ndarray, lo: Layout) -> np.ndarray:
    return ((z & lo.entry) + lo.low) & lo.test


def occupied(z: np.ndarray, f: int) -> int:
    """Fields of the matrix that hold a value."""
    lo = layout(f)
    return z.size * lo.k - int(np.bitwise_count(_reserved(z, lo)).sum())


def packed_union(a: np.ndarray, b: np.ndarray, f: int, ops: Ops | None = None) -> np.ndarray:
    lo = layout(f)
    z = merge(a, b, f, ops)
    if ops:
        ops.spend(z.size, lo, 0, 9)
    return compact(z, same_as_left(z, lo) | _reserved(z, lo), f, ops)


def packed_intersect(a: np.ndarray, b: np.ndarray, f: int, ops: Ops | None = None) -> np.ndarray:
    lo = layout(f)
    z = merge(a, b, f, ops)
    if ops:
        ops.spend(z.size, lo, 0, 9)
    return compact(z, (same_as_left(z, lo) ^ lo.test) | _reserved(z, lo), f, ops)


def packed_truncate(a: np.ndarray, drop: int, f: int, ops: Ops | None = None) -> np.ndarray:
    """Drops low bits of every entry and what is then double; fields keep their width."""
    lo = layout(f)
    keep = lo.low * U((1 << (f - drop)) - 1)
    gone = _reserved(a, lo)
    z = ((a >> U(drop)) & keep) | (gone - (gone >> U(f)))
    if ops:
        ops.read(a.size)
        ops.spend(a.size, lo, 0, 12)
    return compact(z, same_as_left(z, lo) | _reserved(z, lo), f, ops)
