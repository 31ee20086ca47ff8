"""Choices made before a query runs: precision, rung, bucket parameter, tier."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.hashing import WIDTH

TINY = 64
#: Elements of a shard, about: 32 MB of hashes.
SHARD_ELEMENTS = 1 << 22


def ceil_log2(n: int) -> int:
    return max(0, (max(1, n) - 1).bit_length())


def choose_r(cards: list[int], c: int = 1, w: int = WIDTH) -> int:
    """Precision for an expression over sets of these sizes: log n plus c log w, within 1..w."""
    return max(1, min(w, ceil_log2(sum(cards)) + c * ceil_log2(w)))


def rung_schedule(card: int, w: int = WIDTH) -> list[int]:
    """Precisions at which a set is kept: ceil(log |S|) + 1, 2, 4, ... below w, and w itself."""
    base = ceil_log2(card)
    steps = int(math.log2(w - base)) if w > base else -1
    return sorted({min(w, base + (1 << i)) for i in range(steps + 1)} | {w})


def rung_schedule_column(card: Column, w: int = WIDTH) -> Column:
    """The same as an array column."""
    base = F.ceil(F.log2(F.greatest(card, F.lit(1)))).cast("int")
    steps = F.floor(F.log2(F.lit(w) - base)).cast("int")
    climbs = F.transform(F.sequence(F.lit(0), steps), lambda i: base + F.pow(F.lit(2), i).cast("int"))
    return F.array_sort(F.array_distinct(F.concat(F.filter(climbs, lambda r: r < w), F.array(F.lit(w)))))


def pick_rung(rungs: list[int], r: int) -> int:
    """The smallest stored precision that is enough."""
    return min(x for x in rungs if x >= r)


def pick_rung_column(rungs: Column, r: int) -> Column:
    return F.array_min(F.filter(rungs, lambda x: x >= r))


def balanced_b(n: int, w: int = 64) -> int:
    """Largest b with 2^b groups of about w elements each, 0 for small sets."""
    return max(0, int(math.floor(math.log2(n) - math.log2(w)))) if n > 0 else 0


def balanced_b_column(n: Column, w: int = 64) -> Column:
    return F.greatest(F.lit(0), F.floor(F.log2(F.greatest(n, F.lit(1))) - math.log2(w))).cast("int")


def field_bits(value_bits: int, w: int = 64) -> int:
    """Entry bits of a field: room for the value and the reserved all-ones, and for counts of a word's fields."""
    f = max(1, value_bits + 1)
    while fields_per_word(f, w) > 1 << f:
        f += 1
    return f


def fields_per_word(f: int, w: int = 64) -> int:
    """Fields of f bits and a test bit in a word of w bits, rounded down to a power of two."""
    return 1 << max(0, (w // (f + 1)).bit_length() - 1)


def shard_bits_for(n: int) -> int:
    """Shards of about SHARD_ELEMENTS elements, eight at least."""
    return max(3, min(20, ceil_log2(-(-n // SHARD_ELEMENTS))))


def choose_tier(cards: list[int], stored: bool, has_and: bool = True, union_path: bool = False) -> str:
    """probe, union, packed or columns; all give the same answer at any size."""
    if union_path:
        return "union"
    if has_and and max(cards) > 64 * max(1, min(cards)):
        return "probe"
    return "packed" if stored else "columns"
