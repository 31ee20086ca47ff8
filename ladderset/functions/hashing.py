"""One hash for all sets, and its prefixes, as column expressions and as the same arithmetic in plain SQL.

The mother hash has 62 bits and is non-negative. Every shorter hash is a prefix of it, so a longer one
determines all shorter ones, and equal elements of all sets agree at every precision.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDTH = 62
PRIME = (1 << 31) - 1
# fixed values: lane constants of the default hash (a1, a2, a3, b), which tests and SQL twins share
LANES = ((1103515245, 1500450271, 97, 12345), (1812433253, 1664525, 331, 1013904223))


def lanes(seed: int = 0) -> tuple[tuple[int, ...], ...]:
    """Constants of the two lanes; seed 0 gives the fixed ones."""
    if not seed:
        return LANES
    rng = random.Random(seed)
    return tuple(tuple(rng.randrange(1, PRIME) for _ in range(4)) for _ in range(2))


def tables(seed: int = 0) -> list[list[int]]:
    """Eight tables of 256 random 62-bit entries, one per byte of the key."""
    rng = random.Random(9176 + seed)
    return [[rng.getrandbits(WIDTH) for _ in range(256)] for _ in range(8)]


def mother_hash(col: Column | str, kind: str = "linear2", seed: int = 0) -> Column:
    """The 62-bit hash of a key. linear2 and tabulation are strongly universal; xxhash also takes strings."""
    c = F.col(col) if isinstance(col, str) else col
    if kind == "xxhash":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), c), 2)
    c = c.cast("long")
    if kind == "linear2":
        low = F.lit((1 << 30) - 1)
        x = (c.bitwiseAND(low), F.shiftright(c, 30).bitwiseAND(low), F.shiftright(c, 60).bitwiseAND(F.lit(15)))
        one, two = ((a1 * x[0] + a2 * x[1] + a3 * x[2] + b) % PRIME for a1, a2, a3, b in lanes(seed))
        return F.shiftleft(one.cast("long"), 31).bitwiseOR(two.cast("long"))
    if kind == "tabulation":
        out = None
        for i, t in enumerate(tables(seed)):
            cell = F.get(F.lit(t).cast("array<bigint>"), F.shiftright(c, 8 * i).bitwiseAND(F.lit(255)).cast("int"))
            out = cell if out is None else out.bitwiseXOR(cell)
        return out
    raise ValueError(kind)


def mother_hash_sql(x: str, kind: str = "linear2", seed: int = 0) -> str:
    """The same value in plain SQL."""
    if kind == "linear2":
        low = (1 << 30) - 1
        one, two = (f"(({a1} * ({x} & {low}) + {a2} * (({x} >> 30) & {low}) + {a3} * (({x} >> 60) & 15) + {b}) % {PRIME})" for a1, a2, a3, b in lanes(seed))
        return f"({one} * 2147483648 + {two})"
    cells = [f"list_extract([{', '.join(map(str, t))}], CAST((({x} >> {8 * i}) & 255) + 1 AS BIGINT))" for i, t in enumerate(tables(seed))]
    out = cells[0]
    for c in cells[1:]:
        out = f"xor({out}, {c})"
    return f"CAST({out} AS BIGINT)"


def prefix_hash(hs: Column | str, r: int | Column) -> Column:
    """The r most significant bits of the mother hash."""
    hs = F.col(hs) if isinstance(hs, str) else hs
    return F.shiftrightunsigned(hs, WIDTH - r) if isinstance(r, int) else F.call_function("shiftrightunsigned", hs, F.lit(WIDTH) - r)


def hashed_set(family: DataFrame, r: int, kind: str = "linear2", seed: int = 0) -> DataFrame:
    """Distinct (set_id, hv) at precision r."""
    return family.select("set_id", prefix_hash(mother_hash("elem", kind, seed), r).alias("hv")).distinct()
