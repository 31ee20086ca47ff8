"""Cost and accuracy formulas: upper bounds, the lower bound, their I/O versions, space, and predicted gains."""

from __future__ import annotations

import math


def log2(x: float) -> float:
    return math.log2(max(x, 1.0))


def cost_expression(nodes: list[dict], n: int, kprime: int, w: int, power: int = 2, only: tuple[str, ...] = ("leaf", "or", "and", "minus")) -> float:
    """Occurrences plus, for each node, whole words of its useful size times squared log of the slack."""
    total = float(kprime)
    for v in nodes:
        if v["op"] in only and v["psi_star"] > 0:
            total += math.ceil(v["psi_star"] / w * log2(n * w / v["psi_star"]) ** power)
    return total


def cost_leaf_union(nodes: list[dict], n: int, kprime: int, w: int) -> float:
    """The same without intersection nodes."""
    return cost_expression(nodes, n, kprime, w, only=("leaf", "or"))


def cost_intersection(n: int, m: int, k: int, w: int, power: int = 2) -> float:
    return n * log2(w) ** power / w + k * m


def cost_union_depth(n: int, m: int, kprime: int, d: int, w: int, power: int = 2) -> float:
    return m + kprime + n / w * (d + log2(w)) ** power


def cost_io(n: int, m: int, k: int, w: int, block: int) -> float:
    """Blocks of `block` words act as longer words, and the log counts once."""
    return cost_intersection(n, m, k, w * block, power=1)


def lower_parts(n: int, m: int, k: int, w: int) -> tuple[float, float]:
    """What deciding emptiness needs, and what telling k elements needs."""
    return n / (w * m * max(log2(m), 1.0)), max(0.0, 1 - log2(k) / w) * k


def cost_lower(n: int, m: int, k: int, w: int) -> float:
    return sum(lower_parts(n, m, k, w))


def gap(n: int, m: int, k: int, w: int) -> float:
    return cost_intersection(n, m, k, w) / max(cost_lower(n, m, k, w), 1e-12)


def gap_limit(m: int, w: int) -> float:
    return log2(w) ** 2 * m * max(log2(m), 1.0)


def predicted_speedup(w: int) -> float:
    return w / log2(w) ** 2


def comparison_factor(a: int, b: int) -> float:
    """What comparisons cost over hashing for sets of uneven size."""
    return log2(1 + max(a, b) / max(1, min(a, b)))


def space_bits(card: int, r: int, w: int = 64) -> float:
    """Bits of one balanced rung: a remainder per element, and the array of groups."""
    from .choose import balanced_b

    b = balanced_b(card, w)
    return card * (r - b) + (1 << b) * w


def information_bits(card: int, r: int) -> float:
    """Bits that any representation of a set of `card` r-bit values needs, about."""
    return card * max(0.0, r - log2(card))


def false_bound(n: int, r: int) -> float:
    """Expected false occurrences: each collides with another of n inputs."""
    return n * n / 2.0**r
