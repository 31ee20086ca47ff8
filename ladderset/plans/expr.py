"""Set expressions: trees of unions and intersections over named sets, their bounds and rewrites."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Leaf:
    set_id: str

    def __str__(self) -> str:
        return self.set_id


@dataclass(frozen=True)
class Node:
    """op is "or", "and" or "minus" (two children; the second only takes away)."""

    op: str
    children: tuple

    def __str__(self) -> str:
        return "(" + {"or": " | ", "and": " & ", "minus": " - "}[self.op].join(map(str, self.children)) + ")"


Expr = Leaf | Node


def any_of(*parts) -> Expr:
    return _chain("or", parts)


def all_of(*parts) -> Expr:
    return _chain("and", parts)


def minus(a, b) -> Expr:
    return Node("minus", (_leaf(a), _leaf(b)))


def _leaf(x) -> Expr:
    return x if isinstance(x, (Leaf, Node)) else Leaf(str(x))


def _chain(op: str, parts) -> Expr:
    """Binary, left-deep."""
    out = _leaf(parts[0])
    for p in parts[1:]:
        out = Node(op, (out, _leaf(p)))
    return out


_TOKEN = re.compile(r"\s*(?:([()|&\-])|([^\s()|&]+))")


def parse(text: str) -> Expr:
    """`(a & b) | c`; & binds tighter than | and -; a name may hold anything but blanks, brackets, | and &."""
    tokens = [m[1] or m[2] for m in _TOKEN.finditer(text)]
    at = 0

    def atom() -> Expr:
        nonlocal at
        if at >= len(tokens):
            raise ValueError(f"unfinished expression: {text}")
        t = tokens[at]
        at += 1
        if t == "(":
            e = alternatives()
            if at >= len(tokens) or tokens[at] != ")":
                raise ValueError(f"missing bracket: {text}")
            at += 1
            return e
        if t in ")|&-":
            raise ValueError(f"unexpected {t}: {text}")
        return Leaf(t)

    def factors() -> Expr:
        nonlocal at
        e = atom()
        while at < len(tokens) and tokens[at] == "&":
            at += 1
            e = Node("and", (e, atom()))
        return e

    def alternatives() -> Expr:
        nonlocal at
        e = factors()
        while at < len(tokens) and tokens[at] in "|-":
            op = "or" if tokens[at] == "|" else "minus"
            at += 1
            e = Node(op, (e, factors()))
        return e

    out = alternatives()
    if at != len(tokens):
        raise ValueError(f"trailing text: {text}")
    return out


def walk(e: Expr, parent: int = -1, out: list | None = None) -> list[tuple[int, int, Expr]]:
    """(number, parent's number, node), parents first."""
    out = [] if out is None else out
    me = len(out)
    out.append((me, parent, e))
    for c in e.children if isinstance(e, Node) else ():
        walk(c, me, out)
    return out


def leaves(e: Expr) -> list[Leaf]:
    return [n for _, _, n in walk(e) if isinstance(n, Leaf)]


def set_ids(e: Expr) -> list[str]:
    return list(dict.fromkeys(x.set_id for x in leaves(e)))


def union_depth(e: Expr) -> int:
    """Most unions on a path to the root."""
    if isinstance(e, Leaf):
        return 0
    return (e.op == "or") + max(map(union_depth, e.children))


def bounds(e: Expr, cards: dict[str, int], known: dict[int, int] | None = None) -> list[dict]:
    """psi (size bound from below) and psi_star (what can still be useful above) of every node, and the visiting order.

    Children of an intersection tie on psi_star, so they are visited by psi. `known` has sizes of nodes that stand in for psi, such as
    estimates from a sample.
    """
    rows = walk(e)
    psi: dict[int, int] = {}
    for me, _, n in reversed(rows):
        kids = [psi[i] for i, p, _ in rows if p == me]
        psi[me] = cards.get(n.set_id, 0) if isinstance(n, Leaf) else {"or": sum, "and": min, "minus": lambda k: k[0]}[n.op](kids)
        if known and me in known:
            psi[me] = known[me]
    star: dict[int, int] = {}
    for me, parent, _ in rows:
        star[me] = psi[me] if parent < 0 else min(psi[me], star[parent])
    order: dict[int, int] = {}

    def visit(me: int) -> None:
        kids = [i for i, p, _ in rows if p == me]
        n = rows[me][2]
        if isinstance(n, Node) and n.op == "and":
            kids.sort(key=lambda i: (star[i], psi[i], i))
        for k in kids:
            visit(k)
        order[me] = len(order)

    visit(0)
    return [{"node": me, "parent": parent, "op": "leaf" if isinstance(n, Leaf) else n.op, "set_id": n.set_id if isinstance(n, Leaf) else None, "psi": psi[me], "psi_star": star[me], "visit": order[me]} for me, parent, n in rows]


def flatten(e: Expr) -> Expr:
    """Adjacent equal operators become one with many children, so unions and intersections alternate."""
    if isinstance(e, Leaf) or e.op == "minus":
        return e if isinstance(e, Leaf) else Node(e.op, tuple(map(flatten, e.children)))
    kids = []
    for c in map(flatten, e.children):
        kids += c.children if isinstance(c, Node) and c.op == e.op else [c]
    return Node(e.op, tuple(kids))


def balance(e: Expr) -> Expr:
    """The same expression with binary operators, runs of equal ones as balanced trees."""
    e = flatten(e)
    if isinstance(e, Leaf):
        return e

    def tree(kids: list) -> Expr:
        return kids[0] if len(kids) == 1 else Node(e.op, (tree(kids[: len(kids) // 2]), tree(kids[len(kids) // 2 :])))

    kids = [balance(c) for c in e.children]
    return Node("minus", tuple(kids)) if e.op == "minus" else tree(kids)


def simplify(e: Expr) -> Expr:
    """Drops repeated children and absorbed ones: A|A, A&A, A|(A&B), A&(A|B)."""
    e = flatten(e)
    if isinstance(e, Leaf):
        return e
    kids = [simplify(c) for c in e.children]
    if e.op == "minus":
        return Node("minus", tuple(kids))
    kids = list(dict.fromkeys(kids))
    other = "and" if e.op == "or" else "or"
    here = set(kids)
    kids = [k for k in kids if not (isinstance(k, Node) and k.op == other and here & set(k.children))] or kids[:1]
    return kids[0] if len(kids) == 1 else Node(e.op, tuple(kids))


def fold(e: Expr, leaf: Callable, either: Callable, both: Callable, without: Callable):
    """Evaluates the tree bottom-up; leaves are numbered from left to right."""
    numbers: Iterator[int] = iter(range(1 << 30))

    def go(n: Expr):
        if isinstance(n, Leaf):
            return leaf(next(numbers), n)
        kids = [go(c) for c in n.children]
        out = kids[0]
        for k in kids[1:]:
            out = {"or": either, "and": both, "minus": without}[n.op](out, k)
        return out

    return go(e)


MASK_BITS = 62


def mask_columns(n: int) -> list[str]:
    return [f"m{i}" for i in range(-(-n // MASK_BITS))]


def bit_is_set(i: int, cols: list[Column]) -> Column:
    return cols[i // MASK_BITS].bitwiseAND(F.lit(1 << (i % MASK_BITS))) != 0


class Masks:
    """The expression over provenance masks (bit i: in the set of leaf i), in as few terms as its operators need.

    Runs of leaves below one operator become a single comparison with a constant mask.
    """

    def __init__(self, e: Expr, cols: list[Column], sketch: bool = False):
        self.cols, self.sketch, self.e = cols, sketch, flatten(e)

    @staticmethod
    def _split(n: Node, at: int) -> tuple[list[int], list[tuple[Node, int]]]:
        """Numbers of the leaves right below a node whose first leaf is number `at`, and its other children with theirs."""
        own, rest = [], []
        for c in n.children:
            if isinstance(c, Leaf):
                own.append(at)
            else:
                rest.append((c, at))
            at += len(leaves(c))
        return own, rest

    @staticmethod
    def _mask(numbers: list[int], j: int) -> int:
        return sum(1 << (i % MASK_BITS) for i in numbers if i // MASK_BITS == j)

    def _terms(self, numbers: list[int], every: bool) -> list[Column]:
        out = []
        for j, col in enumerate(self.cols):
            if m := self._mask(numbers, j):
                got = col.bitwiseAND(F.lit(m))
                out.append(got == m if every else got != 0)
        return out

    def value(self, n: Expr | None = None, at: int = 0) -> Column:
        n = self.e if n is None else n
        if isinstance(n, Leaf):
            return bit_is_set(at, self.cols)
        if n.op == "minus":
            a = self.value(n.children[0], at)
            return a if self.sketch else a & ~self.value(n.children[1], at + len(leaves(n.children[0])))
        own, rest = self._split(n, at)
        terms = self._terms(own, n.op == "and") + [self.value(c, i) for c, i in rest]
        out = terms[0]
        for t in terms[1:]:
            out = out & t if n.op == "and" else out | t
        return out

    def allowed(self, j: int, n: Expr | None = None, at: int = 0) -> Column:
        """Of mask column j, the leaves whose ancestors all hold. Below a union that follows from the leaf itself."""
        n = self.e if n is None else n
        keep = lambda numbers: self.cols[j].bitwiseAND(F.lit(self._mask(list(numbers), j)).cast("long"))
        if isinstance(n, Leaf):
            return keep([at])
        if n.op == "minus":
            first = n.children[0]
            # what is taken away matters where the first side holds, whatever its own value
            both = self.allowed(j, first, at).bitwiseOR(keep(range(at + len(leaves(first)), at + len(leaves(n)))))
            return F.when(self.value(first, at), both).otherwise(F.lit(0).cast("long"))
        own, rest = self._split(n, at)
        out = keep(own)
        for c, i in rest:
            out = out.bitwiseOR(self.allowed(j, c, i))
        return F.when(self.value(n, at), out).otherwise(F.lit(0).cast("long")) if n.op == "and" else out


def holds(e: Expr, cols: list[Column], sketch: bool = False) -> Column:
    """Whether masks satisfy the expression. In a sketch nothing is taken away."""
    return Masks(e, cols, sketch).value()


def allowed_masks(e: Expr, cols: list[Column]) -> list[Column]:
    """Masks cut to the occurrences that can still matter, by the sketch's masks."""
    m = Masks(e, cols, sketch=True)
    return [m.allowed(j) for j in range(len(cols))]


def to_sql(e: Expr, leaf_sql: Callable[[str], str]) -> str:
    """A query for the expression with INTERSECT, UNION and EXCEPT, always in brackets."""
    return fold(e, lambda _, n: f"({leaf_sql(n.set_id)})", lambda a, b: f"(SELECT * FROM {a} UNION SELECT * FROM {b})", lambda a, b: f"(SELECT * FROM {a} INTERSECT SELECT * FROM {b})", lambda a, b: f"(SELECT * FROM {a} EXCEPT SELECT * FROM {b})")
