"""Exact evaluation of set expressions: a sketch on hash prefixes, shrunk inputs, an exact finish.

Two tiers share the plan. The relational tier is all Catalyst: one aggregate of provenance masks by hash
prefix is the sketch of every node at once, a join by prefix shrinks the inputs, and the finish groups by
element on the same partitioning. The packed tier reads stored rungs and works on packed words: the whole tree
is evaluated range by range of the hash, small sides first, intermediates cut to what can be useful, and only
the dictionary's shards that the survivors touch are read.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import WIDTH, mother_hash, prefix_hash
from ..plans.choose import balanced_b, choose_r, choose_tier, field_bits, pick_rung
from ..plans.expr import MASK_BITS, Expr, Leaf, Node, all_of, allowed_masks, bit_is_set, bounds, flatten, fold, holds, leaves, mask_columns, parse, set_ids, simplify, union_depth, walk
from ..sources.scratch import staged
from . import ladder as L
from .packed import Ops, layout, occupied, packed_intersect, packed_union, unpack

bit_of = bit_is_set


def as_expr(e: Expr | str) -> Expr:
    return parse(e) if isinstance(e, str) else e


def sizes(e: Expr, family: DataFrame) -> dict[str, int]:
    """Sizes of the named sets: as many rows as the expression has sets."""
    ids = set_ids(e)
    got = {r["set_id"]: r["card"] for r in family.where(F.col("set_id").isin(ids)).groupBy("set_id").agg(F.count("*").alias("card")).collect()}
    return {s: got.get(s, 0) for s in ids}


def precision(e: Expr, family: DataFrame, r: int | None, c: int = 1) -> int:
    return choose_r(list(sizes(e, family).values()), c) if r is None else r


def planned_precision(family: DataFrame) -> int:
    """A precision that is enough, without a pass over the sets: from the optimiser's estimate of their bytes, of which every row takes one at
    least. Too large a precision only costs bits of a column; sizes are counted where the estimate knows nothing."""
    size = int(str(family._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return choose_r([size]) if size < 1 << 50 else choose_r([family.count()])


def marked(e: Expr, family: DataFrame) -> DataFrame:
    """(elem, m0, m1, ...): inputs of the expression with the leaves each belongs to, as bits. The table of leaves is as small as the expression."""
    masks: dict[str, list[int]] = {}
    cols = mask_columns(len(leaves(e)))
    for i, leaf in enumerate(leaves(e)):
        masks.setdefault(leaf.set_id, [0] * len(cols))[i // MASK_BITS] |= 1 << (i % MASK_BITS)
    table = family.sparkSession.createDataFrame([(s, *m) for s, m in masks.items()], "set_id string, " + ", ".join(f"{c} long" for c in cols))
    return family.where(F.col("set_id").isin(list(masks))).join(F.broadcast(table), "set_id").select("elem", *cols)


def _or(cols: list[str]) -> list[Column]:
    return [F.bit_or(c).alias(c) for c in cols]


def sketch(e: Expr | str, family: DataFrame, r: int, kind: str = "linear2", seed: int = 0) -> DataFrame:
    """Prefixes that survive the expression, with their masks."""
    e = as_expr(e)
    cols = mask_columns(len(leaves(e)))
    hashed = marked(e, family).withColumn("hv", prefix_hash(mother_hash("elem", kind, seed), r))
    return hashed.groupBy("hv").agg(*_or(cols)).where(holds(e, [F.col(c) for c in cols], sketch=True))


def shrink(e: Expr | str, family: DataFrame, r: int, mode: str = "path", kind: str = "linear2", seed: int = 0, h: DataFrame | None = None) -> DataFrame:
    """(hv, elem, masks): occurrences that may matter. global: prefix in the sketch; path: also every node on the way up holds; none: all.
    `h` is a sketch (hv) that is there already, for mode global."""
    e = as_expr(e)
    cols = mask_columns(len(leaves(e)))
    rows = marked(e, family).withColumn("hv", prefix_hash(mother_hash("elem", kind, seed), r))
    if mode == "none":
        return rows.select("hv", "elem", *cols)
    if h is not None:
        return rows.join(h.select("hv"), "hv", "left_semi").select("hv", "elem", *cols)
    h = sketch(e, family, r, kind, seed).select("hv", *[F.col(c).alias(f"h_{c}") for c in cols])
    kept = rows.join(h, "hv")
    if mode == "path":
        for c, ok in zip(cols, allowed_masks(e, [F.col(f"h_{c}") for c in cols]), strict=True):
            kept = kept.withColumn(c, F.col(c).bitwiseAND(ok))
        kept = kept.where(reduce(lambda a, b: a | b, [F.col(c) != 0 for c in cols]))
    return kept.select("hv", "elem", *cols)


def finish(e: Expr | str, candidates: DataFrame, how: str = "mask") -> DataFrame:
    """The exact answer from candidates (hv, elem, masks): by masks, or by nested unions and intersections."""
    e = as_expr(e)
    cols = mask_columns(len(leaves(e)))
    if how == "mask":
        # equal elements have equal prefixes, so this keeps the partitioning of the shrink
        return candidates.groupBy("hv", "elem").agg(*_or(cols)).where(holds(e, [F.col(c) for c in cols])).select("elem")
    bit = lambda i: F.col(cols[i // MASK_BITS]).bitwiseAND(F.lit(1 << (i % MASK_BITS))) != 0
    return tree(e, lambda i, _: candidates.where(bit(i)).select("elem"))


def tree(e: Expr, leaf, join_hint: str | None = None) -> DataFrame:
    """Unions and intersections node by node; intersections as semi-joins, optionally with a join hint."""

    def both(a: DataFrame, b: DataFrame) -> DataFrame:
        return a.join(b.hint(join_hint) if join_hint else b, a.columns, "left_semi")

    return fold(e, leaf, lambda a, b: a.union(b).distinct(), both, lambda a, b: a.join(b, a.columns, "left_anti"))


def evaluate(e: Expr | str, family: DataFrame, mode: str = "path", how: str = "mask", r: int | None = None, kind: str = "linear2", seed: int = 0, tier: str = "columns", store: L.Ladder | None = None, cap: bool = True, ordered: bool = True, sampled: int = 0) -> DataFrame:
    """The elements of the expression, (elem).

    tier: columns (one aggregate is the sketch of all nodes), nodes (a sketch node by node, small sides first and cut; `sampled` low hash
    bits give estimated sizes in place of bounds), packed (needs a store), mask, union, probe or auto.
    """
    e = as_expr(e)
    if tier == "auto":
        cards = list(sizes(e, family).values())
        tier = choose_tier(cards, store is not None, any(isinstance(n, Node) and n.op == "and" for _, _, n in walk(e)), all(not isinstance(n, Node) or n.op == "or" for _, _, n in walk(e)))
        if tier == "probe" and not (isinstance(flat := flatten(e), Node) and flat.op == "and" and all(isinstance(c, Leaf) for c in flat.children)):
            tier = "packed" if store else "columns"
    if tier == "mask":
        return finish(e, shrink(e, family, 1, "none", kind, seed))
    if tier == "union":
        return family.where(F.col("set_id").isin(set_ids(e))).select("elem").distinct()
    if tier == "probe":
        ids = [x.set_id for x in leaves(e)]
        return probe_stored(ids, store) if store else probe(ids, family)
    if tier == "packed":
        return evaluate_packed(e, store, r=r, mode=mode, cap=cap, ordered=ordered)
    r = planned_precision(family) if r is None else r
    if tier == "nodes":
        h = sketch_by_node(e, family, r, cap, ordered, kind, sampled=sampled)
        return finish(e, shrink(e, family, r, "global", kind, seed, h), how)
    return finish(e, shrink(e, family, r, mode, kind, seed), how)


def approximate(e: Expr | str, family: DataFrame, r: int, kind: str = "linear2") -> DataFrame:
    """A superset of the answer: all input elements whose prefix survives."""
    e = as_expr(e)
    return shrink(e, family, r, "global", kind).select("elem").distinct()


def cardinality(e: Expr | str, family: DataFrame, **options) -> DataFrame:
    return evaluate(e, family, **options).agg(F.count("*").alias("k"))


def occurrences(e: Expr | str, family: DataFrame, **options) -> DataFrame:
    """(set_id, elem) of the inputs whose element is in the answer."""
    e = as_expr(e)
    return family.where(F.col("set_id").isin(set_ids(e))).join(evaluate(e, family, **options), "elem", "left_semi").select("set_id", "elem")


def intersect_all(ids: list[str], family: DataFrame, r: int | None = None, kind: str = "linear2") -> DataFrame:
    """Intersection of m sets: prefixes that all of them have, candidates, exact check."""
    return evaluate(all_of(*ids), family, mode="global", r=r, kind=kind)


def intersect_two(a: str, b: str, family: DataFrame, c: int = 1, kind: str = "linear2") -> DataFrame:
    """Two sets, with hashes whose range follows the smaller one: of the larger, about a w-th part of the smaller's size comes along by chance."""
    e = all_of(a, b)
    return evaluate(e, family, mode="global", r=choose_r([min(sizes(e, family).values())], c), kind=kind)


def probe(ids: list[str], family: DataFrame, bits: int | None = None) -> DataFrame:
    """Uneven intersection: only the hash buckets that the smallest set touches are kept of the others."""
    card = sizes(all_of(*ids), family)
    order = sorted(dict.fromkeys(ids), key=lambda s: (card[s], s))
    b = max(1, balanced_b(max(card.values()))) if bits is None else bits
    hashed = L.with_hash(family).withColumn("bucket", prefix_hash("hs", b))
    out = hashed.where(F.col("set_id") == order[0]).select("bucket", "elem")
    for s in order[1:]:
        touched = hashed.where(F.col("set_id") == s).join(out.select("bucket").distinct(), "bucket", "left_semi")
        out = out.join(touched.select("bucket", "elem"), ["bucket", "elem"], "left_semi")
    return out.select("elem")


#: Buckets up to which a probe gives them to the scan of stored rows as a list.
LISTED_BUCKETS = 1024


def probe_stored(ids: list[str], store: L.Ladder) -> DataFrame:
    """Uneven intersection from a store: of each larger set only the stored buckets that the smaller side touches are read and
    unpacked, and then only the elements of prefixes that both have."""
    card, have = store.cards(ids), store.precisions(ids)
    order = sorted(dict.fromkeys(ids), key=lambda s: (card[s], s))
    r = choose_r([card[order[0]]])
    out = staged(store.dictionary.where(F.col("set_id") == order[0]).select("hs", "elem"), "probe")
    for s in order[1:]:
        if s not in have:
            return out.where(F.lit(False)).select("elem")
        rung = pick_rung(have[s], r)
        b = min(rung, balanced_b(card[s]))
        touched = out.select(prefix_hash("hs", b).alias("bucket")).distinct()
        rows = store.rungs.where((F.col("set_id") == s) & (F.col("r") == rung))
        few = [x["bucket"] for x in touched.limit(LISTED_BUCKETS + 1).collect()]
        rows = rows.where(F.col("bucket").isin(few)) if len(few) <= LISTED_BUCKETS else rows.join(touched, "bucket", "left_semi")
        both = staged(L.members(rows).select("set_id", "hv").join(out.select(prefix_hash("hs", rung).alias("hv")), "hv", "left_semi"), "probe")
        found = L.lookup(store.dictionary, both, rung, store.shard_bits).select("elem")
        out = staged(out.join(found, "elem", "left_semi"), "probe")
    return out.select("elem")


def sketch_by_node(e: Expr | str, family: DataFrame, r: int, cap: bool = True, ordered: bool = True, kind: str = "linear2", raw: bool = False, sampled: int = 0, record: list | None = None) -> DataFrame:
    """The root's sketch node by node, small sides of intersections first. A node that came out larger than twice its useful size is cut by
    the smallest side that is already there. With raw=True on elements themselves: the comparison-based algorithm.

    Inputs are read once, and intermediates are written, so each is computed once and cuts go by true sizes. Operators may have any
    number of children. `record` gets (node, op, size).
    """
    e = as_expr(e)
    known = None
    if sampled:
        from .protocol import sampled_sizes

        known = {x["node"]: x["estimate"] for x in sampled_sizes(e, family, sampled).collect()}
    info = {x["node"]: x for x in bounds(e, sizes(e, family), known)}
    rows = walk(e)
    kids = {me: [i for i, p, _ in rows if p == me] for me, _, _ in rows}
    value = F.col("elem") if raw else prefix_hash(mother_hash("elem", kind), r)
    base = staged(family.where(F.col("set_id").isin(set_ids(e))).select("set_id", value.alias("hv")).distinct(), "inputs")
    size_of = {x["set_id"]: x["n"] for x in base.groupBy("set_id").agg(F.count("*").alias("n")).collect()}

    def kept(df: DataFrame) -> tuple[DataFrame, int]:
        df = staged(df, "node")
        return df, df.count()

    def visit(me: int, cuts: list[tuple[int, DataFrame]]) -> tuple[DataFrame, int]:
        node, x = rows[me][2], info[me]
        if isinstance(node, Leaf):
            out, size = base.where(F.col("set_id") == node.set_id).select("hv"), size_of.get(node.set_id, 0)
        else:
            todo = sorted(kids[me], key=lambda i: (info[i]["psi_star"], info[i]["psi"], i)) if ordered and node.op == "and" else kids[me]
            out, size = visit(todo[0], cuts)
            for i in todo[1:]:
                if node.op == "minus" and not raw or node.op != "or" and not size:
                    continue
                other, _ = visit(i, [*cuts, (size, out)] if node.op == "and" else cuts)
                out, size = kept(out.union(other).distinct() if node.op == "or" else out.join(other, "hv", "left_semi" if node.op == "and" else "left_anti"))
        if cap and size > 2 * x["psi_star"] and cuts:
            out, size = kept(out.join(min(cuts, key=lambda c: c[0])[1], "hv", "left_semi"))
        if record is not None:
            record.append((me, x["op"], size))
        return out, size

    return visit(0, [])[0]


# -- the packed tier -------------------------------------------------------------------------------------

#: Buckets of a group, as a power of two: what one packed operation goes over.
PER_GROUP_BITS = 10


@dataclass
class EvalPlan:
    """What a packed evaluation will do."""

    expr: Expr
    cards: dict[str, int]
    r: int
    b: int
    rungs: dict[str, int]
    lanes: int = 1
    mode: str = "path"
    cap: bool = True
    ordered: bool = True
    balanced: bool = True

    @property
    def group_bits(self) -> int:
        return max(0, self.b - PER_GROUP_BITS)

    def steps(self) -> list[tuple]:
        """(step, node, op, set_id, rung, psi, psi_star, may_be_cut) in the order of evaluation."""
        out = []
        nodes = bounds(self.expr, self.cards)
        under_and = {0: False}
        for x in nodes[1:]:
            under_and[x["node"]] = under_and[x["parent"]] or nodes[x["parent"]]["op"] == "and"
        for step, x in enumerate(sorted(nodes, key=lambda x: x["visit"])):
            out.append((step, x["node"], x["op"], x["set_id"], self.rungs.get(x["set_id"]), x["psi"], x["psi_star"], self.cap and under_and[x["node"]] and x["psi"] > 2 * x["psi_star"]))
        return out

    def explain(self) -> str:
        lines = [f"{self.expr}: r={self.r} b={self.b} words of {64 * self.lanes} bits, {1 << self.group_bits} groups, shrink {self.mode}"]
        for step, node, op, sid, rung, psi, star, cut in self.steps():
            lines.append(f"  {step}. node {node} {op}{f' {sid} from rung {rung}' if sid else ''}: at most {psi}, useful {star}{', cut if larger' if cut else ''}")
        return "\n".join(lines)


def plan_packed(e: Expr | str, store: L.Ladder, r: int | None = None, mode: str = "path", lanes: int = 1, cap: bool = True, ordered: bool = True, balanced: bool = True, simple: bool = True) -> EvalPlan:
    """Repeated and absorbed parts go, equal operators become one; the catalog gives sizes and rungs."""
    e = simplify(as_expr(e)) if simple else flatten(as_expr(e))
    ids, w = set_ids(e), 64 * lanes
    cards, have = store.cards(ids), store.precisions(ids)
    r = choose_r([cards[x.set_id] for x in leaves(e)], w=min(WIDTH, w) if lanes == 1 else w) if r is None else r
    r = min(r, WIDTH)
    b = min(r, balanced_b(max(1, sum(cards.values())), w))
    return EvalPlan(e, cards, r, b, {s: pick_rung(p, r) for s, p in have.items()}, lanes, mode, cap, ordered, balanced)


#: Rows of packed_candidates that are no candidates: counters, by a negative leaf. Words read of stored set i are under WORDS_OF_SET - i.
WORD_OPS, WORDS_READ, SKETCH, CUTS, INTERMEDIATE, SKIPPED = -1, -2, -3, -4, -5, -6
WORDS_OF_SET = -100


def evaluate_group(plan: EvalPlan, inputs: dict[str, np.ndarray], f: int, ops: Ops) -> tuple[dict[int, np.ndarray], dict[int, int]]:
    """Sketch and shrink on matrices of packed runs, a line for each bucket of one hash range: what is left of each leaf, and counters.

    Sizes in the range are known, so order, cuts and stops go by them.
    """
    rows = walk(plan.expr)
    kids = {me: [i for i, p, _ in rows if p == me] for me, _, _ in rows}
    empty = np.full((len(next(iter(inputs.values()))), 1), layout(f).entry, np.uint64)
    size = {s: occupied(m, f) for s, m in inputs.items()}
    info = bounds(plan.expr, size)
    told = dict.fromkeys((SKETCH, CUTS, INTERMEDIATE, SKIPPED), 0)
    value: dict[int, np.ndarray] = {}
    known: dict[Expr, tuple[int, np.ndarray, int]] = {}  # subtrees that were evaluated whole, by where

    def union(parts: list[tuple[int, np.ndarray]]) -> tuple[np.ndarray, int]:
        """Pairwise, small ones first, or one after the other."""
        if plan.balanced:
            heap = [(n, i, m) for i, (n, m) in enumerate(parts)]
            heapq.heapify(heap)
            while len(heap) > 1:
                (_, i, x), (_, _, y) = heapq.heappop(heap), heapq.heappop(heap)
                z = packed_union(x, y, f, ops)
                heapq.heappush(heap, (occupied(z, f), i, z))
            return heap[0][2], heap[0][0]
        out = reduce(lambda x, y: packed_union(x, y, f, ops), [m for _, m in parts])
        return out, occupied(out, f)

    def visit(me: int, cuts: list[tuple[int, np.ndarray]]) -> tuple[np.ndarray, int]:
        node, x = rows[me][2], info[me]
        uncut = told[CUTS]
        if node in known and not cuts:
            before, out, n = known[node]
            value.update({me + i: value[before + i] for i in range(len(walk(node))) if before + i in value})
            return out, n
        if isinstance(node, Leaf):
            out, n = inputs[node.set_id], size[node.set_id]
        elif node.op == "or":
            parts = [visit(i, cuts)[::-1] for i in kids[me]]
            out, n = union(parts)
        else:
            todo = sorted(kids[me], key=lambda i: (info[i]["psi_star"], info[i]["psi"], i)) if plan.ordered and node.op == "and" else kids[me]
            out, n = visit(todo[0], cuts)
            for k, i in enumerate(todo[1:]):
                if not n:  # nothing can come of the rest
                    told[SKIPPED] += len(todo) - 1 - k
                    break
                other, _ = visit(i, [*cuts, (n, out)] if node.op == "and" else cuts)
                if node.op == "and":  # what is taken away isn't sure, so nothing is
                    out = packed_intersect(out, other, f, ops)
                    n = occupied(out, f)
        if plan.cap and cuts and n > 2 * x["psi_star"]:
            out = packed_intersect(out, min(cuts, key=lambda c: c[0])[1], f, ops)
            n = occupied(out, f)
            told[CUTS] += 1
        if told[CUTS] == uncut and not cuts:
            known[node] = me, out, n
        told[INTERMEDIATE] += n
        value[me] = out
        return out, n

    _, told[SKETCH] = visit(0, [])
    final, left, number = {0: value[0]}, {}, 0
    for me, parent, node in rows:
        if parent >= 0:
            # the taken-away side of a difference is judged by its parent too: what can't be in the answer needn't be taken away
            above = final[0] if plan.mode == "global" else final[parent]
            final[me] = packed_intersect(value[me], above, f, ops) if me in value else empty
        if isinstance(node, Leaf):
            left[number] = final[me]
            number += 1
    return left, told


def packed_candidates(plan: EvalPlan, store: L.Ladder) -> DataFrame:
    """Per leaf, the prefixes that survive sketch and shrink, (leaf, hv), on packed words; rows with a negative leaf are counters.

    Rungs of at least r bits are cut to r by the packed kernel and dealt to the query's buckets in the scan; what moves is packed rows. A
    group is a range of buckets, and so of the hash: the whole tree is evaluated in it.
    """
    ids, r, b, s = set_ids(plan.expr), plan.r, plan.b, plan.group_bits
    wanted = reduce(lambda a, c: a | c, [(F.col("set_id") == k) & (F.col("r") == v) for k, v in plan.rungs.items()]) if plan.rungs else F.lit(False)
    rungs = store.rungs.where(F.col("set_id").isin(ids) & F.col("r").isin(sorted(set(plan.rungs.values())))).where(wanted).select(*L.NAMES)

    def deal(batches):
        for batch in batches:
            t = pa.Table.from_batches([batch])
            for high in pa.compute.unique(t["r"]).to_pylist():
                rows = t.filter(pa.compute.equal(t["r"], high))
                ops, parts = Ops(plan.lanes), []
                wide = pa.compute.less_equal(rows["b"], r)
                if (some := rows.filter(wide)).num_rows:
                    for cut in L.cut(some, high - r, ops):
                        if not cut:
                            continue
                        got = L.rung_batch(cut)
                        ops.spend(len(L.words_of(got)[0]), layout(cut[0][6]), 28, 16)
                        parts += L._recoded(got, b)
                if (rest := rows.filter(pa.compute.invert(wide))).num_rows:  # finer buckets than the query's precision
                    parts += L._recoded(rest, b, high - r)
                _, length = L.words_of(rows)
                kinds, number = L._kinds(rows)
                read = {sid: int(n) for (sid,), n in zip(kinds, np.bincount(number, length, len(kinds)), strict=True)}
                # counters travel as rows without a field width
                parts += [(sid, -2, r, b, np.zeros(1, np.int64), np.zeros(1, np.int64), 0, np.array([words, int(ops.word_ops) if i == 0 else 0], np.uint64), np.array([2])) for i, (sid, words) in enumerate(read.items())]
                yield L.rung_batch(parts)

    def run(rows: pa.Table) -> pa.Table:
        ops, f = Ops(plan.lanes), field_bits(r - b)
        counters = rows.filter(pa.compute.equal(rows["f"], 0))
        rows = rows.filter(pa.compute.greater(rows["f"], 0)).select(L.NAMES)
        out: list[tuple[int, np.ndarray]] = []
        told: dict[int, int] = {}
        for sid, (words, spent) in zip(counters["set_id"].to_pylist(), counters["words"].to_pylist(), strict=True):
            told[WORDS_OF_SET - ids.index(sid)] = told.get(WORDS_OF_SET - ids.index(sid), 0) + words
            ops.word_ops += spent
        if rows.num_rows:
            bucket = np.unique(rows["bucket"].to_numpy())
            inputs = {sid: L.matrix_of(rows.filter(pa.compute.equal(rows["set_id"], sid)), bucket, f, ops) for sid in ids}
            left, counts = evaluate_group(plan, inputs, f, ops)
            told |= counts
            for number, m in left.items():
                v = unpack(m, f)
                i, j = np.nonzero(v != layout(f).none)
                out.append((number, (v[i, j] | bucket[i].astype(np.uint64) << np.uint64(r - b)).astype(np.int64) if r > b else bucket[i]))
        told |= {WORD_OPS: int(ops.word_ops), WORDS_READ: int(ops.words_read)}
        out += [(k, np.array([v], np.int64)) for k, v in told.items()]
        return pa.table([pa.array(np.repeat([k for k, _ in out], [len(v) for _, v in out]), pa.int32()), pa.array(np.concatenate([v for _, v in out]), pa.int64())], ["leaf", "hv"])

    grouped = rungs.mapInArrow(deal, L.RUNGS).withColumn("g", F.shiftrightunsigned("bucket", b - s)).groupBy("g")
    return grouped.applyInArrow(run, "leaf int, hv long")


def counters(candidates: DataFrame, ids: list[str]) -> dict[str, int]:
    """Sums of the counters of packed_candidates, and of the candidates themselves."""
    sums = {x["leaf"]: x["n"] for x in candidates.where("leaf < 0").groupBy("leaf").agg(F.sum("hv").alias("n")).collect()}
    names = {WORD_OPS: "word_ops", WORDS_READ: "words_in_kernels", SKETCH: "sketch", CUTS: "cuts", INTERMEDIATE: "intermediate", SKIPPED: "skipped"}
    out = {n: sums.get(k, 0) for k, n in names.items()}
    out |= {f"words_of {s}": sums.get(WORDS_OF_SET - i, 0) for i, s in enumerate(ids)}
    return out | {"candidates": candidates.where("leaf >= 0").count()}


def evaluate_packed(e: Expr | str, store: L.Ladder, r: int | None = None, mode: str = "path", lanes: int = 1, cap: bool = True, ordered: bool = True, balanced: bool = True) -> DataFrame:
    """The elements of the expression from a stored ladder.

    Surviving prefixes are written and counted: up to BROADCAST_ROWS of them go to the dictionary's scan as a broadcast, so its elements
    don't move; more are joined in a shuffle. Either way only shards that hold survivors are read.
    """
    plan = plan_packed(e, store, r, mode, lanes, cap, ordered, balanced)
    e, ids = plan.expr, set_ids(plan.expr)
    found = staged(packed_candidates(plan, store).where("leaf >= 0"), "candidates")
    cols = mask_columns(len(leaves(e)))
    bits = [(i, x.set_id, *[1 << (i % MASK_BITS) if i // MASK_BITS == j else 0 for j in range(len(cols))]) for i, x in enumerate(leaves(e))]
    table = store.rungs.sparkSession.createDataFrame(bits, "leaf int, set_id string, " + ", ".join(f"{c} long" for c in cols))
    prefixes = found.join(F.broadcast(table), "leaf").groupBy("set_id", "hv").agg(*_or(cols))
    mine, rows = L.pruned(store.dictionary.where(F.col("set_id").isin(ids)), found, plan.r, store.shard_bits)
    prefixes = F.broadcast(prefixes) if rows <= L.BROADCAST_ROWS else prefixes.hint("merge")
    return finish(e, mine.withColumn("hv", prefix_hash("hs", plan.r)).join(prefixes, ["set_id", "hv"]).select("hv", "elem", *cols))


def profile(e: Expr | str, family: DataFrame) -> dict:
    """m, n, k, k', union depth and bounds of a query."""
    e = as_expr(e)
    card = sizes(e, family)
    answer = evaluate(e, family)
    k = answer.count()
    kp = family.where(F.col("set_id").isin(set_ids(e))).join(answer, "elem", "left_semi").count()
    nodes = bounds(e, card)
    return {"m": len(leaves(e)), "n": sum(card[x.set_id] for x in leaves(e)), "k": k, "kprime": kp, "depth": union_depth(e), "psi_root": nodes[0]["psi"], "psi_star_sum": sum(x["psi_star"] for x in nodes)}
