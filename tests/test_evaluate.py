"""Expressions, bounds and exact evaluation against plain Python sets."""

import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from ladderset.functions.hashing import mother_hash, prefix_hash
from ladderset.operators import baselines as B
from ladderset.operators import evaluate as E
from ladderset.operators import ladder as L
from ladderset.operators import protocol as P
from ladderset.operators.packed import Ops, pack, unpack
from ladderset.plans import choose, cost
from ladderset.plans.choose import field_bits
from ladderset.plans.expr import Leaf, Node, balance, bounds, flatten, fold, leaves, parse, set_ids, simplify, union_depth, walk
from ladderset.sources.families import synthetic

NAMES = [f"s{i}" for i in range(7)]


def random_tree(rng, depth, ops=("or", "and")):
    if depth == 0 or rng.random() < 0.2:
        return Leaf(rng.choice(NAMES))
    return Node(rng.choice(ops), (random_tree(rng, depth - 1, ops), random_tree(rng, depth - 1, ops)))


def truth(e, sets):
    return fold(e, lambda _, x: set(sets.get(x.set_id, ())), set.__or__, set.__and__, set.__sub__)


@pytest.fixture(scope="module")
def data(spark):
    rng = random.Random(4)
    sets = {n: set(rng.sample(range(-300, 300), rng.choice([0, 1, 20, 150, 400]))) | {2**63 - 1, -(2**63)} for n in NAMES[:-1]}
    sets["s0"] = set(range(-200, 200))
    rows = [(n, x) for n, s in sets.items() for x in s]
    fam = spark.createDataFrame(rows, "set_id string, elem long").cache()
    return sets, fam


def test_bounds_and_rewrites():
    rng = random.Random(1)
    for _ in range(300):
        e = random_tree(rng, 4)
        sets = {n: set(rng.sample(range(60), rng.randint(0, 60))) for n in NAMES}
        rows = bounds(e, {n: len(s) for n, s in sets.items()})
        for x, (me, _, n) in zip(rows, walk(e)):
            assert x["node"] == me and x["psi"] >= len(truth(n, sets)) and x["psi_star"] <= x["psi"]
            if isinstance(n, Node) and n.op == "and":
                kids = [r["psi_star"] for r in rows if r["parent"] == me]
                assert kids[0] == kids[1]
        for f in (flatten, balance, simplify):
            assert truth(f(e), sets) == truth(e, sets)
        assert union_depth(balance(e)) <= union_depth(e) + 3 and parse(str(e)) == e


@pytest.mark.parametrize("seed", range(5))
def test_random_trees(data, seed):
    sets, fam = data
    rng = random.Random(seed)
    e = random_tree(rng, 3, ("or", "and", "and", "minus"))
    want = sorted(truth(e, sets))
    for options in ({"mode": "path", "r": 8}, {"mode": "global", "r": 10}, {"r": 9, "how": "nested"}, {"tier": "mask"}, {"tier": "nodes", "r": 9}):
        assert sorted(r[0] for r in E.evaluate(e, fam, **options).collect()) == want, (str(e), options)


def stored(fam, **options):
    ladder = L.build_ladder(fam, **options)
    return replace(ladder, rungs=ladder.rungs.cache(), dictionary=ladder.dictionary.cache())


def test_packed_tier(data):
    sets, fam = data
    ladder = stored(fam, shard_bits=1)
    for text in ("(s0 & s1) | (s2 & s3)", "(s0 - s1) & (s2 | s4)", "s0 & s6", "s5", "((s0 | s1) & s2) | ((s0 | s1) & s3)"):
        for r in (2, 9, 40):
            got = sorted(x[0] for x in E.evaluate_packed(text, ladder, r=r, mode=("path", "global")[r == 9], lanes=(1, 4)[r == 40], cap=r != 9, ordered=r != 2, balanced=r != 9).collect())
            assert got == sorted(truth(parse(text), sets)), (text, r)
    assert sorted(x[0] for x in E.evaluate("s0 & s2", fam, tier="packed", store=ladder).collect()) == sorted(sets["s0"] & sets["s2"])


def test_groups_against_sets():
    """Sketch and shrink of random trees on packed matrices: nothing useful goes, cuts act, and less comes out of more switches."""
    rng = random.Random(11)
    f, spent, cuts, skipped = field_bits(9), {True: 0, False: 0}, 0, 0
    for _ in range(150):
        e = simplify(random_tree(rng, 4, ("or", "and", "and", "minus")))
        sets = [{n: set(rng.sample(range(400), rng.choice([0, 2, 10, 120]))) for n in NAMES} for _ in range(3)]
        inputs = {}
        for n in set_ids(e):
            runs = [sorted(s[n]) for s in sets]
            m = np.full((3, max(1, max(map(len, runs)))), (1 << f) - 1, np.uint64)
            for i, r in enumerate(runs):
                m[i, : len(r)] = r
            inputs[n] = pack(m, f)
        for act in (True, False):
            plan = E.EvalPlan(e, {}, 9, 0, {}, 1, rng.choice(["path", "global"]), act, act, act)
            left, told = E.evaluate_group(plan, inputs, f, Ops())
            spent[act] += told[E.INTERMEDIATE]
            cuts, skipped = cuts + act * told[E.CUTS], skipped + told[E.SKIPPED]
            assert act or not told[E.CUTS]
            for i, s in enumerate(sets):
                kept = [{int(v) for v in unpack(left[j], f)[i] if v != (1 << f) - 1} for j in range(len(left))]
                assert all(k <= s[x.set_id] for k, x in zip(kept, leaves(e)))
                got = fold(e, lambda j, _: kept[j], set.__or__, set.__and__, set.__sub__)
                assert got == truth(e, s), (str(e), act)
    assert cuts > 20 and skipped > 20 and spent[True] < spent[False]


def test_a_cut_acts_where_a_small_side_stands_beside_a_union(spark):
    fam = spark.range(4000).select(F.expr("CASE WHEN id % 2 = 0 THEN 'A' ELSE 'B' END").alias("set_id"), F.col("id").alias("elem")).union(spark.range(9).select(F.lit("s"), F.col("id") * 400))
    ladder = stored(fam)
    cost = {}
    for cap in (True, False):
        plan = E.plan_packed("(A | B) & s", ladder, cap=cap)
        cost[cap] = E.counters(E.packed_candidates(plan, ladder), ["A", "B", "s"])
        sizes = []
        E.sketch_by_node("(A | B) & s", fam, 30, cap=cap, record=sizes)
        assert dict((n, k) for n, _, k in sizes)[1] == (9 if cap else 4000)
    assert cost[True]["cuts"] and not cost[False]["cuts"] and cost[True]["intermediate"] * 5 < cost[False]["intermediate"]
    assert sorted(x[0] for x in E.evaluate("(A | B) & s", fam, tier="nodes", sampled=2).collect()) == list(range(0, 3600, 400))


def test_probe_and_two_sets(spark, data):
    sets, fam = data
    ladder = stored(fam)
    for a, b in (("s0", "s2"), ("s1", "s0"), ("s6", "s0")):
        want = sorted(sets.get(a, set()) & sets.get(b, set()))
        assert sorted(x[0] for x in E.probe_stored([a, b], ladder).collect()) == want
        assert sorted(x[0] for x in E.intersect_two(a, b, fam).collect()) == want


def test_plan_explains_itself(data):
    _, fam = data
    plan = E.plan_packed("(s0 | s0) & (s0 | s1) & s2", L.build_ladder(fam))
    assert str(plan.expr) == "(s0 & s2)" and "from rung" in plan.explain() and len(plan.steps()) == 3


def test_more_than_sixty_two_leaves(data):
    sets, fam = data
    text = " | ".join(f"(s{i % 6} & s{(i + 1) % 6})" for i in range(40))
    assert sorted(r[0] for r in E.evaluate(text, fam, r=9).collect()) == sorted(truth(parse(text), sets))


def test_hand_checked_shrink(spark):
    fam = spark.createDataFrame([("A", 1), ("A", 2), ("A", 3), ("B", 2), ("B", 5), ("C", 3), ("C", 7)], "set_id string, elem long")
    count = {m: E.shrink("(A & B) | C", fam, 62, m).agg(F.sum(F.expr("bit_count(m0)"))).first()[0] for m in ("global", "path")}
    assert count == {"global": 5, "path": 4}
    assert sorted(r[0] for r in E.evaluate("(A & B) | C", fam).collect()) == [2, 3, 7]


def test_hash_values_and_prefixes(spark):
    keys = spark.createDataFrame([(0,), (1,), (2,), (3,), (2**63 - 1,), (-(2**63),), (-1,)], "k long")
    rows = keys.select("k", mother_hash("k").alias("h"), mother_hash("k", "tabulation").alias("t"), prefix_hash(mother_hash("k"), 10).alias("p")).collect()
    assert [r["h"] for r in rows[:4]] == [26511699538783, 2369807455320702149, 127902382661961259, 2497683326283124625]
    assert all(0 <= r["h"] < 2**62 and 0 <= r["t"] < 2**62 and r["p"] == r["h"] >> 52 for r in rows)


def test_rungs():
    assert choose.rung_schedule(100) == [8, 9, 11, 15, 23, 39, 62]
    assert choose.pick_rung(choose.rung_schedule(100), 12) == 15 and choose.pick_rung(choose.rung_schedule(100), 49) == 62
    assert all(any(x >= r for x in choose.rung_schedule(n)) for n in (1, 5, 100, 10**6) for r in range(1, 63))


def test_false_candidates_fall_with_precision(spark):
    fam = synthetic(spark, "controlled", 3000, 3, 40)
    kept = []
    for r in (10, 12, 14, 18):
        kept.append(E.shrink("s0 & s1 & s2", fam, r, "global", "tabulation").agg(F.sum(F.expr("bit_count(m0)"))).first()[0])
    assert kept == sorted(kept, reverse=True) and kept[-1] - 120 <= 3 * cost.false_bound(3080, 18) + 10


def test_costs_behave():
    assert cost.predicted_speedup(4096) > cost.predicted_speedup(512) > cost.predicted_speedup(64)
    for n in (10**5, 10**7):
        for m in (2, 4, 8):
            assert cost.gap(n, m, 10, 64) <= 2 * cost.gap_limit(m, 64) and cost.cost_lower(n, m, 10, 64) <= cost.cost_intersection(n, m, 10, 64)
    assert cost.cost_io(10**7, 3, 10, 64, 128) < cost.cost_intersection(10**7, 3, 10, 64)


def test_gadgets(spark):
    unique = P.unique_intersection(spark, 60, 3)
    assert unique.count() == 62 and E.intersect_all(["s0", "s1", "s2"], unique).collect()[0][0] == 0
    assert not P.is_disjoint(["s0", "s1"], unique).first()[0] and P.is_disjoint(["s0", "s1"], synthetic(spark, "disjoint", 50)).first()[0]
    e = P.equality_instance(parse("(a & b) | (c & d)"))
    assert {x for x in str(e).replace("(", " ").replace(")", " ").split() if x[0] == "s"} == {"s0", "s1"}
    nested = synthetic(spark, "nested", 64, 3)
    assert nested.groupBy("set_id").count().orderBy("set_id").collect()[2][1] == 16


def test_baselines(data):
    sets, fam = data
    text = "(s0 & s1) | (s2 & s3)"
    want = sorted(truth(parse(text), sets))
    for f in (B.merge_sorted, B.hash_probe, B.sql_operators, B.full_hashing, B.wide_sketch, B.bounded_tree):
        assert sorted(r[0] for r in f(text, fam).collect()) == want
    both = sorted(sets["s0"] & sets["s2"])
    for f in (B.gallop, B.arrays, E.probe):
        assert sorted(r[0] for r in f(["s0", "s2"], fam).collect()) == both


def answer(text, ladder):
    return sorted(x[0] for x in E.evaluate_packed(text, ladder).collect())


def test_ladder_store(spark, data, tmp_path):
    sets, fam = data
    path = f"file://{tmp_path}/l"
    for _ in range(2):  # writing again replaces
        L.write_ladder(fam, path, "one", shard_bits=1)
        L.write_ladder(fam.where("set_id = 's1'"), path, "two", shard_bits=1)
    ladder = L.read_ladder(spark, path, "one")
    assert ladder.dictionary.count() == fam.count() and L.versions(spark, path, "one") == [0, 1]
    assert answer("s0 & s1", ladder) == sorted(sets["s0"] & sets["s1"])
    scan = ladder.rungs.where("r = 62")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(r" in scan
    with pytest.raises(FileNotFoundError):
        L.read_ladder(spark, path, "three")


def test_a_store_that_shrinks_loses_its_old_rungs(spark, tmp_path):
    path = f"file://{tmp_path}/l"
    for a, b in ((3000, 429), (10, 7)):
        fam = spark.range(a).select(F.lit("A").alias("set_id"), F.col("id").alias("elem")).union(spark.range(b).select(F.lit("B"), F.col("id") + 5))
        L.write_ladder(fam, path, "f")
        assert answer("A & B", L.read_ladder(spark, path, "f")) == list(range(5, min(a, b + 5)))


def test_a_store_keeps_its_hash(spark, tmp_path):
    path = f"file://{tmp_path}/l"
    fam = synthetic(spark, "controlled", 3000, 2, 429)
    L.write_ladder(fam, path, "f", kind="tabulation", seed=3)
    assert answer("s0 & s1", L.read_ladder(spark, path, "f")) == list(range(429))
    with pytest.raises(ValueError):
        L.read_ladder(spark, path, "f", kind="linear2")


@pytest.mark.parametrize("most", [1, 2, 8])
def test_appending_gives_the_ladder_of_the_whole(spark, tmp_path, most):
    """New sets, sets that outgrow their shape, sets that stay in shape, and repeated elements; several times in a row, through a store that
    writes whole versions always, now and then, or not at all."""
    path = f"file://{tmp_path}/l"
    parts = [{"A": range(100), "B": range(0, 5000, 2), "t": range(3)}, {"A": range(50, 600), "B": range(1, 40, 2), "C": range(90, 140), "t": range(70)}, {"B": range(0, 9000, 3), "C": range(300)}, {"B": range(5), "C": range(295, 310)}]
    fams = [spark.createDataFrame([(s, x) for s, xs in p.items() for x in xs], "set_id string, elem long") for p in parts]
    L.write_ladder(fams[0], path, "f", shard_bits=2)
    for k in (1, 2, 2, 3):  # doing a version again changes nothing
        L.append_to_store(spark, path, "f", fams[k], version=k, most=most)
    got = L.read_ladder(spark, path, "f")
    whole = fams[0].union(fams[1]).union(fams[2]).union(fams[3]).distinct()
    want = L.build_ladder(whole, shard_bits=2)
    rows = lambda x: sorted(map(tuple, x.collect()))
    assert rows(L.members(got.rungs).distinct()) == rows(L.members(want.rungs))
    assert rows(got.catalog.select("set_id", "card", "b", F.col("precisions").cast("string"))) == rows(want.catalog.select("set_id", "card", "b", F.col("precisions").cast("string")))
    assert rows(got.dictionary) == rows(want.dictionary)
    slices = got.rungs.groupBy("set_id", "r", "bucket").count().where("count > 1").count()
    assert slices == 0 if most == 1 else slices > 0
    assert answer("(A & B) | (C & t)", got) == sorted(set(range(600)) & (set(range(0, 5000, 2)) | set(range(1, 40, 2)) | set(range(0, 9000, 3)) | set(range(5))) | set(range(70)))
    assert sorted(x[0] for x in E.probe_stored(["t", "B"], got).collect()) == sorted(set(range(70)) & (set(range(0, 5000, 2)) | set(range(1, 40, 2)) | set(range(0, 9000, 3)) | set(range(5))))
    kept = L.versions(spark, path, "f")
    assert kept[-1] == 3 and (kept == [2, 3] if most == 1 else 0 in kept or most == 2)


def test_rows_of_packed_operations(spark, data):
    sets, fam = data
    rungs = L.build_rungs(fam, schedule=[20], shard_bits=1).cache()
    hv = {n: set(x[0] for x in fam.where(F.col("set_id") == n).select(prefix_hash(mother_hash("elem"), 20)).collect()) for n in NAMES}
    for op, f in (("or", set.union), ("and", set.intersection)):
        for b in (None, 0, 7):
            got = [x[0] for x in L.members(L.rebalance(L.combine(rungs, "s0", "s2", op, b), 60)).select("hv").collect()]
            assert sorted(got) == sorted(f(hv["s0"], hv["s2"])), (op, b)
    cut = [tuple(x) for x in L.members(L.truncate(rungs, 6)).select("set_id", "hv").collect()]
    assert sorted(cut) == sorted({(n, v >> 6) for n, vs in hv.items() for v in vs})


def test_false_candidates_stay_below_their_bound_over_seeds(spark):
    """Mean over seeds of the hash: every false occurrence collides with another of the inputs."""
    n, k, m = 3000, 40, 3
    fam = synthetic(spark, "controlled", n, m, k).cache()
    for r in (12, 15):
        kept = [E.shrink("s0 & s1 & s2", fam, r, "global", "tabulation", seed).agg(F.sum(F.expr("bit_count(m0)"))).first()[0] for seed in range(1, 7)]
        false = sum(kept) / len(kept) - k * m
        assert 0 <= false <= cost.false_bound(n + (m - 1) * k, r)


def test_space_of_ladders(spark):
    """A rung takes a few times its card (r - log card + log W) bits, a ladder a bounded number of words an element, all precisions far more."""
    per = []
    for n in (1 << 11, 1 << 14):
        fam = synthetic(spark, "disjoint", n, 1).cache()
        rungs = L.build_rungs(fam).groupBy("r").agg(F.sum(F.size("words")).alias("words")).collect()
        for x in rungs:
            bound = n * (x["r"] - np.log2(n) + 6)
            assert cost.information_bits(n, x["r"]) <= x["words"] * 64 <= 6 * bound, (n, x)
        per.append(sum(x["words"] for x in rungs) / n)
        every = L.build_rungs(fam, schedule="all").agg(F.sum(F.size("words"))).first()[0]
        assert every > 5 * sum(x["words"] for x in rungs)
    assert max(per) < 6 and abs(per[0] - per[1]) < 1


def test_counted_runs_lie_between_the_bounds(spark):
    """Words read are no less than the lower bound says, and operations no more than a constant times the upper one, for all sizes alike."""
    ratios = []
    for n in (4_000, 32_000):
        for m in (2, 4):
            fam = synthetic(spark, "controlled", n, m, 10).cache()
            ladder, ids = L.build_ladder(fam), [f"s{i}" for i in range(m)]
            plan = E.plan_packed(" & ".join(ids), ladder)
            c = E.counters(E.packed_candidates(plan, ladder), ids)
            size = sum(plan.cards.values())
            assert sum(c[f"words_of {s}"] for s in ids) >= cost.lower_parts(size, m, 10, 64)[0]
            assert c["candidates"] >= 10 * m and c["sketch"] >= 10
            ratios.append(c["word_ops"] / cost.cost_intersection(size, m, 10, 64))
            assert cost.gap(size, m, 10, 64) <= 2 * cost.gap_limit(m, 64)
    assert max(ratios) < 2 * min(ratios), ratios


def test_gallop_counts_comparisons(spark):
    """Few for a small set in a large one: about twice the logarithm of the ratio each, and far fewer than the larger set has elements."""
    fam = synthetic(spark, "skewed", 1 << 14, 2, 64)
    spent = B.gallop(["s0", "s1"], fam, shard_bits=3, counts=True).agg(F.sum("elem")).first()[0]
    assert 64 <= spent <= 64 * (2 * np.log2((1 << 14) / 64) + 6) < 1 << 14
    assert sorted(r[0] for r in B.gallop(["s0", "s1"], fam).collect()) == [i * 256 for i in range(64)]


def test_strings_are_told_apart_at_the_finish(spark):
    rng = random.Random(3)
    sets = {n: {f"word {rng.randrange(900)}" for _ in range(400)} for n in NAMES[:4]}
    fam = spark.createDataFrame([(n, x) for n, s in sets.items() for x in s], "set_id string, elem string")
    for text in ("(s0 & s1) | (s2 & s3)", "(s0 | s1) - s2"):
        assert sorted(r[0] for r in E.evaluate(text, fam, kind="xxhash", r=6).collect()) == sorted(truth(parse(text), sets))
