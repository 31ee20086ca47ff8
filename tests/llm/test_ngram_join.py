"""The n-gram Jaccard join against brute force, with tiny blocks so that popular n-grams are split."""

import collections
import random
import re

import pytest

from ladderset.llm import ngram_join


def brute(rows, k, num, den):
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[d] = frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    label = {d: d for d in sets}

    def root(x):
        while label[x] != x:
            x = label[x]
        return x

    where = collections.defaultdict(list)
    for d in sets:
        for e, n in collections.Counter(e for s in sets[d] for e in where[s]).items():
            if den * n >= num * (len(sets[d]) + len(sets[e]) - n) and root(d) != root(e):
                a, b = root(d), root(e)
                label[max(a, b)] = min(a, b)
        for s in sets[d]:
            where[s].append(d)
    return {d: (len(sets[d]), root(d)) for d in sets}


def corpus(n):
    rng, rows = random.Random(3), []
    words = [f"w{i}" for i in range(30)]
    for i in range(n):
        if rows and rng.random() < 0.8:
            w = (rng.choice(rows[-60:])[1] or "").split()
            for _ in range(rng.randint(0, 2)):
                if w:
                    w[rng.randrange(len(w))] = rng.choice(words)
            rows.append((i, " ".join(w)))
        else:
            rows.append((i, " ".join(rng.choices(words, k=rng.choice([0, 1, 2, 3, 20, 60])))))
    rows += [(n, None), (n + 1, ""), (n + 2, "A b\x0bC"), (n + 3, "a B c"), (n + 4, "long " * 30000)]
    return rows


def test_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK", 40)
    rows = corpus(700)
    docs = spark.createDataFrame([(*r, 1, "x", 2) for r in rows], "doc_id long, text string, n int, key string, cid int")
    got = {r[0]: (r[1], r[2]) for r in ngram_join.similar_groups(docs, 3, 90, 100).collect()}
    assert got == brute(rows, 3, 90, 100)


def test_repeats_nulls_and_empty(spark):
    docs = spark.createDataFrame([(1, "a b c d"), (1, "a b c d"), (2, "A B C D"), (None, "a b c d"), (None, "only here now")], "doc_id long, text string")
    got = sorted(map(tuple, ngram_join.similar_groups(docs, 3, 90, 100).collect()), key=str)
    assert got == sorted([(1, 2, 1), (1, 2, 1), (2, 2, 1), (None, 2, 1), (None, 1, None)], key=str)
    assert ngram_join.similar_groups(docs.limit(0), 3, 90, 100).count() == 0


@pytest.mark.parametrize("n", [0, 1])
def test_components_of_a_long_chain(spark, n):
    from ladderset.llm.support import Scratch

    edges = spark.createDataFrame([(i, i + 1) for i in range(40 * n)], "a long, b long")
    got = {r[0]: r[1] for r in ngram_join.components(edges, Scratch(spark, "t")).collect()}
    assert got == dict.fromkeys(range(41), 0) if n else not got


def brute_pairs(rows, k, num, den):
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[d] = frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    ids = sorted(d for d in sets if sets[d])
    return sets, [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b])]


def near_copies():
    """A group in which nearly every two texts are linked, wider than a tile, beside the mixed corpus."""
    words = [f"n{i}" for i in range(200)]
    return [(10_000 + i, " ".join(w if j != 2 * i else f"x{i}" for j, w in enumerate(words))) for i in range(100)] + corpus(250)


def test_links_and_pairs_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK", 40)
    monkeypatch.setattr(ngram_join, "TILE", 16)
    rows = near_copies()
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets, links = brute_pairs(rows, 3, 90, 100)
    count = collections.Counter(x for p in links for x in p)
    assert min(count[10_000 + i] for i in range(100)) == 99
    got = {r[0]: tuple(r)[1:] for r in ngram_join.similar_links(docs, 3, 90, 100).collect()}
    assert got == {d: (*v, count[d]) for d, v in brute(rows, 3, 90, 100).items()}
    rep = {}
    for d in sorted(sets):
        rep.setdefault(sets[d], d)
    pairs, members = ngram_join.similar_pairs(docs, 3, 90, 100)
    found = [tuple(r) for r in pairs.collect()]
    assert len(found) == len(set(found)) and set(found) == {(a, b) for a, b in links if rep[sets[a]] == a and rep[sets[b]] == b and sets[a] != sets[b]}
    assert dict(map(tuple, members.collect())) == {d: rep[x] for d, x in sets.items() if x}


def test_links_of_repeats_and_nulls(spark):
    docs = spark.createDataFrame([(1, "a b c d"), (1, "a b c d"), (2, "A B C D"), (None, "a b c d"), (None, "only here now"), (3, None)], "doc_id long, text string")
    got = sorted(map(tuple, ngram_join.similar_links(docs, 3, 90, 100).collect()), key=str)
    assert got == sorted([(1, 2, 1, 1), (1, 2, 1, 1), (2, 2, 1, 1), (None, 2, 1, 2), (None, 1, None, None), (3, 0, 3, 0)], key=str)
    assert ngram_join.similar_links(docs.limit(0), 3, 90, 100).count() == 0
