"""Exact and line deduplication, quality rules and toxicity against plain Python, with odd rows and clashing columns."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from ladderset.llm import exact_dedup, line_dedup, quality_rules, toxicity

SCHEMA = "doc_id long, text string, n int, kept string, size int, pos int, is_toxic int"


def table(spark, pairs):
    return spark.createDataFrame([(d, t, 1, "x", 2, 3, 4) for d, t in pairs], SCHEMA)


PAIRS = [(1, "a"), (2, None), (3, ""), (4, "a"), (5, "b" * 300_000), (6, "b" * 300_000), (7, "b" * 299_999 + "c"), (4, "a"), (None, "a"), (None, None), (8, "A"), (9, "é"), (10, "é"), (None, "x y"), (None, "x y"), (None, "alone")]


def test_exact_groups(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "LARGE_GROUP", 3)
    for pairs in (PAIRS, PAIRS * 9):
        got = [tuple(r) for r in exact_dedup.exact_groups(table(spark, pairs), digest=True).collect()]
        groups = Counter(t or "" for _, t in pairs)
        best = {}
        for d, t in pairs:
            best[t or ""] = max(best.get(t or "", -1), -1 if d is None else d)
        named = [(d, None if best[t or ""] < 0 else best[t or ""], groups[t or ""], hashlib.sha256((t or "").encode()).hexdigest()) for d, t in pairs]
        assert sorted((r[:3] + r[4:] for r in got), key=str) == sorted(named, key=str)
        kept = [r for r in got if r[3]]
        assert len(kept) == len({r[4] for r in got}) == len({r[4] for r in kept}) and all(r[0] == r[1] for r in kept)
    assert exact_dedup.exact_groups(table(spark, [])).count() == 0


def key(line):
    return re.sub("[A-Z]", lambda m: m[0].lower(), line.strip(" \t\n\x0b\x0c\r"))


def test_line_dedup(spark):
    rng = random.Random(2)
    lines = ["", " ", "Common ", "\tcommon", "COMMON\r", "rare", "é", "x y", "Éé", "other\x0b"]
    pairs = [(i, "\n".join(rng.choices(lines, k=rng.randint(0, 6)))) for i in range(40)]
    pairs += [(50, None), (51, ""), (52, "common\n" * 3000 + "end"), (None, "common"), (None, "common")]
    for least in (1, 5, 30):
        got = line_dedup.drop_common_lines(table(spark, pairs), min_documents=least)
        assert got.columns == [*SCHEMA.replace(",", "").split()[::2], "n_lines", "n_dropped"]
        seen = Counter(k for _, t in pairs for k in {key(x) for x in (t or "").split("\n")})
        drop = {k for k, n in seen.items() if k and n >= least}
        want = []
        for d, t in pairs:
            parts = (t or "").split("\n")
            kept = [x for x in parts if key(x) not in drop]
            want.append((d, "\n".join(kept), len(parts), len(parts) - len(kept)))
        assert sorted(map(tuple, got.select("doc_id", "text", "n_lines", "n_dropped").collect()), key=str) == sorted(want, key=str)
    assert line_dedup.drop_common_lines(table(spark, [])).count() == 0


def test_line_dedup_carries_columns_of_any_name(spark):
    rows = [(f"same line\nown {i}", 77, 1, 2, i, "p", 9.5, 3) for i in range(12)]
    docs = spark.createDataFrame(rows, "text string, k1 int, dropped int, n_lines int, doc_id long, row string, `a.b` double, hit int")
    got = line_dedup.drop_common_lines(docs)
    assert got.columns == ["text", "k1", "dropped", "doc_id", "row", "a.b", "hit", "n_lines", "n_dropped"]
    assert sorted(map(tuple, got.collect())) == sorted((f"own {i}", 77, 1, i, "p", 9.5, 3, 2, 1) for i in range(12))


def test_line_keys_lower_ascii_alone(spark):
    lines = ["ABC z", "É A", "ÉA", "é a", "İX", "ΣΑΣ Q", "“Zitat” – À", "Ⅷ B", "ß Ÿ", "\u00a0Ab\u00a0", "Ω𐐀C"]
    rows = spark.createDataFrame([(x,) for x in lines], "x string").select("x", line_dedup.line_key(line_dedup.F.col("x")).alias("k")).collect()
    assert all(r["k"] == key(r["x"]) for r in rows)


def statistics(t):
    t = t or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    windows = {}
    for i in range(len(w) - 4):
        windows.setdefault(tuple(w[i : i + 5]), []).append(i)
    covered = {j for at in windows.values() if len(at) > 1 for i in at for j in range(i, i + 5)}
    seen, again = set(), 0
    for line in t.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            again += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), again, len(covered)


def test_quality_rules(spark, monkeypatch):
    monkeypatch.setattr(quality_rules, "SLICE_BYTES", 500)
    rng = random.Random(3)
    pairs = [(i, "".join(rng.choices(["a ", "b ", "\n", "é", "  ", "one two three four five ", "x\n", "$$$ "], k=rng.randint(0, 40)))) for i in range(300)]
    pairs += [(None, None), (1, ""), (2, "word " * 50_000), (3, "THE END!! " * 40), (4, " ".join(f"w{i}" for i in range(500)))]
    got = quality_rules.apply_rules(table(spark, pairs), digest=True)
    rows = got.collect()
    assert len(rows) == len(pairs) and "pos" in got.columns
    for r in rows:
        s = statistics(r["text"])
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == s
        failed = s[0] < 10 or 100 * s[4] > 20 * s[0]
        assert r["base_failed"] == failed and not (failed and r["kept"])
    plain = {(r["doc_id"], r["text"]): r["kept"] for r in quality_rules.apply_rules(table(spark, pairs)).collect()}
    assert all(plain[r["doc_id"], r["text"]] == r["kept"] for r in rows) and plain[4, pairs[-1][1]]
    assert quality_rules.apply_rules(table(spark, [])).count() == 0


def test_quality_rules_replace_clashing_columns(spark):
    docs = spark.createDataFrame([(1, "few words", 5, "x", 2.5)], "doc_id long, text string, n_words int, kept string, `a.b` double")
    got = quality_rules.apply_rules(docs, digest=True)
    assert got.columns[:4] == ["doc_id", "text", "a.b", "kept"] and got.first()["n_words"] == 2
    assert quality_rules.apply_rules(docs).columns == ["doc_id", "text", "n_words", "a.b", "kept"]


def test_survivors_take_their_statistics_along():
    import pyarrow as pa

    from ladderset.llm.textscan import buffer_of

    rng = random.Random(6)
    texts = ["".join(rng.choices(["a b ", "é\n", "x\nx\n", "one two three four five ", ""], k=rng.randint(0, 12))) for _ in range(80)]
    stats = quality_rules.TextStats(*buffer_of(pa.array(texts)))
    assert stats.lines and len(stats.words.start)
    rows = np.array(sorted(rng.sample(range(80), 33)))
    got, fresh = stats.take(rows), quality_rules.TextStats(*buffer_of(pa.array([texts[i] for i in rows])))
    for name in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines", "n_repeat_words"):
        assert (getattr(got, name) == getattr(fresh, name)).all(), name


def test_any_order_of_rules_gives_one_verdict():
    import pyarrow as pa

    from ladderset.llm.textscan import buffer_of

    rng = random.Random(4)
    texts = ["".join(rng.choices(["a b c ", "d\n", "e f g h i j k l ", "## ", "LOUD!! "], k=rng.randint(0, 30))) for _ in range(300)]
    buf, off = buffer_of(pa.array(texts))
    want = None
    for _ in range(5):
        rules = rng.sample(quality_rules.RULES, len(quality_rules.RULES))
        got = quality_rules.cascade(quality_rules.TextStats(buf, off), rules).tolist()
        assert want in (None, got)
        want = got
    ordered = quality_rules.order_rules(texts, quality_rules.RULES)
    rates = [s / max(c, 1e-12) for _, c, s in ordered]
    assert rates == sorted(rates, reverse=True)


def test_chain_learns_and_generalises():
    rng = np.random.default_rng(5)
    texts, y = [], []
    for _ in range(900):
        bad, rude = rng.random() < 0.3, rng.random() < 0.25
        w = [f"w{x}" for x in rng.integers(0, 400, 40)]
        if bad:
            w += [f"junk{rng.integers(0, 4)}"] * 2
        if rude:
            w.insert(3, f"rude{rng.integers(0, 5)}")
        texts.append(" ".join(w))
        y.append((bad, rude))
    import pyarrow as pa

    from ladderset.llm.textscan import buffer_of

    y = np.array(y, int)
    row, slot = toxicity.word_features(*buffer_of(pa.array(texts)))
    train = row < 600
    chain = toxicity.fit_chain(row[train], slot[train], y[:600], ["bad", "rude"], np.arange(600) % 3)
    p = chain.probabilities(row, slot, 900)[600:]
    for k in range(2):
        hit = p[:, k] >= chain.thresholds[k]
        assert (hit == (y[600:, k] > 0)).mean() > 0.97


def test_held_out_toxic_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = toxicity.category_labels(spark.read.parquet("/root/testdata/sf0.1/labels.parquet"))
    chain = toxicity.train_toxicity(docs, labels.where("doc_id % 4 > 0"), toxicity.CATEGORIES)
    rest = labels.where("doc_id % 4 = 0").select("doc_id", "toxic")
    rows = toxicity.score_toxicity(docs.join(rest, "doc_id"), chain).collect()
    hit = sum(r["is_toxic"] and r["toxic"] for r in rows)
    assert hit / sum(r["toxic"] for r in rows) > 0.85 and hit / sum(r["is_toxic"] for r in rows) > 0.95


def test_toxicity_odd_rows(spark):
    docs = table(spark, [(i, "you fool" if i % 2 else "kind words") for i in range(40)] + [(None, None), (50, ""), (1, "you fool")])
    labels = spark.createDataFrame([(i, i % 2, None if i > 30 else i % 2) for i in range(40)], "doc_id long, a int, b int")
    chain = toxicity.train_toxicity(docs, labels, ["a", "b"])
    out = toxicity.score_toxicity(docs, chain)
    assert out.count() == 43 and "is_toxic" in out.columns
    none = toxicity.train_toxicity(docs.limit(0), labels, ["a"])
    assert toxicity.score_toxicity(docs, none).where("is_a").count() == 0
    assert toxicity.score_toxicity(docs.limit(0), chain).count() == 0


@pytest.mark.parametrize("p,y", [([0.9, 0.8, 0.1], [1, 1, 0]), ([0.5, 0.5], [1, 0])])
def test_threshold(p, y):
    cut = toxicity.best_threshold(np.array(p), np.array(y))
    assert 0.2 <= cut <= 0.9
