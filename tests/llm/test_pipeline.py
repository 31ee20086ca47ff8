"""The pipeline's stages, each against plain Python on its own input."""

import re
from collections import Counter

import pytest

pipeline = pytest.importorskip("corpus_pipeline")
SF = "/root/testdata/sf0.001"


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in pipeline.STAGES:
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        out = stage(spark, docs, SF)
        rows = out.collect()
        seen[name] = rows
        if name != "best_fit_packing":
            assert out.columns == columns
            after = {r["doc_id"]: r["text"] for r in rows}
            assert set(after) <= set(before) and len(after) == len(rows)
        if name in ("toxicity", "quality_rules", "ngram_jaccard_join"):
            assert all(before[d] == t for d, t in after.items())
        if name == "line_dedup":
            def key(line):
                return re.sub("[A-Z]", lambda m: m[0].lower(), line.strip(" \t\n\x0b\x0c\r"))

            common = {k for k, n in Counter(k for t in before.values() for k in {key(x) for x in t.split("\n")}).items() if k and n >= 10}
            assert after == {d: "\n".join(x for x in t.split("\n") if key(x) not in common) for d, t in before.items()}
        if name == "ngram_jaccard_join":
            sets = {d: {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for d, t in before.items() for w in [words(re.sub("[A-Z]", lambda m: m[0].lower(), t))]}
            kept = list(after)
            for i, a in enumerate(kept):
                assert not any(100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]) and sets[a] for b in kept[:i])
            for d in set(before) - set(after):
                assert any(e != d and 100 * len(sets[d] & sets[e]) >= 80 * len(sets[d] | sets[e]) for e in before)
        if name == "best_fit_packing":
            assert {r["doc_id"] for r in rows} == set(before)
        docs = spark.createDataFrame(rows, out.schema)


LONG = " ".join(f"word{i}" for i in range(60))
ODD = [(None, LONG), (None, LONG + " more"), (None, "another text " + " ".join(f"other{i}" for i in range(50))), (None, None), (7, LONG), (7, LONG), (8, ""), (9, None), (9, "x")]


def test_stages_with_null_and_repeated_ids(spark):
    like = spark.read.parquet(f"{SF}/documents.parquet")
    docs = spark.createDataFrame([(d, t, "en", "s", 1, i) for i, (d, t) in enumerate(ODD)], "doc_id long, text string, lang string, source string, n_chars long, row int")
    stages = dict(pipeline.STAGES)
    for rows in (docs, docs.limit(0)):
        for name in ("toxicity", "quality_rules", "line_dedup", "ngram_jaccard_join"):
            out = stages[name](spark, rows, SF)
            assert out.columns == rows.columns and set(like.columns) <= set(out.columns)
            got = sorted((r["row"], r["text"]) for r in out.collect())
            if rows is not docs:
                assert got == []
            elif name == "quality_rules":
                assert [r for r, _ in got] == [0, 1, 2, 4, 5]
            elif name == "line_dedup":
                assert got == [(i, t or "") for i, (_, t) in enumerate(ODD)]
            elif name == "ngram_jaccard_join":
                kept = [r for r, _ in got]
                assert len({0, 1, 4, 5} & set(kept)) == 1 and {2, 3, 6, 7, 8} <= set(kept)
        assert stages["best_fit_packing"](spark, rows, SF).count() == (len(ODD) if rows is docs else 0)


def test_query_registry():
    import __spark_entry__

    names = set(__spark_entry__.queries())
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
