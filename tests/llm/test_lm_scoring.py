"""Interpolated bigram scores against dictionaries of counts."""

import collections
import math
import re
import zlib

import pytest

from ladderset.llm import lm_scoring
from ladderset.llm.support import Scratch

TEXTS = ["the cat sat on the mat", "The dog sat", "", None, "a\x0bb  c\n the cat", "one " * 300, "the the cat", "unseen word here"]


def test_scores(spark, monkeypatch):
    monkeypatch.setattr(lm_scoring, "BLOCK_BYTES", 200)
    rows = [(i, TEXTS[i % len(TEXTS)], 1, b"x") for i in range(120)] + [(4, "repeated row", 1, b"x"), (None, "no id", 1, b"x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, block int, codes binary")
    model = lm_scoring.Model(docs.select("doc_id", "text"), Scratch(spark, "t"))
    assert all(abs(w.sum() - 1) < 1e-9 and (w >= 0).all() for w in model.weights)
    tokens = [(d, re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower()) + ["</s>"]) for d, t, *_ in rows]
    held = [d is not None and zlib.crc32(str(d).encode()) % 7 == 2 for d, _ in tokens]
    c1 = collections.Counter(w for (_, ws), h in zip(tokens, held) if not h for w in ws)
    c2 = collections.Counter(p for (_, ws), h in zip(tokens, held) if not h for p in zip(["</s>", *ws[:-1]], ws))
    n, v = sum(c1.values()), len(c1)
    want = []
    for (d, ws), h in zip(tokens, held):
        score = 0
        for a, w in zip(["</s>", *ws[:-1]], ws):
            b = min(1 + int(math.log2(c1[a])), lm_scoring.BUCKETS - 1) if c1[a] else 0
            l2, l1, l0 = model.weights[b]
            score += math.log10((l2 * c2[a, w] / c1[a] if c1[a] else 0) + l1 * c1[w] / n + l0 / (v + 1))
        want.append((d, h, len(ws), sum(c1[w] > 0 for w in ws), n, sum(math.log10((c1[w] + 1) / (n + v + 1)) for w in ws), score))
    got = sorted(map(tuple, model.score().collect()), key=str)
    for g, w in zip(got, sorted(want, key=str), strict=True):
        assert g[:5] == w[:5] and g[5:] == pytest.approx(w[5:], rel=1e-6)
    assert lm_scoring.score_documents(docs.limit(0)).count() == 0


def test_held_out_likelihood_beats_the_base(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = lm_scoring.score_documents(docs).where("held_out").collect()
    assert sum(r["score"] for r in rows) > 0.95 * sum(r["base_score"] for r in rows)
