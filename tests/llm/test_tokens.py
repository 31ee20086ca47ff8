"""Token ids, token files and packing against the tokenizers library and plain Python."""

import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

pytest.importorskip("tokenizers")
from ladderset.llm import packing, token_files  # noqa: E402
from ladderset.llm.tokenids import BatchEncoder, vocabulary  # noqa: E402

ODD = ["", None, "  ", "it's DON'T 'll x!'s", "a<|endoftext|>B <|ENDOFTEXT|>", "T̈ W̊ İI Σας", "½x² 中文,字\x0bé É\x1cz", "a" * 5000, "word " * 9000]


WHOLE = BatchEncoder(vocabulary(), 1)


def reference(text):
    return WHOLE.tokenizer.encode(text or "", add_special_tokens=False).ids + [1]


def crc(ids):
    return zlib.crc32(np.asarray(ids, "<u4").tobytes())


def test_pieces_equal_whole_texts():
    rng = random.Random(5)
    alphabet = [*"aAtTjJ'sS!.,-19 \n\té", "̈", "̊", "̌", "ß", "İ", "Σ", "中", "'ll", "<|endoftext|>"]
    texts = ODD + ["".join(rng.choices(alphabet, k=rng.randint(1, 50))) for _ in range(2000)]
    ids, at = BatchEncoder(vocabulary(), 1).encode(pa.array(texts, pa.string()))
    for i, t in enumerate(texts):
        assert ids[at[i] : at[i + 1]].tolist() == reference(t)


@pytest.mark.parametrize("planes", ["byte", "bit"])
@pytest.mark.parametrize("n", [0, 1, 7, 4096, 10_001])
def test_shard_round_trip(planes, n):
    ids = np.random.default_rng(n).integers(0, 2**17, n).astype("<u4")
    image = token_files.shard_image(np.arange(3), np.array([n, 0, 0]), ids, 1000, planes)
    shard = token_files.Shard(image)
    assert (shard.tokens() == ids).all() and (shard.tokens(n // 3, n // 2) == ids[n // 3 : n // 2]).all()
    with pytest.raises(ValueError):
        token_files.Shard(image[:-40] + b"x" + image[-39:])


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, part int, seq int, length int")


def test_token_files(spark, tmp_path):
    rows = [(i * 7 % 50, ODD[i % len(ODD)], 1, 2, 3) for i in range(50)] + [(3, "again", 1, 2, 3), (None, "no id", 1, 2, 3)]
    path = f"file://{tmp_path}/t"
    token_files.write_token_files(docs_of(spark, rows), path, vocabulary(), shard_tokens=3000, block=512)
    got = sorted(token_files.read_token_files(spark, path, with_ids=True).collect(), key=lambda r: r["start"])
    ids = [r["doc_id"] for r in got]
    assert len(got) == len(rows) and ids[0] is None and ids[1:] == sorted(ids[1:])
    at = 0
    for r in got:
        assert r["start"] == at and r["n_tokens"] == len(r["ids"]) and r["ids_crc32"] == crc(r["ids"])
        at += r["n_tokens"]
    want = sorted((-1 if d is None else d, reference(t)) for d, t, *_ in rows)
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["ids"]) for r in got) == want
    empty = f"file://{tmp_path}/e"
    token_files.write_token_files(docs_of(spark, []), empty, vocabulary())
    assert token_files.read_token_files(spark, empty).count() == 0


def test_knapsack_is_exact():
    rng = np.random.default_rng(1)
    for _ in range(20):
        lengths = np.unique(rng.integers(1, 30, 6))
        values = rng.random(len(lengths))
        counts = packing.best_configuration(values, lengths, 60)
        assert (counts * lengths).sum() <= 60
        best = np.zeros(61)
        for c in range(1, 61):
            best[c] = max([best[c - 1]] + [best[c - k] + v for k, v in zip(lengths, values) if k <= c])
        assert abs((counts * values).sum() - best[60]) < 1e-9


def holds_all(plan, hist, cap):
    """Whether the plan has every piece once, gapless, within the capacity."""
    fill, count = {}, {}
    for length, first, times, seq, off in plan.rows:
        assert first == count.get(length, 0)
        count[length] = first + times
        for i in range(times):
            fill.setdefault(seq + i, []).append((off, length))
    assert count == hist and len(fill) == plan.sequences
    for parts in fill.values():
        at = 0
        for off, length in sorted(parts):
            assert off == at
            at += length
        assert at <= cap


def histogram(lengths):
    return {int(k): int(n) for k, n in zip(*np.unique(lengths, return_counts=True), strict=True)}


LENGTHS = {
    "uniform": lambda r: r.integers(1, 4097, 20_000),
    "middle": lambda r: r.integers(1300, 2801, 20_000),
    "thirds": lambda r: r.choice([1365, 1366, 1000, 1700, 2731, 700], 20_000),
    "near_thirds": lambda r: r.choice([1366, 1364, 1367, 1363, 2100, 1990], 8_000),
    "quarters": lambda r: r.integers(820, 1500, 20_000),
    "log_normal": lambda r: np.clip(np.exp(r.normal(6, 1.2, 30_000)), 1, 4096).astype(int),
    "large_and_small": lambda r: r.choice([2240, 1280, 30], 5_000),
    "short": lambda r: r.integers(1, 60, 30_000),
}


@pytest.mark.parametrize("name", LENGTHS)
def test_plan_is_near_its_bound_and_never_worse_than_best_fit(name):
    hist = histogram(LENGTHS[name](np.random.default_rng(7)))
    plan = packing.plan_packing(hist)
    holds_all(plan, hist, 4096)
    assert plan.sequences <= packing.Filler(hist, 4096).best_fit().sequences
    assert plan.lower_bound <= plan.sequences <= 1.01 * plan.lower_bound + 1


def fewest(items, cap):
    """The least number of bins, by trying everything."""
    best = len(items)

    def go(i, rooms):
        nonlocal best
        if len(rooms) >= best:
            return
        if i == len(items):
            best = len(rooms)
            return
        for j in {r: j for j, r in enumerate(rooms) if r >= items[i]}.values():
            go(i + 1, [*rooms[:j], rooms[j] - items[i], *rooms[j + 1 :]])
        go(i + 1, [*rooms, cap - items[i]])

    go(0, [])
    return best


def test_bound_and_plan_hold_the_optimum():
    rng = np.random.default_rng(5)
    for _ in range(60):
        cap = int(rng.integers(10, 40))
        items = sorted(rng.integers(1, cap + 1, int(rng.integers(1, 9))).tolist(), reverse=True)
        hist, best = histogram(items), fewest(items, cap)
        plan = packing.plan_packing(hist, cap)
        holds_all(plan, hist, cap)
        assert plan.lower_bound <= best <= plan.sequences <= best + 1, (items, cap)


def test_cover_is_feasible_and_bounded():
    rng = np.random.default_rng(3)
    for _ in range(10):
        lengths = np.unique(rng.integers(5, 60, 8))
        need = rng.integers(50, 500, len(lengths)).astype(float)
        cover = packing.configuration_program(lengths, need, 100)
        got = sum(c * x for c, x in cover.configurations)
        assert (got >= need * (1 - 1e-9)).all() and all((c * lengths).sum() <= 100 for c, _ in cover.configurations)
        assert abs(sum(x for _, x in cover.configurations) - cover.value) < 1e-6 * cover.value
        assert cover.bound <= cover.value * (1 + 1e-9) and cover.value <= 1.05 * cover.bound


def test_packing_query(spark):
    rows = [(i, ODD[i % len(ODD)], 1, 2, 3) for i in range(60)] + [(5, ODD[5], 1, 2, 3), (None, "x", 1, 2, 3)]
    got = packing.best_fit_pack(docs_of(spark, rows), vocabulary()).collect()
    want = sorted((-1 if d is None else d, k // 4096, crc(ids[k : k + 4096]), k) for d, t, *_ in rows for ids in [reference(t)] for k in range(0, len(ids), 4096))
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["piece"], r["ids_crc32"], r["start"]) for r in got) == want
    seqs = {}
    for r in got:
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in seqs.values():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at <= 4096
    assert packing.best_fit_pack(docs_of(spark, []), vocabulary()).count() == 0
    pieces = packing.pieces_of(docs_of(spark, rows[:20]), vocabulary(), with_ids=True)
    placed = packing.best_fit_pack(docs_of(spark, rows[:20]), vocabulary())
    for s in packing.assemble(pieces, placed).collect():
        assert len(s["ids"]) <= 4096
