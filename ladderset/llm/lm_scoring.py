"""Language-model scoring by deleted interpolation of unigram and bigram estimates.

    p(w | h) = l2(b) c(h w) / c(h) + l1(b) c(w) / N + l0(b) / (V + 1),   b = bucket of c(h)

Contexts fall into buckets by the logarithm of their training count. For each bucket the three weights are
learned by expectation-maximisation on counts of a held-out part of the training documents, against
estimates from the rest; scoring then uses the counts of all training documents.

The corpus is tokenised once into blocks, one row each: the distinct word hashes of the block and its texts
as codes into them. Each block asks for the totals of its own distinct unigrams and bigrams, as sorted
hashes cut by hash range ("shards"), each with the block's own counts; a shard adds the counts of all
blocks and answers every block in the order in which it asked. So what moves is distinct n-grams per
block, not tokens, and no task holds more than one shard or one block. The number of shards follows the
amount asked for. Blocks and answers meet once, in a written table; the weights are learned from a few
columns of it (the estimates for held-out bigrams), and scoring reads the others. Rounds of
expectation-maximisation end when the held-out log-likelihood hardly rises.

N-grams are told apart by hashes of 64 bits (words) and 56 bits (bigrams); two that agreed would be counted as one.

Words are `[^\\x20\\x09-\\x0D]+` with A-Z lowered; a text ends with one end token, which counts as a token and is the context of
first words. Defined cases: null text is empty (its end token alone); rows that repeat a doc_id count as
often as they stand; a null doc_id counts as training text; an empty table gives an empty result, and
without any training document all counts are 0; further columns of the input are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import Scratch, table
from .textscan import LOWER, buffer_of, mix, range_hash, slices, words_of

#: Text of a block. Rows stay well below what a JVM heap takes as huge objects.
BLOCK_BYTES = 4 << 20
#: Compressed bytes of text codes for each shard of the counts.
SHARD_BYTES = 2_000_000
BUCKETS = 16
#: Most rounds of expectation-maximisation, and the relative gain in log-likelihood below which it stops.
EM_ROUNDS = 24
EM_GAIN = 1e-5
#: One in so many training documents serves as held-out counts for the weights.
WEIGHT_SHARE = 10
END = np.uint64(0x5851F42D4C957F2D)
PAIR_SHIFT = np.uint64(8)
TRAIN, WEIGH, TEST = 0, 1, 2

_pack = zstandard.ZstdCompressor(level=1).compress
_unpack = zstandard.ZstdDecompressor().decompress


def put(a: np.ndarray, kind: str) -> bytes:
    """An array as compressed byte planes."""
    raw = np.ascontiguousarray(a, kind)
    return _pack(np.ascontiguousarray(raw.view(np.uint8).reshape(-1, raw.itemsize).T).tobytes())


def get(b: bytes, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(_unpack(b), np.uint8).reshape(size, -1).T).view(kind).ravel()


def put_sorted(a: np.ndarray) -> bytes:
    return put(np.diff(a, prepend=np.uint64(0)), "<u8")


def get_sorted(b: bytes) -> np.ndarray:
    return np.cumsum(get(b, "<u8"), dtype=np.uint64)


def in_test(ids: pa.Array) -> np.ndarray:
    """Held-out documents: crc32 of doc_id as text is 2 modulo 7."""
    return np.array([i is not None and zlib.crc32(str(i).encode()) % 7 == 2 for i in ids.to_pylist()], bool)


class Block:
    """Texts as codes into the block's distinct word hashes, ends included; roles of documents."""

    def __init__(self, words: np.ndarray, codes: np.ndarray, length: np.ndarray, role: np.ndarray):
        self.words, self.codes, self.length, self.role = words, codes, length, role
        self.doc = np.repeat(np.arange(len(length)), length)
        last = np.cumsum(length) - 1
        self.end = int(np.searchsorted(words, END))
        before = np.empty(len(codes), np.int64)
        before[1:] = codes[:-1]
        before[last + 1 - length] = self.end  # an end stands before each first word
        self.pair = before * len(words) + codes

    def bigrams(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Distinct (context, word) code pairs ordered by hash, their hashes, and the place of every token's pair."""
        pairs, place = np.unique(self.pair, return_inverse=True)
        h = mix(self.words[pairs // len(self.words)] * np.uint64(0x9E3779B97F4A7C15) + self.words[pairs % len(self.words)] + np.uint64(1)) >> PAIR_SHIFT
        order = np.argsort(h)
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        return pairs[order], h[order], rank[place]

    def counts(self, place: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Of n items: occurrences in training documents, and in those that serve for the weights."""
        role = self.role[self.doc]
        return np.bincount(place[role != TEST], minlength=n), np.bincount(place[role == WEIGH], minlength=n)


BLOCKS = "block long, n_docs int, words binary, codes binary, length binary, role binary, doc_ids array<long>"


def _blocks(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for batch in batches:
            buf, off = buffer_of(batch.column(1))
            for lo, hi in slices(off, BLOCK_BYTES):
                ids = batch.column(0).slice(lo, hi - lo)
                low = LOWER[buf[off[lo] : off[hi]]]
                w = words_of(low, off[lo : hi + 1] - off[lo])
                h = range_hash(low, w.start, w.end)
                h[h == END] ^= np.uint64(1)
                words, codes = np.unique(np.insert(h, w.first[1:], END), return_inverse=True)
                test = in_test(ids)
                draw = mix(ids.fill_null(0).to_numpy(zero_copy_only=False).astype(np.uint64)) % np.uint64(WEIGHT_SHARE)
                role = np.where(test, TEST, np.where(draw == 0, WEIGH, TRAIN)).astype(np.uint8)
                cols = [[number], [hi - lo], [put_sorted(words)], [put(codes, "<u4")], [put(np.diff(w.first) + 1, "<u4")], [put(role, "u1")], [ids.to_pylist()]]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), *[pa.binary()] * 4, pa.list_(pa.int64())), strict=True)], [x.split()[0] for x in BLOCKS.split(", ")])
                number += 1

    return docs.mapInArrow(run, BLOCKS)


def _rows(table: pa.RecordBatch | pa.Table) -> Iterator[dict]:
    """Rows one by one, so that only one block is open at a time."""
    for i in range(table.num_rows):
        yield table.slice(i, 1).to_pylist()[0]


def _open(row: dict) -> Block:
    return Block(get_sorted(row["words"]), get(row["codes"], "<u4").astype(np.int64), get(row["length"], "<u4").astype(np.int64), get(row["role"], "u1"))


ASKED = "block long, shard int, order int, keys binary, own binary, weigh binary"


def _ask(blocks: DataFrame, shards: int) -> DataFrame:
    """Each block's distinct n-grams by shard, with its own training counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in _rows(batch):
                b, out = _open(row), []
                _, h2, place = b.bigrams()
                for order, h, at in ((1, b.words, b.codes), (2, h2, place)):
                    own, weigh = b.counts(at, len(h))
                    cut = np.searchsorted(h, edges(shards) >> (PAIR_SHIFT if order == 2 else np.uint64(0)))
                    cut[-1] = len(h)
                    out += [(row["block"], s, order, put_sorted(h[x:y]), put(own[x:y], "<u4"), put(weigh[x:y], "<u4")) for s, (x, y) in enumerate(zip(cut[:-1], cut[1:], strict=True)) if y > x]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int32(), pa.int32(), *[pa.binary()] * 3), strict=True)], [x.split()[0] for x in ASKED.split(", ")])

    return blocks.select("block", "words", "codes", "length", "role").mapInArrow(run, ASKED)


def edges(shards: int) -> np.ndarray:
    """Bounds of the hash ranges; the last one is above every hash but the largest, which no shard needs to tell apart."""
    return np.array([min(2**64 - 1, i * 2**64 // shards) for i in range(shards + 1)], np.uint64)


ANSWERED = "block long, shard int, order int, total binary, weigh binary, tokens long, known long, rest_tokens long, rest_known long"


def _answer(asked: DataFrame) -> DataFrame:
    """Totals over all blocks, in the order of each block's keys; also the shard's unigram tokens and distinct unigrams in training,
    and in training without the part that serves for the weights."""

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        keys = [get_sorted(x) for x in rows["keys"].to_pylist()]
        own, weigh = ([get(x, "<u4") for x in rows[c].to_pylist()] for c in ("own", "weigh"))
        every, place = np.unique(np.concatenate(keys), return_inverse=True)
        total, part = (np.bincount(place, np.concatenate(x).astype(float), len(every)).astype(np.int64) for x in (own, weigh))
        ends = np.cumsum([len(k) for k in keys])
        at = [place[e - len(k) : e] for e, k in zip(ends, keys, strict=True)]
        first = key[1].as_py() == 1
        n = len(keys)
        cols = [rows["block"], rows["shard"], rows["order"], pa.array([put(total[x], "<u8") for x in at], pa.binary()), pa.array([put(part[x], "<u8") for x in at], pa.binary())]
        rest = total - part
        cols += [pa.array([int(x.sum()) if first else 0] * n, pa.int64()) for x in (total, total > 0, rest, rest > 0)]
        return pa.table(cols, [x.split()[0] for x in ANSWERED.split(", ")])

    return asked.groupBy("shard", "order").applyInArrow(run, ANSWERED)


def bucket_of(count: np.ndarray) -> np.ndarray:
    """0 for contexts never seen, then one for each doubling of the count, and one for all beyond."""
    return np.where(count > 0, np.minimum(1 + np.log2(np.maximum(count, 1)).astype(np.int64), BUCKETS - 1), 0)


def estimates(c2, ch, c1, n, v) -> np.ndarray:
    """Bigram, unigram and uniform estimates, a row each."""
    return np.stack([c2 / np.maximum(ch, 1), c1 / max(n, 1), np.full(len(c1), 1 / (v + 1))])


def _totals(answers: pa.Table, order: int) -> tuple[np.ndarray, np.ndarray]:
    mine = answers.filter(pc.equal(answers["order"], order)).sort_by("shard")
    return tuple(np.concatenate([get(x, "<u8") for x in mine[c].to_pylist()]).astype(np.int64) for c in ("total", "weigh"))


JOINED = "words binary, codes binary, length binary, role binary, doc_ids array<long>, t1 binary, t2 binary, bucket binary, p binary, count binary"
SCORED = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


class Model:
    """Counts are asked for and answered once; weights are learned; any of the blocks' texts can be scored."""

    def __init__(self, docs: DataFrame, scratch: Scratch, rounds: int = EM_ROUNDS):
        blocks = scratch.stage(_blocks(docs), "blocks")
        size = blocks.agg(F.sum(F.octet_length("codes")).alias("n")).first()["n"] or 0
        answered = scratch.stage(_answer(_ask(blocks, max(8, size // SHARD_BYTES))), "answered")
        totals = ("tokens", "known", "rest_tokens", "rest_known")
        sums = answered.where("order = 1").groupBy("shard").agg(*[F.max(c).alias(c) for c in totals]).agg(*[F.sum(c).alias(c) for c in totals]).first()
        self.tokens, self.known, *rest = (sums[c] or 0 for c in totals)
        self.joined = scratch.stage(self._join(blocks, answered, *rest), "joined")
        scratch.drop(blocks, answered)
        self.weights = self._learn(rounds)

    @staticmethod
    def _join(blocks: DataFrame, answered: DataFrame, tokens: int, known: int) -> DataFrame:
        """Each block with the totals of its n-grams and the estimates, from the rest of training, of its held-out bigrams."""

        def run(rows: pa.Table, answers: pa.Table) -> pa.Table:
            row = next(_rows(rows))
            b = _open(row)
            pairs, _, place = b.bigrams()
            own = b.counts(place, len(pairs))[1]
            some = np.flatnonzero(own)
            (t1, w1), (t2, w2) = _totals(answers, 1), _totals(answers, 2)
            h, w = pairs[some] // len(b.words), pairs[some] % len(b.words)
            rest1 = t1 - w1
            p = estimates((t2 - w2)[some], rest1[h], rest1[w], tokens, known)
            row |= {"t1": put(t1, "<u8"), "t2": put(t2, "<u8"), "bucket": put(bucket_of(rest1[h]), "u1"), "p": p.astype("<f4").tobytes(), "count": put(own[some], "<u4")}
            names = [x.split()[0] for x in JOINED.split(", ")]
            return pa.table([pa.array([row[c]], pa.list_(pa.int64()) if c == "doc_ids" else pa.binary()) for c in names], names)

        mine = answered.select("block", "shard", "order", "total", "weigh").groupBy("block")
        return blocks.groupBy("block").cogroup(mine).applyInArrow(run, JOINED)

    def _learn(self, rounds: int) -> np.ndarray:
        """One row of three weights a bucket, by expectation-maximisation on the held-out counts."""
        held = self.joined.select("bucket", "p", "count")
        weights = np.tile([0.6, 0.35, 0.05], (BUCKETS, 1))
        weights[0] = [0, 0.9, 0.1]
        before = -np.inf
        for _ in range(rounds):
            now = weights

            def expect(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
                out = np.zeros((BUCKETS, 4))
                for batch in batches:
                    for row in _rows(batch):
                        bucket, count = get(row["bucket"], "u1"), get(row["count"], "<u4")
                        p = np.frombuffer(row["p"], "<f4").reshape(3, -1) * now[bucket].T
                        every = np.maximum(p.sum(0), 1e-300)
                        out += np.stack([np.bincount(bucket, x, BUCKETS) for x in (*(p / every * count), np.log(every) * count)], 1)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(BUCKETS, dtype=np.int32)), *(pa.array(out[:, j]) for j in range(4))], ["bucket", "w2", "w1", "w0", "fit"])

            sums = held.mapInArrow(expect, "bucket int, w2 double, w1 double, w0 double, fit double").groupBy("bucket").agg(*[F.sum(c).alias(c) for c in ("w2", "w1", "w0", "fit")]).collect()
            fit = sum(r["fit"] for r in sums)
            if fit - before <= EM_GAIN * abs(fit):
                break
            before, weights = fit, now.copy()
            for r in sums:
                got = np.array([r["w2"], r["w1"], r["w0"]])
                if got.sum() > 0:
                    got += 1e-6 * got.sum()
                    if r["bucket"] == 0:
                        got[0] = 0
                    weights[r["bucket"]] = got / got.sum()
        return weights

    def score(self) -> DataFrame:
        """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
        tokens, known, weights = self.tokens, self.known, self.weights

        names = [x.split()[0] for x in SCORED.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in _rows(batch):
                    b = _open(row)
                    pairs, _, place = b.bigrams()
                    t1, t2 = (get(row[c], "<u8").astype(np.int64) for c in ("t1", "t2"))
                    h, w = pairs // len(b.words), pairs % len(b.words)
                    p = (estimates(t2, t1[h], t1[w], tokens, known) * weights[bucket_of(t1[h])].T).sum(0)
                    rows = len(b.length)
                    base = np.log10((t1 + 1) / (tokens + known + 1))
                    cols = [np.bincount(b.doc, (t1 > 0)[b.codes], rows).astype(np.int64), np.full(rows, tokens), np.bincount(b.doc, base[b.codes], rows), np.bincount(b.doc, np.log10(p)[place], rows)]
                    yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(b.role == TEST), pa.array(b.length), *map(pa.array, cols)], names)

        return self.joined.select("words", "codes", "length", "role", "doc_ids", "t1", "t2").mapInArrow(run, SCORED)


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rounds: int = EM_ROUNDS) -> DataFrame:
    chosen = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return Model(chosen, Scratch(docs.sparkSession, "lm"), rounds).score()


def op3_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(table(spark, sf_dir, "documents"))
