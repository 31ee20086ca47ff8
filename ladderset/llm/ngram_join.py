"""Set-similarity join of documents on word n-grams (Jaccard), by rare-first prefix filtering.

1. Shingle frequencies go into a fixed-size sketch of counters; (counter, hash) is one global rare-first
   order, the same for every document whatever the counters' error, so the prefix filter stays exact.
2. Each document becomes a set of shingle hashes. Equal sets are one class from here on; a class keeps
   its prefix n-grams and counts of its shingles in 128 hash ranges.
3. Classes that share a prefix n-gram meet, in blocks of bounded size (a popular n-gram's classes are
   split into blocks, and every pair of blocks is a group of its own). Inside a group, pairs pass a length
   filter, a positional filter and a suffix filter (the range counts bound the difference of two sets
   from below); nothing is emitted for a pair that fails.
4. Pairs are verified on whole sets. First every class proposes only its closest candidate outside its
   component; then all candidates that still lie in different components are verified. A pair whose ends
   are already joined by verified links cannot change a component, so for components alone (`similar_groups`)
   a large group of near copies costs about one verified pair per member, not one per pair.
5. Components are found by minimum labels with pointer jumping, in staged tables.
6. For the links (`similar_links`, `similar_pairs`) every candidate pair inside a component is verified as
   well; a pair across components was a candidate of step 4 and failed there, or was none. A component's
   classes are dealt to tiles, candidates travel packed by pair of tiles, and such a pair of tiles gets
   its sets once, so a set is not copied for each of its pairs.

Defined cases: null or empty text has no shingles, is linked with nothing and is its own component; a text
of fewer words than n has its whole word sequence as its one shingle; rows that repeat a doc_id are in
the result once per row; a null doc_id takes the component of an equal set, if there is one, and else
null; an empty table gives an empty result; further columns of the input are ignored. Links are counted
between different doc_ids: rows that repeat a doc_id count once, rows with a null doc_id are not counted
(one with an equal set has that set's number, another null).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import Scratch, bitmap_of, table, with_bitmap
from .textscan import buffer_of, mix, shingle_sets, slices

SKETCH_BITS = 18
CHUNK = 1 << 12
RANGES = 128
BLOCK = 1024
SLICE_BYTES = 2 << 20
PROPOSALS = 2
TILE = 64


def _sketch(docs: DataFrame, k: int) -> np.ndarray:
    """Occurrences of shingles per hash range: 2^18 counters, whatever the corpus."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << SKETCH_BITS, np.int64)
        for batch in batches:
            buf, off = buffer_of(batch.column(0))
            for lo, hi in slices(off, SLICE_BYTES):
                _, v = shingle_sets(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], k)
                total += np.bincount((v >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=len(total))
        part = TaskContext.get().partitionId() // 64
        parts = [(i, c) for i, c in enumerate(total.reshape(-1, CHUNK)) if c.any()]
        yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in parts], pa.int32()), pa.array([part] * len(parts), pa.int32()), pa.array([c.astype("<i4").tobytes() if c.max() < 2**31 else c.astype("<i8").tobytes() for _, c in parts], pa.binary())], ["chunk", "part", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}
        for batch in batches:
            for c, p, b in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                held.setdefault((c, p), np.zeros(CHUNK, np.int64))
                held[c, p] += np.frombuffer(b, "<i4" if len(b) == 4 * CHUNK else "<i8")
        keys = list(held)
        yield pa.RecordBatch.from_arrays([pa.array([c for c, _ in keys], pa.int32()), pa.array([p for _, p in keys], pa.int32()), pa.array([held[x].astype("<i8").tobytes() for x in keys], pa.binary())], ["chunk", "part", "counts"])

    schema = "chunk int, part int, counts binary"
    once = docs.select("text").mapInArrow(count, schema).repartition("chunk", "part").mapInArrow(add, schema)
    twice = once.withColumn("part", F.lit(0)).repartition("chunk").mapInArrow(add, schema)
    out = np.zeros((1 << SKETCH_BITS) // CHUNK * CHUNK, np.int64).reshape(-1, CHUNK)
    for r in twice.collect():  # at most 64 rows
        out[r["chunk"]] += np.frombuffer(r["counts"], "<i8")
    return out.ravel()


SET_COLUMNS = "doc_id long, n long, s1 long, s2 long, keys array<long>, ranges binary"


def _sets(docs: DataFrame, counts: np.ndarray, k: int, num: int, den: int) -> DataFrame:
    """Per document: set size, a 128-bit set hash, prefix n-grams rare first, and range counts."""
    shift = max(0, int(counts.max(initial=0)).bit_length() - 24)
    shared = docs.sparkSession.sparkContext.broadcast((counts >> shift).astype(np.uint64))  # 2 MB

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = shared.value
        for batch in batches:
            buf, off = buffer_of(batch.column(1))
            for lo, hi in slices(off, SLICE_BYTES):
                rows = hi - lo
                r, v = shingle_sets(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], k)
                n, s1, s2, ranges = set_digests(r, v, rows)
                at = np.cumsum(n) - n
                order = np.lexsort((rank[(v >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)] << np.uint64(40) | v >> np.uint64(24), r))
                length = np.where(n > 0, n + (-num * n) // den + 1, 0)
                inside = np.arange(len(v)) - np.repeat(at, n)
                keys = v[order][inside < np.repeat(length, n)].view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]), pa.int32()), pa.array(keys))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, rows), pa.array(n), pa.array(s1), pa.array(s2), lists, pa.array([x.tobytes() for x in ranges], pa.binary())], ["doc_id", "n", "s1", "s2", "keys", "ranges"])

    return docs.mapInArrow(run, SET_COLUMNS)


def set_digests(r: np.ndarray, v: np.ndarray, rows: int) -> tuple[np.ndarray, ...]:
    """Sizes, two order-free 64-bit sums, and clipped range counts of the sets (r, v)."""
    n = np.bincount(r, minlength=rows)
    mixed = mix(v)
    sums = []
    for x in (mixed, mix(mixed ^ np.uint64(0x2545F4914F6CDD1D))):
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(x, dtype=np.uint64)])
        ends = np.cumsum(n)
        sums.append((total[ends] - total[ends - n]).view(np.int64))
    ranges = np.bincount(r * RANGES + (mixed >> np.uint64(40)).astype(np.int64) % RANGES, minlength=rows * RANGES).reshape(rows, RANGES)
    return n, sums[0], sums[1], np.minimum(ranges, 255).astype(np.uint8)


def needed_overlap(a: np.ndarray, b: np.ndarray, num: int, den: int) -> np.ndarray:
    return -((-num * (a + b)) // (num + den))


class Group:
    """Classes that share a prefix n-gram; finds pairs that may be similar."""

    def __init__(self, cid, n, pos, label, block, ranges, num, den, inside=False):
        self.cid, self.n, self.pos, self.label, self.block, self.ranges, self.num, self.den, self.inside = cid, n, pos, label, block, ranges, num, den, inside

    def passes(self, i: np.ndarray, j: np.ndarray, cross: np.ndarray | bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of candidate index pairs, those that pass all filters, and how far apart their range counts are."""
        ni, nj = self.n[i], self.n[j]
        alpha = needed_overlap(ni, nj, self.num, self.den)
        ok = ((self.label[i] == self.label[j]) == self.inside) & (self.cid[i] != self.cid[j])
        ok &= ~np.broadcast_to(cross, ok.shape) | (self.block[i] != self.block[j])
        ok &= self.den * np.minimum(ni, nj) >= self.num * np.maximum(ni, nj)
        ok &= np.minimum(ni - self.pos[i], nj - self.pos[j]) >= alpha
        i, j, most = i[ok], j[ok], (ni + nj - 2 * alpha)[ok]
        gap = np.empty(len(i), np.int64)
        for lo in range(0, len(i), 1 << 14):
            s = slice(lo, lo + (1 << 14))
            gap[s] = np.abs(self.ranges[i[s]].astype(np.int16) - self.ranges[j[s]]).sum(1)
        near = gap <= most
        return i[near], j[near], gap[near]

    def pairs(self, first: np.ndarray, size: np.ndarray, cross: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Passing pairs of the groups that start at `first`; small groups together, a large one by rows."""
        small = size <= 64
        mine = np.repeat(small, size)
        row, end, cr = (x[mine] for x in (np.arange(size.sum()), np.repeat(first + size, size), np.repeat(cross, size)))
        for d in range(1, int(size[small].max(initial=1))):
            some = row + d < end
            row, end, cr = row[some], end[some], cr[some]
            yield self.passes(row, row + d, cr)
        for f, s, c in zip(first[~small].tolist(), size[~small].tolist(), cross[~small].tolist(), strict=True):
            for a in range(f, f + s - 1, 256):
                i, j = np.meshgrid(np.arange(a, min(a + 256, f + s)), np.arange(a + 1, f + s), indexing="ij")
                ahead = i < j
                yield self.passes(i[ahead], j[ahead], c)


BUCKET = "key long, bi int, bj int, block int, cid long, n long, pos int, label long, ranges binary"


INSIDE = "label long, ti int, tj int, pairs binary"


def _candidates(buckets: DataFrame, num: int, den: int, closest: bool, inside: bool = False) -> DataFrame:
    """Candidate pairs (cid, other) of groups (key, bi, bj): each row's closest, or all.

    `closest` returns whole bucket rows with `other`, so the rows that have any candidate can go on alone.
    `inside` returns the pairs within components instead of those across, packed by pair of tiles (column `tile`).
    """

    def flush(t: pa.Table) -> Iterator[pa.RecordBatch]:
        key, bi, bj, block, cid, n, pos, label = (t[c].to_numpy() for c in ("key", "bi", "bj", "block", "cid", "n", "pos", "label"))
        ranges = np.frombuffer(b"".join(t["ranges"].to_pylist()), np.uint8).reshape(-1, RANGES)
        first = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])]))
        size = np.diff(np.append(first, len(key)))
        found = list(Group(cid, n, pos, label, block, ranges, num, den, inside).pairs(first, size, bi[first] != bj[first]))
        i, j, gap = (np.concatenate([f[x] for f in found]) if found else np.empty(0, np.int64) for x in range(3))
        if closest:
            me, other, gap = np.concatenate([i, j]), np.concatenate([j, i]), np.concatenate([gap, gap])
            order = np.lexsort((cid[other], gap, me))
            me, other = me[order], other[order]
            top = np.concatenate([[True], me[1:] != me[:-1]]) if len(me) else np.empty(0, bool)
            out = t.take(pa.array(me[top])).append_column("other", pa.array(cid[other[top]]))
            yield from out.select([*names, "other"]).to_batches()
        elif inside:
            tile = t["tile"].to_numpy()
            swap = (tile[i] > tile[j]) | (tile[i] == tile[j]) & (cid[i] > cid[j])
            i, j = np.where(swap, j, i), np.where(swap, i, j)
            pair = np.unique(np.stack([label[i], tile[i], tile[j], cid[i], cid[j]], 1).astype(np.int64), axis=0)
            starts = np.flatnonzero(np.concatenate([[True], (pair[1:, :3] != pair[:-1, :3]).any(1)])) if len(pair) else np.empty(0, np.int64)
            packed = [x.tobytes() for x in np.split(np.ascontiguousarray(pair[:, 3:]), starts[1:])] if len(pair) else []
            yield pa.RecordBatch.from_arrays([pa.array(pair[starts, 0]), pa.array(pair[starts, 1], pa.int32()), pa.array(pair[starts, 2], pa.int32()), pa.array(packed, pa.binary())], ["label", "ti", "tj", "pairs"])
        else:
            pair = np.unique(np.stack([np.minimum(cid[i], cid[j]), np.maximum(cid[i], cid[j])], 1), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])

    names = [x.split()[0] for x in BUCKET.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            rows += batch.num_rows
            if rows < 20_000:
                continue
            t = pa.Table.from_batches(held)
            key, bi, bj = (t[c].to_numpy() for c in ("key", "bi", "bj"))
            other = np.flatnonzero((key != key[-1]) | (bi != bi[-1]) | (bj != bj[-1]))
            if len(other):  # the last group may go on
                cut = int(other[-1]) + 1
                yield from flush(t.slice(0, cut))
                held = t.slice(cut).to_batches()
                rows = t.num_rows - cut
        if rows:
            yield from flush(pa.Table.from_batches(held))

    dealt = buckets.repartition("key", "bi", "bj").sortWithinPartitions("key", "bi", "bj", "cid")
    return dealt.mapInArrow(run, INSIDE if inside else BUCKET + ", other long" if closest else "a long, b long")


def _whole_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(cid, items): whole sets of the wanted classes (cid, rep, s1, s2), from their representatives' texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = buffer_of(batch.column("text"))
            for lo, hi in slices(off, SLICE_BYTES):
                r, v = shingle_sets(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], k)
                n, s1, s2, _ = set_digests(r, v, hi - lo)
                same = (s1 == batch.column("s1").to_numpy()[lo:hi]) & (s2 == batch.column("s2").to_numpy()[lo:hi])
                ends = np.cumsum(n)
                keep = np.flatnonzero(same)
                yield pa.RecordBatch.from_arrays([batch.column("cid").slice(lo, hi - lo).take(pa.array(keep)), pa.array([v[ends[x] - n[x] : ends[x]].astype("<u8").tobytes() for x in keep], pa.binary())], ["cid", "items"])

    wanted = wanted.withColumnRenamed("rep", "doc_id")
    some = with_bitmap(docs, bitmap_of(wanted, "doc_id"), "hit", "doc_id").where("hit").drop("hit")
    return some.join(wanted, "doc_id").select("cid", "s1", "s2", "text").mapInArrow(run, "cid long, items binary").dropDuplicates(["cid"])


def _verified(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """The pairs whose Jaccard similarity is num/den at least."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            link = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
                x, y = np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")
                both = len(np.intersect1d(x, y, assume_unique=True))
                link.append(den * both >= num * (len(x) + len(y) - both))
            t = pa.Table.from_batches([batch.select(["a", "b"])]).filter(pa.array(link, pa.bool_()))
            yield from t.to_batches()

    full = pairs.join(sets.select(F.col("cid").alias("a"), F.col("items").alias("x")), "a").join(sets.select(F.col("cid").alias("b"), F.col("items").alias("y")), "b")
    return full.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _verified_inside(found: DataFrame, tiles: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """(cid, linked, others) from packed candidates of INSIDE: of each class and pair of tiles, the doc_ids of linked classes and the linked classes above it."""
    pairs_of_tiles = found.select("label", "ti", "tj").distinct()
    ends = pairs_of_tiles.withColumn("tile", F.explode(F.array_distinct(F.array("ti", "tj"))))
    content = ends.join(tiles, ["label", "tile"]).join(sets, "cid").select("label", "ti", "tj", "cid", "docs", "items")
    rows = found.select("label", "ti", "tj", F.lit(None).cast("long").alias("cid"), F.lit(None).cast("long").alias("docs"), F.col("pairs").alias("items")).union(content)

    def links(pairs: list[bytes], held: dict[int, tuple[int, np.ndarray]]) -> Iterator[tuple[int, int, np.ndarray]]:
        pair = np.unique(np.frombuffer(b"".join(pairs), np.int64).reshape(-1, 2), axis=0)
        linked: dict[int, int] = {}
        above: dict[int, list[int]] = {}
        for a, bs in zip(pair[(at := np.flatnonzero(np.diff(pair[:, 0], prepend=pair[0, 0] - 1))), 0].tolist(), np.split(pair[:, 1], at[1:]), strict=True):
            mine = np.sort(held[a][1])
            others = [held[b][1] for b in bs.tolist()]
            n = np.array([len(x) for x in others])
            every = np.concatenate(others)
            hit = mine[np.minimum(np.searchsorted(mine, every), len(mine) - 1)] == every
            both = np.add.reduceat(hit.astype(np.int64), np.cumsum(n) - n)
            for b in bs[den * both >= num * (len(mine) + n - both)].tolist():
                linked[a] = linked.get(a, 0) + held[b][0]
                linked[b] = linked.get(b, 0) + held[a][0]
                above.setdefault(min(a, b), []).append(max(a, b))
        return ((c, k, above.get(c, [])) for c, k in linked.items())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, pairs, held, out = None, [], {}, []

        def batch_of(rows: list) -> pa.RecordBatch:
            cols = list(zip(*rows, strict=True)) or [()] * 3
            return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.list_(pa.int64()))], ["cid", "linked", "others"])

        for batch in batches:
            for label, ti, tj, cid, docs, items in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if now != (label, ti, tj):
                    if pairs:
                        out += links(pairs, held)
                    now, pairs, held = (label, ti, tj), [], {}
                if cid is None:
                    pairs.append(items)
                else:
                    held[cid] = (docs, np.frombuffer(items, "<u8"))
            if len(out) > 5_000:
                yield batch_of(out)
                out = []
        if pairs:
            out += links(pairs, held)
        yield batch_of(out)

    return rows.repartition("label", "ti", "tj").sortWithinPartitions("label", "ti", "tj").mapInArrow(run, "cid long, linked long, others array<long>")


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(cid, label) of every vertex of the edges (a, b), a staged table: label is the smallest vertex of its component."""
    rows = 2 * edges.count()  # bounds the vertices too
    both = scratch.stage(edges.union(edges.select("b", "a")).toDF("cid", "other").distinct(), "edges", rows)
    labels = scratch.stage(both.groupBy("cid").agg(F.least("cid", F.min("other")).alias("label")), "labels", rows)
    while True:
        near = both.join(labels.select(F.col("cid").alias("other"), "label"), "other").groupBy("cid").agg(F.min("label").alias("near"))
        lower = labels.join(near, "cid").select("cid", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        jump = labels.select(F.col("cid").alias("label"), F.col("label").alias("root"))
        new = scratch.stage(lower.join(jump, "label", "left").select("cid", "old", F.least("label", "root").alias("label")), "labels", rows)
        scratch.drop(labels)
        labels = new
        if not new.where("old <> label").limit(1).count():
            scratch.drop(both)
            return labels.select("cid", "label")


@dataclass
class Joined:
    """The staged tables of a join: documents with their sets, classes, rows with candidates, whole sets, components."""

    scratch: Scratch
    members: DataFrame
    classes: DataFrame
    alive: DataFrame
    sets: DataFrame
    labels: DataFrame
    num: int
    den: int

    def groups(self) -> DataFrame:
        """(doc_id, n, s1, s2, component_id) of every document."""
        named = self.classes.select("cid", "n", "s1", "s2", "rep").join(self.labels, "cid", "left").withColumn("label", F.coalesce("label", "cid"))
        smallest = named.groupBy("label").agg(F.min("rep").alias("component_id"))
        by_set = named.join(smallest, "label").select("n", "s1", "s2", "component_id")
        return self.members.select("doc_id", "n", "s1", "s2").join(by_set, ["n", "s1", "s2"], "left").withColumn("component_id", F.coalesce("component_id", "doc_id"))

    def sizes(self) -> DataFrame:
        """(cid, docs): different doc_ids of every class."""
        docs = self.members.where("n > 0 and doc_id is not null").groupBy("n", "s1", "s2").agg(F.count_distinct("doc_id").alias("docs"))
        return self.classes.select("cid", "n", "s1", "s2").join(docs, ["n", "s1", "s2"])

    def links(self) -> DataFrame:
        """(cid, linked, others) of all links between classes."""
        wide = self.labels.groupBy("label").agg(F.ceil(F.count("*") / TILE).cast("int").alias("tiles"))
        tiles = self.scratch.stage(self.labels.join(wide, "label").select("cid", "label", F.pmod(F.xxhash64("cid"), "tiles").cast("int").alias("tile")), "tiles", self.labels.count())
        again = self.alive.drop("other", "label").join(tiles, "cid").select(*[x.split()[0] for x in BUCKET.split(", ")], "tile")
        found = self.scratch.stage(_candidates(again, self.num, self.den, closest=False, inside=True), "inside")
        return _verified_inside(found, tiles, self.sets.join(self.sizes().select("cid", "docs"), "cid"), self.num, self.den)


def _join(docs: DataFrame, k: int, num: int, den: int, id_col: str, text_col: str) -> Joined:
    spark = docs.sparkSession
    scratch = Scratch(spark, "ngram-join")
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    members = scratch.stage(_sets(docs, _sketch(docs, k), k, num, den), "members")
    classes = scratch.stage(
        members.where("n > 0 and doc_id is not null")
        .groupBy("n", "s1", "s2")
        .agg(F.min("doc_id").alias("rep"), F.first("keys").alias("keys"), F.first("ranges").alias("ranges"))
        .withColumn("cid", F.monotonically_increasing_id()),
        "classes",
    )
    keyed = classes.select("cid", "n", F.posexplode("keys").alias("pos", "key"))
    popular = keyed.groupBy("key").agg(F.count("*").alias("c")).where("c > 1")
    blocks = F.ceil(F.col("c") / BLOCK).cast("int")
    buckets = (
        keyed.join(popular, "key")
        .withColumn("block", F.pmod(F.xxhash64("cid", "key"), blocks).cast("int"))
        .withColumn("o", F.explode(F.sequence(F.lit(0), blocks - 1)))
        .select("key", F.least("block", "o").alias("bi"), F.greatest("block", "o").alias("bj"), "block", "cid", "n", "pos", F.col("cid").alias("label"))
        .join(classes.select("cid", "ranges"), "cid")
        .select(*[x.split()[0] for x in BUCKET.split(", ")])
    )
    alive = scratch.stage(_candidates(buckets, num, den, closest=True), "alive")
    wanted = classes.join(alive.select("cid").distinct(), "cid", "left_semi").select("cid", "rep", "s1", "s2")
    sets = scratch.stage(_whole_sets(docs, wanted, k), "sets")

    def pairs_of(df: DataFrame) -> DataFrame:
        return df.select(F.least("cid", "other").alias("a"), F.greatest("cid", "other").alias("b")).distinct()

    rows = alive.count()  # a candidate each, so a bound on its pairs
    links = scratch.stage(_verified(pairs_of(alive), sets, num, den), "links", 8 * rows)  # verifying is more work than its rows tell
    labels = components(links, scratch)
    for last in [False] * (PROPOSALS - 1) + [True]:
        again = alive.drop("other", "label").join(labels, "cid", "left").withColumn("label", F.coalesce("label", "cid")).select(*[x.split()[0] for x in BUCKET.split(", ")])
        found = _candidates(again, num, den, closest=not last)
        more = scratch.stage(_verified(found.distinct() if last else pairs_of(found), sets, num, den), "links")
        if more.limit(1).count():
            links = scratch.stage(links.union(more).distinct(), "links", links.count() + more.count())
            labels = components(links, scratch)
    return Joined(scratch, members, classes, alive, sets, labels, num, den)


def similar_groups(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest doc_id reachable over pairs with Jaccard >= num/den). Components only."""
    return _join(docs, k, num, den, id_col, text_col).groups().select("doc_id", F.col("n").alias("n_shingles"), "component_id")


def similar_links(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`similar_groups` with n_links: how many other doc_ids have Jaccard >= num/den with the document."""
    joined = _join(docs, k, num, den, id_col, text_col)
    linked = joined.links().groupBy("cid").agg(F.sum("linked").alias("linked"))
    by_set = joined.sizes().join(linked, "cid", "left").select("n", "s1", "s2", (F.col("docs") + F.coalesce("linked", F.lit(0))).alias("near"))
    near = F.col("near") - F.when(F.col("doc_id").isNull(), 0).otherwise(1)
    return joined.groups().join(by_set, ["n", "s1", "s2"], "left").select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(near, F.when(F.col("doc_id").isNotNull() | (F.col("n") == 0), 0)).cast("long").alias("n_links"))


def similar_pairs(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(a, b) of every two classes of equal sets with Jaccard >= num/den, named by their smallest doc_ids, and (doc_id, rep) of the documents in classes."""
    joined = _join(docs, k, num, den, id_col, text_col)
    rep = joined.classes.select("cid", "rep")
    pairs = joined.links().select("cid", F.explode("others").alias("other")).join(rep, "cid").join(rep.toDF("other", "rep2"), "other")
    reps = joined.classes.select("n", "s1", "s2", "rep")
    return pairs.select(F.least("rep", "rep2").alias("a"), F.greatest("rep", "rep2").alias("b")), joined.members.join(reps, ["n", "s1", "s2"]).select("doc_id", "rep")


def op5_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_links(table(spark, sf_dir, "documents"), k=3, num=90, den=100)


ORACLE = {
    "op5_ngram_jaccard": r"""
        WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
        s AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + 2], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w WHERE len(ws) >= 3)
              UNION ALL SELECT doc_id, array_to_string(ws, ' ') FROM w WHERE len(ws) IN (1, 2)),
        c AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
        common AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s x JOIN s y USING (g) WHERE x.doc_id <> y.doc_id GROUP BY 1, 2),
        link AS (SELECT a, b FROM common JOIN c x ON x.doc_id = a JOIN c y ON y.doc_id = b WHERE 100 * k >= 90 * (x.n + y.n - k)),
        linked AS (SELECT a, CAST(count(*) AS BIGINT) AS n_links FROM link GROUP BY 1),
        reach AS (SELECT DISTINCT a AS doc_id, a AS other FROM link UNION SELECT reach.doc_id, link.b FROM reach JOIN link ON link.a = reach.other),
        smallest AS (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY 1)
        SELECT w.doc_id, CAST(coalesce(c.n, 0) AS BIGINT) AS n_shingles, coalesce(component_id, w.doc_id) AS component_id, coalesce(n_links, 0) AS n_links
        FROM w LEFT JOIN c USING (doc_id) LEFT JOIN smallest USING (doc_id) LEFT JOIN linked ON linked.a = w.doc_id
    """
}
