"""The stored form of sets: rungs (a set at several precisions, bucketed and packed), the dictionary, and a catalog.

All precisions are prefixes of one hash, so hash prefixes place equal elements of all sets together. A
family is shuffled once for its rungs: large sets by the top bits of the hash (a shard holds their slice of
every rung), sets too small to fill the shards by a hash of their name. The number of shards follows the size
of the family. Sorted partitions then stream through the packing, one set of one shard at a time: the top
rung is hashed and every lower one is derived from the one above by dropping bits.

The dictionary (set, hash, element) is placed by shard and sorted by hash, so the elements of a prefix are a
range of one shard; a lookup reads the shards that its prefixes touch.

A store keeps versions: a write makes a new folder and names it complete when all is there, a read takes the
newest complete one, so writing again replaces a family, shrunk sets and lost rungs included. A batch that is
appended makes a version of only what is new: slices of buckets, which every reader unites with the stored
ones, and whole rungs of sets that have outgrown their shape. After a few of those a whole version is written.
"""

from __future__ import annotations

import ast
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import WIDTH, mother_hash
from ..plans.choose import TINY, balanced_b, balanced_b_column, ceil_log2, field_bits, rung_schedule, rung_schedule_column, shard_bits_for
from ..sources.scratch import file_system, staged
from .packed import Ops, layout, pack, packed_intersect, packed_truncate, packed_union, unpack

RUNGS = "set_id string, shard long, r int, b int, bucket long, n int, f int, words array<bigint>"
NAMES = [c.split()[0] for c in RUNGS.split(", ")]
#: Rows that a packing task gathers before it packs whole sets of them.
CHUNK = 200_000
#: Buckets that meet in one group of a packed operation, as a power of two.
GROUP_BITS = 8


# -- packed rows as arrays ---------------------------------------------------------------------------


def encode(hv: np.ndarray, r: int, b: int) -> tuple[np.ndarray, np.ndarray, int, np.ndarray, np.ndarray]:
    """Sorted distinct r-bit values as buckets: (bucket, count, field bits, all words, words of each)."""
    f = field_bits(r - b)
    lo = layout(f)
    bucket = (hv >> np.uint64(r - b)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])) if len(hv) else np.empty(0, np.int64)
    n = np.diff(np.append(first, len(hv)))
    length = np.maximum(1, -(-n // lo.k))
    start = np.cumsum(length) - length
    # every bucket begins a word: a value goes to the field of its rank
    rank = np.arange(len(hv)) - np.repeat(first, n)
    fields = np.full(int(length.sum()) * lo.k, lo.none, np.uint64)
    fields[np.repeat(start * lo.k, n) + rank] = hv & np.uint64((1 << (r - b)) - 1)
    return bucket[first], n, f, pack(fields.reshape(-1, lo.k), f).ravel(), length


def decode(r: int, b: int, f: int, bucket: int, words: np.ndarray) -> np.ndarray:
    """The r-bit values of one stored bucket."""
    v = unpack(np.asarray(words, np.int64).view(np.uint64)[None, :], f)[0]
    v = v[v != np.uint64((1 << f) - 1)]
    return v | np.uint64(bucket) << np.uint64(r - b) if r > b else np.full(len(v), bucket, np.uint64)


def _ints(rows: pa.RecordBatch | pa.Table, name: str) -> np.ndarray:
    return rows.column(name).to_numpy(zero_copy_only=False) if isinstance(rows, pa.RecordBatch) else rows[name].to_numpy()


def words_of(rows: pa.RecordBatch | pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """All words of stored rows, and how many each row has."""
    col = rows.column("words")
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
        col = pa.concat_arrays(col.chunks) if isinstance(col, pa.ChunkedArray) else col
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.int64, copy=False).view(np.uint64), col.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)


def values_of(rows: pa.RecordBatch | pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(row, value) of all stored values, rows in order and values ascending in each."""
    r, b, f, bucket = (_ints(rows, c).astype(np.int64) for c in ("r", "b", "f", "bucket"))
    words, length = words_of(rows)
    row = np.repeat(np.arange(len(length)), length)
    out: list[tuple[np.ndarray, np.ndarray]] = []
    for width in np.unique(f[length > 0]):
        mine = np.flatnonzero(f[row] == width)
        v = unpack(words[mine][:, None], int(width))
        i, j = np.nonzero(v != layout(int(width)).none)
        out.append((row[mine][i], v[i, j]))
    at, v = (np.concatenate([o[x] for o in out]) if out else np.empty(0, t) for x, t in ((0, np.int64), (1, np.uint64)))
    v = v | np.where(r > b, bucket << np.minimum(r - b, 62), bucket).astype(np.uint64)[at] if len(at) else v
    order = np.argsort(at, kind="stable") if len(out) > 1 else slice(None)
    return at[order], np.where(r[at] > b[at], v, bucket[at].astype(np.uint64))[order] if len(at) else v


Part = tuple  # set_id, shard, r, b, buckets, counts, f, words, words of each


def rung_batch(parts: list[Part]) -> pa.RecordBatch:
    """Parts as one batch of stored rows."""
    rep = [len(p[4]) for p in parts]
    col = lambda i, t: pa.array(np.repeat(np.array([p[i] for p in parts], np.int64), rep), pa.int64()).cast(t)
    cat = lambda i, t: np.concatenate([np.empty(0, t), *(p[i] for p in parts)]).astype(t)
    ends = np.concatenate([[0], np.cumsum(cat(8, np.int64))])
    words = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(cat(7, np.uint64).view(np.int64)))
    names = pa.array([p[0] for p in parts], pa.string()).take(pa.array(np.repeat(np.arange(len(parts)), rep)))
    return pa.RecordBatch.from_arrays([names, col(1, pa.int64()), col(2, pa.int32()), col(3, pa.int32()), pa.array(cat(4, np.int64)), pa.array(cat(5, np.int32)), col(6, pa.int32()), words], NAMES)


def matrix_of(rows: pa.Table, bucket: np.ndarray, f: int, ops: Ops | None = None) -> np.ndarray:
    """One set's rows as a matrix of runs, a line for each of `bucket`; slices of a bucket from several stored rows are united."""
    empty = np.full((len(bucket), 1), layout(f).entry, np.uint64)
    if not rows.num_rows:
        return empty
    words, length = words_of(rows)
    at = np.searchsorted(bucket, _ints(rows, "bucket"))
    order = np.argsort(at, kind="stable")
    sorted_at = at[order]
    first = np.flatnonzero(np.concatenate([[True], sorted_at[1:] != sorted_at[:-1]]))
    layer = np.empty(len(at), np.int64)
    layer[order] = np.arange(len(at)) - np.repeat(first, np.diff(np.append(first, len(at))))
    start = np.cumsum(length) - length
    out = None
    for k in range(int(layer.max()) + 1):
        some = np.flatnonzero(layer == k)
        m = np.full((len(bucket), int(length[some].max())), layout(f).entry, np.uint64)
        line = np.repeat(at[some], length[some])
        inside = np.arange(len(line)) - np.repeat(np.cumsum(length[some]) - length[some], length[some])
        m[line, inside] = words[np.repeat(start[some], length[some]) + inside]
        out = m if out is None else packed_union(out, m, f, ops)
    return out


def parts_of(sid: str, shard: int, r: int, b: int, bucket: np.ndarray, matrix: np.ndarray, f: int) -> list[Part]:
    """A matrix of runs (a line for each bucket) as a part, lines without a value left out."""
    lo = layout(f)
    used = (unpack(matrix, f) != lo.none).sum(1)
    some = np.flatnonzero(used)
    length = -(-used[some] // lo.k)
    keep = np.arange(matrix.shape[1]) < length[:, None]
    return [(sid, shard, r, b, bucket[some], used[some], f, matrix[some][keep], length)] if len(some) else []


# -- building -----------------------------------------------------------------------------------------


def with_hash(family: DataFrame, kind: str = "linear2", seed: int = 0) -> DataFrame:
    return family.withColumn("hs", mother_hash("elem", kind, seed))


def precisions_of(schedule) -> Callable[[int], list[int]]:
    """Precisions of a set by its size: "ladder", "all" above log |S|, or a list."""

    def of(card: int) -> list[int]:
        if isinstance(schedule, list):
            return sorted(schedule)
        if schedule == "all":
            return list(range(max(1, ceil_log2(card)), WIDTH + 1))
        return [WIDTH] if card < TINY else rung_schedule(card)

    return of


def precisions_column(card, schedule):
    if isinstance(schedule, list):
        return F.array(*map(F.lit, sorted(schedule)))
    if schedule == "all":
        return F.sequence(F.greatest(F.lit(1), F.ceil(F.log2(F.greatest(card, F.lit(1)))).cast("int")), F.lit(WIDTH))
    return F.when(card < TINY, F.array(F.lit(WIDTH))).otherwise(rung_schedule_column(card))


def _whole_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables in which every run of equal (g, set_id) is whole. Batches are sorted by both."""
    held: list[pa.RecordBatch] = []
    rows, want = 0, CHUNK
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        rows += batch.num_rows
        if rows < want:
            continue
        t = pa.Table.from_batches(held).combine_chunks()
        cut = int(run_starts(t)[-1])
        if cut:
            yield t.slice(0, cut)
        held = t.slice(cut).to_batches()
        rows -= cut
        want = max(CHUNK, 2 * rows)  # a long run is gathered in doubling steps
    if rows:
        yield pa.Table.from_batches(held).combine_chunks()


def run_starts(t: pa.Table) -> np.ndarray:
    g, sets = _ints(t, "g"), t["set_id"].combine_chunks().dictionary_encode()
    code = (pa.concat_arrays(sets.chunks) if isinstance(sets, pa.ChunkedArray) else sets).indices.to_numpy(zero_copy_only=False)
    return np.flatnonzero(np.concatenate([[True], (code[1:] != code[:-1]) | (g[1:] != g[:-1])]))


def build_rungs(family: DataFrame, schedule="ladder", shard_bits: int | None = None, kind: str = "linear2", seed: int = 0) -> DataFrame:
    """The rungs of every set: schedule is "ladder", "all" precisions above log |S|, or a list of precisions.

    Only sets of 64 elements a shard and more are cut by shard. At the default number of shards they are at most
    65,536 (SHARD_ELEMENTS / 64), so their table is broadcast; all other sets are whole in their group and counted there.
    """
    bits = shard_bits_for(family.count()) if shard_bits is None else shard_bits
    cards = family.groupBy("set_id").agg(F.count("*").alias("card"))
    large = F.broadcast(cards.where(balanced_b_column(F.col("card")) >= bits))
    sized = with_hash(family, kind, seed).join(large, "set_id", "left")
    shard = F.when(F.col("card").isNotNull(), F.shiftrightunsigned("hs", WIDTH - bits)).otherwise(F.lit(-1).cast("long"))
    group = F.when(F.col("card").isNotNull(), shard).otherwise(-1 - F.pmod(F.xxhash64("set_id"), F.lit(1 << bits)))
    precisions = precisions_of(schedule)

    def tiny(t: pa.Table, first: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        """Sets with a single rung of single-value words, all at once."""
        row = np.repeat(first, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        hs = _ints(t, "hs").astype(np.uint64)[row]
        keep = np.concatenate([[True], (hs[1:] != hs[:-1])]) | (np.concatenate([[0], np.diff(np.repeat(np.arange(len(n)), n))]) > 0)
        size = np.bincount(np.repeat(np.arange(len(n)), n)[keep], minlength=len(n))
        words = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]), pa.int32()), pa.array(hs[keep].view(np.int64)))
        same = lambda v, kind: pa.array(np.full(len(n), v), kind)
        return pa.RecordBatch.from_arrays([t["set_id"].combine_chunks().take(pa.array(first)), same(-1, pa.int64()), same(WIDTH, pa.int32()), same(0, pa.int32()), same(0, pa.int64()), pa.array(size.astype(np.int32)), same(field_bits(WIDTH), pa.int32()), words], NAMES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_runs(batches):
            first = run_starts(t)
            n = np.diff(np.append(first, t.num_rows))
            given, shards = t["card"].to_pandas().fillna(-1).to_numpy().astype(np.int64)[first], _ints(t, "shard")[first]
            hs, names = _ints(t, "hs").astype(np.uint64), t["set_id"].take(pa.array(first)).to_pylist()
            few = (n < TINY) & (given < 0) if schedule == "ladder" else np.zeros(len(n), bool)
            if few.any():
                yield tiny(t, first[few], n[few])
            parts: list[Part] = []
            for x in np.flatnonzero(~few):
                card = int(given[x]) if given[x] >= 0 else int(n[x])
                hv, at = np.unique(hs[first[x] : first[x] + n[x]]), WIDTH
                for r in reversed(precisions(card)):
                    hv = np.unique(hv >> np.uint64(at - r)) if at > r else hv
                    at = r
                    parts.append((names[x], int(shards[x]), r, min(r, balanced_b(card)), *encode(hv, r, min(r, balanced_b(card)))))
                if sum(len(p[7]) for p in parts[-8:]) > CHUNK or len(parts) > 2_000:
                    yield rung_batch(parts)
                    parts = []
            if parts:
                yield rung_batch(parts)

    placed = sized.select("set_id", "hs", "card", shard.alias("shard"), group.alias("g"))
    return placed.repartition("g").sortWithinPartitions("g", "set_id", "hs").mapInArrow(run, RUNGS)


def build_dict(family: DataFrame, shard_bits: int | None = None, kind: str = "linear2", seed: int = 0) -> DataFrame:
    """(set_id, shard, hs, elem), placed by shard and sorted, so the elements of a prefix are a range."""
    bits = shard_bits_for(family.count()) if shard_bits is None else shard_bits
    hashed = with_hash(family, kind, seed).withColumn("shard", F.shiftrightunsigned("hs", WIDTH - bits))
    return hashed.select("set_id", "shard", "hs", "elem").repartition("shard").sortWithinPartitions("shard", "set_id", "hs")


@dataclass
class Ladder:
    """Stored sets. catalog: (set_id, card, b, precisions). All parts use one hash (kind, seed) and one number of shards."""

    catalog: DataFrame
    rungs: DataFrame
    dictionary: DataFrame
    shard_bits: int
    kind: str = "linear2"
    seed: int = 0
    schedule: object = "ladder"
    _shapes: dict = field(default_factory=dict, init=False, repr=False)

    def shapes(self, ids: list[str]) -> dict[str, tuple[int, list[int]]]:
        """Size and precisions of the named sets, as many rows as an expression has sets; read once."""
        if new := [s for s in ids if s not in self._shapes]:
            got = {x["set_id"]: (x["card"], sorted(x["precisions"])) for x in self.catalog.where(F.col("set_id").isin(new)).select("set_id", "card", "precisions").collect()}
            self._shapes |= {s: got.get(s, (0, [])) for s in new}
        return {s: self._shapes[s] for s in ids}

    def cards(self, ids: list[str]) -> dict[str, int]:
        return {s: card for s, (card, _) in self.shapes(ids).items()}

    def precisions(self, ids: list[str]) -> dict[str, list[int]]:
        """Of the sets that are there."""
        return {s: p for s, (_, p) in self.shapes(ids).items() if p}


def catalog_of(cards: DataFrame, schedule="ladder") -> DataFrame:
    """(set_id, card) with the shape that a set of that size is stored in."""
    return cards.select("set_id", "card", balanced_b_column(F.col("card")).alias("b"), precisions_column(F.col("card"), schedule).alias("precisions"))


def build_ladder(family: DataFrame, schedule="ladder", shard_bits: int | None = None, kind: str = "linear2", seed: int = 0) -> Ladder:
    """The ladder of a family, not stored yet."""
    bits = shard_bits_for(family.count()) if shard_bits is None else shard_bits
    cards = family.groupBy("set_id").agg(F.count("*").alias("card"))
    return Ladder(catalog_of(cards, schedule), build_rungs(family, schedule, bits, kind, seed), build_dict(family, bits, kind, seed), bits, kind, seed, schedule)


# -- lookup --------------------------------------------------------------------------------------------

#: Prefixes up to which a lookup hands the dictionary's scan exact ranges of hashes, and rows up to which it broadcasts them.
RANGES = 128
BROADCAST_ROWS = 1 << 20


def pruned(dictionary: DataFrame, prefixes: DataFrame, r: int, shard_bits: int) -> tuple[DataFrame, int]:
    """The part of the dictionary that r-bit prefixes (hv) can be in: their shards (at most 2^shard_bits numbers), or few ranges of
    hashes. Also the number of rows of `prefixes`."""
    shard = F.shiftrightunsigned("hv", r - shard_bits) if r >= shard_bits else F.lit(None).cast("long")
    told = prefixes.agg(F.count("*").alias("n"), F.collect_set(shard).alias("shards")).first()
    if not told["n"]:
        return dictionary.where(F.lit(False)), 0
    if r >= shard_bits:
        dictionary = dictionary.where(F.col("shard").isin(sorted(told["shards"])))
    few = [x["hv"] for x in prefixes.select("hv").distinct().limit(RANGES + 1).collect()] if told["n"] <= 64 * RANGES else []
    if 0 < len(few) <= RANGES:
        low = WIDTH - r
        some = F.lit(False)
        for v in sorted(few):
            some = some | ((F.col("hs") >= F.lit(v << low)) & (F.col("hs") <= F.lit(((v + 1) << low) - 1)))
        dictionary = dictionary.where(some)
    return dictionary, told["n"]


def lookup(dictionary: DataFrame, hv: DataFrame, r: int, shard_bits: int | None = None) -> DataFrame:
    """All elements (set_id, elem, hv) whose r-bit prefix is among (set_id, hv). With shard_bits, only touched shards are read."""
    wanted = hv.select("set_id", "hv").distinct()
    if shard_bits is not None:
        dictionary, _ = pruned(dictionary, wanted, r, shard_bits)
    return dictionary.withColumn("hv", F.shiftrightunsigned("hs", WIDTH - r)).join(wanted, ["set_id", "hv"], "left_semi").select("set_id", "elem", "hv")


# -- operations on stored rows ----------------------------------------------------------------------------


def members(rungs: DataFrame) -> DataFrame:
    """(set_id, r, hv): stored rungs unpacked. In a grown store a value may stand in several slices of its bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row, v = values_of(batch)
            at = pa.array(row)
            yield pa.RecordBatch.from_arrays([batch.column("set_id").take(at), batch.column("r").take(at), pa.array(v.astype(np.int64))], ["set_id", "r", "hv"])

    return rungs.select(*NAMES).mapInArrow(run, "set_id string, r int, hv long")


def _kinds(rows: pa.RecordBatch | pa.Table, *names: str) -> tuple[list[tuple], np.ndarray]:
    """Distinct (set_id, whole numbers of other columns), and which of them each row has."""
    sets = rows.column("set_id")
    sets = (pa.chunked_array([sets]) if isinstance(sets, pa.Array) else sets).combine_chunks()
    sets = (pa.concat_arrays(sets.chunks) if isinstance(sets, pa.ChunkedArray) else sets).dictionary_encode()
    words = sets.dictionary.to_pylist()
    stack = np.stack([sets.indices.to_numpy(zero_copy_only=False).astype(np.int64), *(_ints(rows, n).astype(np.int64) for n in names)], 1)
    keys, number = np.unique(stack, axis=0, return_inverse=True)
    return [(words[k[0]], *k[1:]) for k in keys.tolist()], number.ravel()


def _recoded(rows: pa.RecordBatch | pa.Table, b: int, drop: int = 0) -> list[Part]:
    """Rows with `drop` low bits fewer, in buckets of parameter b."""
    row, v = values_of(rows)
    kinds, number = _kinds(rows, "shard", "r")
    of = number[row]
    parts = []
    for k, (sid, shard, old) in enumerate(kinds):
        new = old - drop
        parts.append((sid, shard, new, min(b, new), *encode(np.unique(v[of == k] >> np.uint64(drop)), new, min(b, new))))
    return parts


def rebucket(rungs: DataFrame, b: int, drop: int = 0) -> DataFrame:
    """Rungs at another bucket parameter, and `drop` low bits fewer. Splitting is local; groups that join meet in one shuffle of packed rows."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield rung_batch(_recoded(batch, b, drop))

    def join(rows: pa.Table) -> pa.Table:
        rows = rows.select(NAMES)
        if len(np.unique(_ints(rows, "bucket"))) == rows.num_rows:
            return rows
        x = rows.slice(0, 1).to_pylist()[0]
        row, v = values_of(rows)
        return pa.Table.from_batches([rung_batch([(x["set_id"], x["shard"], x["r"], x["b"], *encode(np.unique(v), x["r"], x["b"]))])])

    dealt = rungs.select(*NAMES).mapInArrow(split, RUNGS)
    return dealt.groupBy("set_id", "r", F.shiftrightunsigned("bucket", GROUP_BITS).alias("g")).applyInArrow(join, RUNGS)


def rebalance(rungs: DataFrame, n: int, w: int = 64) -> DataFrame:
    """Rows of one precision in the buckets that suit n values."""
    return rebucket(rungs, balanced_b(n, w))


def truncate(rungs: DataFrame, drop: int, ops: Ops | None = None) -> DataFrame:
    """`drop` low bits fewer at the same bucket parameter, on packed words: no shuffle. Every rung must have r - drop >= b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = cut(pa.Table.from_batches([batch]), drop)
            if parts:
                yield rung_batch([p for rows in parts for p in rows])

    return rungs.select(*NAMES).mapInArrow(run, RUNGS)


def cut(rows: pa.Table, drop: int, ops: Ops | None = None) -> list[list[Part]]:
    """Rows by (set, shard, r, b), their words cut by the packed kernel and packed into narrower fields."""
    keys, number = _kinds(rows, "shard", "r", "b", "f")
    out = []
    for k, (sid, shard, r, b, f) in enumerate(keys):
        if r - drop < b:
            raise ValueError("more bits than a bucket's remainder has; re-bucket first")
        some = rows.take(pa.array(np.flatnonzero(number == k)))
        bucket = np.unique(_ints(some, "bucket"))
        m = matrix_of(some, bucket, f, ops)
        if drop:
            m = packed_truncate(m, drop, f, ops)
        narrow = field_bits(r - drop - b)
        v = unpack(m, f)
        v = np.where(v == layout(f).none, layout(narrow).none, v)
        out.append(parts_of(sid, shard, r - drop, b, bucket, pack(v, narrow), narrow))
    return out


def to_buckets(hashed: DataFrame, r: int, b: int) -> DataFrame:
    """Bucketed packed sets from (set_id, hv)."""

    def run(rows: pa.Table) -> pa.Table:
        hv = np.unique(rows["hv"].to_numpy()).astype(np.uint64)
        return pa.Table.from_batches([rung_batch([(rows["set_id"][0].as_py(), -1, r, b, *encode(hv, r, b))])])

    return hashed.withColumn("g", F.shiftrightunsigned("hv", max(0, r - b + GROUP_BITS))).groupBy("set_id", "g").applyInArrow(run, RUNGS)


def combine(rungs: DataFrame, left: str, right: str, op: str, b: int | None = None) -> DataFrame:
    """Union ("or") or intersection ("and") of two stored sets at one precision, as set `result`, on packed words.

    Both sides are brought to one bucket parameter, by default the one that suits their sizes together, and meet group by group;
    `rebalance` suits the result to its own size.
    """
    mine = rungs.where(F.col("set_id").isin(left, right))
    if b is None:
        b = balanced_b(mine.agg(F.sum("n").alias("n")).first()["n"] or 1)
    dealt = rebucket(mine, b)

    def run(rows: pa.Table) -> pa.Table:
        x = rows.slice(0, 1).to_pylist()[0]
        bucket = np.unique(_ints(rows, "bucket"))
        p, q = (matrix_of(rows.filter(pa.compute.equal(rows["set_id"], s)), bucket, x["f"]) for s in (left, right))
        z = (packed_intersect if op == "and" else packed_union)(p, q, x["f"])
        return pa.Table.from_batches([rung_batch(parts_of("result", -1, x["r"], x["b"], bucket, z, x["f"]))])

    return dealt.groupBy(F.shiftrightunsigned("bucket", GROUP_BITS).alias("g")).applyInArrow(lambda rows: run(rows.select(NAMES)), RUNGS)


# -- growth ---------------------------------------------------------------------------------------------


@dataclass
class Growth:
    """What a batch of new (set_id, elem) pairs changes: pairs that are really new, and the sets they meet.

    Where size, precisions and bucket parameter of a set stay in shape (`same`), its buckets take new prefixes; new sets, and sets that
    have outgrown their shape (`other`), are built anew from the dictionary.
    """

    ladder: Ladder
    fresh: DataFrame
    same: DataFrame
    other: DataFrame
    cards: DataFrame

    @staticmethod
    def of(ladder: Ladder, batch: DataFrame) -> Growth:
        pairs = staged(with_hash(batch.select("set_id", "elem").distinct(), ladder.kind, ladder.seed), "batch")
        # of the dictionary, only the shards that the batch touches are read, and a small batch is broadcast to them
        known = lookup(ladder.dictionary, pairs.select("set_id", F.col("hs").alias("hv")), WIDTH, ladder.shard_bits)
        fresh = staged(pairs.select("set_id", "elem").join(known.select("set_id", "elem"), ["set_id", "elem"], "left_anti"), "fresh")
        more = fresh.groupBy("set_id").agg(F.count("*").alias("more"))
        before = ladder.catalog.select("set_id", F.col("card").alias("old"), F.col("b").alias("old_b"), F.col("precisions").alias("old_p"))
        grown = more.join(before, "set_id", "left").withColumn("card", F.col("more") + F.coalesce("old", F.lit(0)))
        shape = grown.select("set_id", "card", "old_b", "old_p", balanced_b_column(F.col("card")).alias("b"), precisions_column(F.col("card"), ladder.schedule).alias("p"))
        # a set that is large enough for another kind of place changes b as well
        keeps = F.coalesce((F.col("b") == F.col("old_b")) & (F.col("p") == F.col("old_p")), F.lit(False))
        return Growth(ladder, fresh, shape.where(keeps).select("set_id", "b", "p"), shape.where(~keeps).select("set_id"), grown.select("set_id", "card"))

    def prefixes(self) -> DataFrame:
        """(set_id, r, b, hv, bucket) that sets in shape take."""
        new = with_hash(self.fresh, self.ladder.kind, self.ladder.seed)
        every = new.join(self.same, "set_id").select("set_id", "hs", "b", F.explode("p").alias("r")).select("set_id", "r", F.least("b", "r").alias("b"), F.call_function("shiftrightunsigned", F.col("hs"), F.lit(WIDTH) - F.col("r")).alias("hv"))
        return every.withColumn("bucket", F.call_function("shiftrightunsigned", F.col("hv"), F.col("r") - F.col("b")))

    def rebuilt(self) -> DataFrame:
        """All rungs of the sets that are built anew."""
        held = self.ladder.dictionary.select("set_id", "elem").join(self.other, "set_id", "left_semi")
        whole = held.union(self.fresh.join(self.other, "set_id", "left_semi"))
        return build_rungs(whole, self.ladder.schedule, self.ladder.shard_bits, self.ladder.kind, self.ladder.seed)

    def entries(self) -> DataFrame:
        return build_dict(self.fresh, self.ladder.shard_bits, self.ladder.kind, self.ladder.seed)

    def catalog(self) -> DataFrame:
        old = self.ladder.catalog.select("set_id", "card").join(self.cards.select("set_id"), "set_id", "left_anti")
        return catalog_of(old.union(self.cards), self.ladder.schedule)


def append_elements(ladder: Ladder, batch: DataFrame) -> Ladder:
    """The ladder after new (set_id, elem) pairs; pairs that it holds already change nothing. Touched buckets take the new prefixes by a
    packed union, all others go along as they are."""
    growth = Growth.of(ladder, batch)
    prefixes = growth.prefixes()
    group = F.shiftrightunsigned("bucket", GROUP_BITS).alias("g")
    touched = prefixes.select("set_id", "r", "bucket").distinct()
    old = ladder.rungs.select(*NAMES)
    stay = old.join(touched, ["set_id", "r", "bucket"], "left_anti").join(growth.other, "set_id", "left_anti").select(*NAMES)
    take = old.join(touched, ["set_id", "r", "bucket"], "left_semi").select(*NAMES)

    def unite(key: tuple, rows: pa.Table, more: pa.Table) -> pa.Table:
        r, b = more["r"][0].as_py(), more["b"][0].as_py()
        sid, hv = more["set_id"][0].as_py(), np.unique(more["hv"].to_numpy()).astype(np.uint64)
        add = pa.Table.from_batches([rung_batch([(sid, -1, r, b, *encode(hv, r, b))])])
        rows = rows.select(NAMES)
        shard = rows["shard"][0].as_py() if rows.num_rows else -1
        bucket = np.unique(np.concatenate([_ints(add, "bucket"), _ints(rows, "bucket") if rows.num_rows else np.empty(0, np.int64)]))
        f = field_bits(r - b)
        parts = parts_of(sid, shard, r, b, bucket, packed_union(matrix_of(rows, bucket, f), matrix_of(add, bucket, f), f), f)
        return pa.Table.from_batches([rung_batch(parts)])

    united = take.groupBy("set_id", "r", group).cogroup(prefixes.groupBy("set_id", "r", group)).applyInArrow(unite, RUNGS)
    return replace(ladder, catalog=growth.catalog(), rungs=stay.union(united).union(growth.rebuilt()), dictionary=ladder.dictionary.union(growth.entries()))


def delta_of(ladder: Ladder, batch: DataFrame) -> tuple[Ladder, DataFrame]:
    """Only what a batch adds, as slices of buckets beside the stored ones, with the whole catalog; and the sets that it replaces."""
    growth = Growth.of(ladder, batch)

    def slices(rows: pa.Table) -> pa.Table:
        r, b = rows["r"][0].as_py(), rows["b"][0].as_py()
        hv = np.unique(rows["hv"].to_numpy()).astype(np.uint64)
        return pa.Table.from_batches([rung_batch([(rows["set_id"][0].as_py(), -1, r, b, *encode(hv, r, b))])])

    added = growth.prefixes().groupBy("set_id", "r", F.shiftrightunsigned("bucket", GROUP_BITS).alias("g")).applyInArrow(slices, RUNGS)
    return replace(ladder, catalog=growth.catalog(), rungs=added.union(growth.rebuilt()), dictionary=growth.entries()), growth.other


# -- the store --------------------------------------------------------------------------------------------

#: Versions that a read puts together at most: an append to a longer chain writes a whole version again.
CHAIN = 8


def _complete(spark: SparkSession, path: str, name: str) -> dict[int, int]:
    """Complete versions and what each stands on (itself, if it is whole), from the names of their marks."""
    fs, folder = file_system(spark, f"{path}/{name}")
    if not fs.exists(folder):
        return {}
    names = [str(s.getPath().getName()) for s in fs.listStatus(folder)]
    return dict(tuple(map(int, x.split("-")[1:])) for x in names if x.startswith("complete-"))


def versions(spark: SparkSession, path: str, name: str) -> list[int]:
    """Complete versions of a family, oldest first."""
    return sorted(_complete(spark, path, name))


def _chain(base: dict[int, int], version: int) -> list[int]:
    """A version and those it stands on, down to a whole one."""
    out = [version]
    while base[out[-1]] != out[-1]:
        out.append(base[out[-1]])
    return out


def store_ladder(ladder: Ladder, spark: SparkSession, path: str, name: str, version: int | None = None, keep: int = 2, base: int | None = None, replaced: DataFrame | None = None) -> int:
    """Writes a ladder as the next version of a family (or as a given one, over what an interrupted write left), and drops versions that
    none of the last `keep` stands on. With `base` it holds only what that version lacks, and `replaced` names the sets whose earlier
    rungs don't count any more. Readers see it when all of it is there."""
    have = _complete(spark, path, name)
    number = version if version is not None else (max(have) + 1 if have else 0)
    at = f"{path}/{name}/v{number}"
    ladder.rungs.write.mode("overwrite").partitionBy("r").parquet(f"{at}/rungs")
    # small pages, so that a range of hashes skips most of a shard
    ladder.dictionary.write.mode("overwrite").option("parquet.page.row.count.limit", "512").partitionBy("shard").parquet(f"{at}/dict")
    options = [F.lit(ladder.shard_bits).alias("shard_bits"), F.lit(ladder.kind).alias("kind"), F.lit(ladder.seed).alias("seed"), F.lit(repr(ladder.schedule)).alias("schedule")]
    ladder.catalog.coalesce(1).write.mode("overwrite").parquet(f"{at}/catalog")
    spark.range(1).select(*options).coalesce(1).write.mode("overwrite").parquet(f"{at}/options")
    if replaced is not None:
        replaced.coalesce(1).write.mode("overwrite").parquet(f"{at}/replaced")
    fs, done = file_system(spark, f"{path}/{name}/complete-{number}-{number if base is None else base}")
    fs.create(done, True).close()
    have[number] = number if base is None else base
    needed = {v for last in sorted(have)[-keep:] for v in _chain(have, last)}
    for old in set(have) - needed:
        for part in (f"complete-{old}-{have[old]}", f"v{old}"):
            fs.delete(file_system(spark, f"{path}/{name}/{part}")[1], True)
    return number


def write_ladder(family: DataFrame, path: str, name: str, **options) -> None:
    """Builds a family's ladder and stores it below `path`; writing a family again replaces it. The family is computed once."""
    store_ladder(build_ladder(staged(family.select("set_id", "elem"), "family"), **options), family.sparkSession, path, name)


def read_ladder(spark: SparkSession, path: str, name: str, kind: str | None = None, version: int | None = None) -> Ladder:
    """The newest complete version of a family. A hash kind other than the one it was stored with is refused."""
    have = _complete(spark, path, name)
    if not have or version is not None and version not in have:
        raise FileNotFoundError(f"no complete version of {name} in {path}")
    chain = _chain(have, max(have) if version is None else version)
    at = f"{path}/{name}/v{chain[0]}"
    o = spark.read.parquet(f"{at}/options").first()
    if kind is not None and kind != o["kind"]:
        raise ValueError(f"{name} is stored with hash kind {o['kind']}, not {kind}")
    rungs = dictionary = gone = None
    for v in chain:  # newest first: a version's replaced sets hide the rungs of all before it
        folder = f"{path}/{name}/v{v}"
        part = spark.read.schema(RUNGS).parquet(f"{folder}/rungs").select(*NAMES)
        entries = spark.read.schema("set_id string, hs long, elem long, shard long").parquet(f"{folder}/dict").select("set_id", "shard", "hs", "elem")
        part = part if gone is None else part.join(gone, "set_id", "left_anti").select(*NAMES)
        rungs, dictionary = (part, entries) if rungs is None else (rungs.union(part), dictionary.union(entries))
        if have[v] != v:
            names = spark.read.schema("set_id string").parquet(f"{folder}/replaced")
            gone = names if gone is None else gone.union(names)
    return Ladder(spark.read.parquet(f"{at}/catalog"), rungs, dictionary, o["shard_bits"], o["kind"], o["seed"], ast.literal_eval(o["schedule"]))


def append_to_store(spark: SparkSession, path: str, name: str, batch: DataFrame, version: int | None = None, most: int = CHAIN) -> int:
    """The newest version (before `version`, if given) with a batch appended, as a version of its own that holds only what is new; after
    `most` of those, a whole one. Doing it again gives the same."""
    have = {v: b for v, b in _complete(spark, path, name).items() if version is None or v < version}
    last = max(have)
    old = read_ladder(spark, path, name, version=last)
    if len(_chain(have, last)) >= most:
        return store_ladder(append_elements(old, batch), spark, path, name, version)
    delta, replaced = delta_of(old, batch)
    return store_ladder(delta, spark, path, name, version, base=last, replaced=replaced)
