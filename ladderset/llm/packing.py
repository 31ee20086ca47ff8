"""Best-fit packing of token pieces into sequences, by a configuration linear program.

Only lengths matter to a packing, and there are at most `capacity` of them. So the corpus is tokenised
once, its pieces are counted by length (a histogram of bounded size), and the program over that
histogram is solved on the driver: one variable per configuration (a multiset of lengths that fits a
sequence), one covering row per length. Multiplicative weights solve it: a dynamic program over the
capacity prices the best configuration under the current weights, it is taken up to the scarcest of its
lengths, and the weight of every length falls exponentially with how much of its need that covered. The
cover is scaled until it is feasible, and the weights give a bound from below on any packing. Lengths are
first grouped (equal mass, rounded up), very short ones are left out; the scaled solution is rounded down,
its places are filled with pieces of the group, and what is left over is placed by best fit, in open
sequences first. Best fit decreasing of the whole histogram is planned as well, and the shorter plan is used.

The plan is run lengths: "pieces of length L with ranks r..r+q go to sequences s..s+q at offset o". Its
size depends on the capacity and the number of configurations, never on the corpus, so it is
broadcast. Ranks within a length are counted per salt and added up over a table of (length, salt), so
a length that a third of all pieces have is spread over many tasks.

Defined cases: null text is a document of its end id alone; rows that repeat a doc_id are packed as
they are; an empty table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .support import Scratch, table
from .tokenids import crc32s, encoder, gather, vocabulary

CAPACITY = 4096
#: Most rounds of multiplicative weights, and the relative gap between cover and bound at which they end.
ROUNDS = 900
GAP = 0.004
STEP = 0.15
#: Most groups of lengths in the program; steps of the capacity in its pricing where lengths are grouped; lengths
#: below this share of the capacity are left to best fit.
GROUPS = 96
GRID = 1024
SHORT = 1 / 32


def best_configuration(values: np.ndarray, lengths: np.ndarray, capacity: int) -> np.ndarray:
    """Counts per length of the configuration with the largest total value: an unbounded knapsack over the capacity."""
    best, take = np.zeros(capacity + 1), np.full(capacity + 1, -1, np.int32)
    fits = np.searchsorted(lengths, np.arange(capacity + 1), "right")
    for c in range(int(lengths[0]), capacity + 1):
        k = fits[c]
        got = best[c - lengths[:k]] + values[:k]
        j = int(got.argmax())
        if got[j] > best[c - 1]:
            best[c], take[c] = got[j], j
        else:
            best[c] = best[c - 1]
    counts, c = np.zeros(len(lengths), np.int64), capacity
    while c >= lengths[0]:
        if take[c] < 0:
            c -= 1
        else:
            counts[take[c]] += 1
            c -= lengths[take[c]]
    return counts


@dataclass
class Cover:
    """A fractional cover of all needs by configurations, and prices per length, from which a bound follows."""

    configurations: list[tuple[np.ndarray, float]]
    value: float
    bound: float
    prices: np.ndarray


def configuration_program(lengths: np.ndarray, need: np.ndarray, capacity: int, rounds: int = ROUNDS, step: float = STEP, gap: float = GAP) -> Cover:
    """Covers `need` pieces of each length by as few sequences as it can, fractionally, by multiplicative weights.

    A weight stands for a whole length's need; the price of one piece is its share of it. Any prices bound the
    program from below: no sequence holds more than the best configuration's worth.
    """
    weight = need * lengths / float(need @ lengths)
    covered = np.zeros(len(need))
    taken: list[tuple[np.ndarray, float]] = []
    best, value, bound, prices = 0, np.inf, 0.0, lengths / capacity
    spent = 0.0
    for _ in range(rounds):
        price = weight / need
        counts = best_configuration(price, lengths, capacity)
        if (got := weight.sum() / float(counts @ price)) > bound:
            bound, prices = got, price / float(counts @ price)
        used = counts > 0
        amount = float(np.min(need[used] / counts[used]))
        part = counts * amount / need
        taken.append((counts, amount))
        spent += amount
        covered += part
        weight = weight * np.exp(-step * part)
        weight /= weight.sum()
        if (least := covered.min()) > 0 and spent / least < value:
            best, value = len(taken), spent / least
            if value <= bound * (1 + gap):
                break
    merged: dict[bytes, list] = {}
    scale = sum(a for _, a in taken[:best]) / value if best else 1.0
    for counts, amount in taken[:best]:
        merged.setdefault(counts.tobytes(), [counts, 0.0])[1] += amount / scale
    return Cover([(c, x) for c, x in merged.values()], value, bound, prices)


def dual_bound(lengths: np.ndarray, need: np.ndarray, prices: np.ndarray, capacity: int) -> int:
    """No packing has fewer sequences: all pieces' prices over the most that a sequence can hold."""
    return int(np.ceil(float(need @ prices) / float(best_configuration(prices, lengths, capacity) @ prices) * (1 - 1e-9)))


@dataclass
class Plan:
    """Run lengths of a packing: `rows` of (length, first rank, how many, first sequence, offset)."""

    capacity: int
    sequences: int = 0
    rows: list[tuple[int, int, int, int, int]] = field(default_factory=list)
    lower_bound: int = 0
    method: str = "best fit"

    def arrays(self) -> dict[int, tuple[np.ndarray, ...]]:
        by: dict[int, list] = {}
        for length, *rest in sorted(self.rows):
            by.setdefault(length, []).append(rest)
        return {k: tuple(np.asarray(c, np.int64) for c in zip(*v, strict=True)) for k, v in by.items()}


class Filler:
    """A plan in the making: what is left of each length, and the room in sequences that are open."""

    def __init__(self, histogram: dict[int, int], capacity: int):
        self.plan = Plan(capacity)
        self.left = {k: n for k, n in histogram.items() if n > 0}
        self.rank = dict.fromkeys(self.left, 0)
        self.free: dict[int, list[tuple[int, int]]] = {}  # room -> runs of (first sequence, how many)

    def place(self, length: int, times: int, first: int, offset: int) -> None:
        self.plan.rows.append((length, self.rank[length], times, first, offset))
        self.rank[length] += times
        self.left[length] -= times

    def leave(self, room: int, first: int, times: int) -> None:
        if room and times:
            self.free.setdefault(room, []).append((first, times))

    def open(self, items: list[int], times: int) -> None:
        """`times` new sequences with these lengths."""
        first, offset = self.plan.sequences, 0
        for length in items:
            self.place(length, times, first, offset)
            offset += length
        self.plan.sequences += times
        self.leave(self.plan.capacity - offset, first, times)

    def draw(self, group: list[int], times: int) -> list[tuple[int, int]]:
        """Runs of (length, how many) of a group's longest pieces; `left` is not touched."""
        out = []
        for length in group:
            if (n := min(times, self.spare[length])) > 0:
                out.append((length, n))
                self.spare[length] -= n
                times -= n
        return out

    def fill(self, groups: list[list[int]], counts: np.ndarray, times: int) -> None:
        """`times` sequences of a configuration over groups of lengths (longest first), as far as the groups have pieces."""
        used = [(g, int(c)) for g, c in zip(groups, counts, strict=True) if c]
        times = min([times, *(sum(self.left[k] for k in g) // c for g, c in used)])
        if times <= 0:
            return
        self.spare = self.left.copy()
        slots = [self.draw(g, times) for g, c in used for _ in range(c)]
        cuts = sorted({0, *(e for runs in slots for e in np.cumsum([n for _, n in runs]).tolist())})
        ends = [np.cumsum([n for _, n in runs]) for runs in slots]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            self.open([runs[int(np.searchsorted(e, a, "right"))][0] for runs, e in zip(slots, ends, strict=True)], b - a)

    def best_fit(self) -> Plan:
        """The rest, longest first, each in the open sequence with the least room for it; runs of equal ones move together."""
        for length in sorted((k for k, n in self.left.items() if n > 0), reverse=True):
            while self.left[length]:
                room = min((r for r in self.free if r >= length), default=None)
                if room is None:
                    each = self.plan.capacity // length
                    times = min(self.left[length], -(-self.left[length] // each))
                    self.open([length], times)
                    continue
                first, times = self.free[room].pop()
                if not self.free[room]:
                    del self.free[room]
                if times > self.left[length]:
                    self.leave(room, first + self.left[length], times - self.left[length])
                    times = self.left[length]
                self.place(length, times, first, self.plan.capacity - room)
                self.leave(room - length, first, times)
        return self.plan


def grouped(lengths: list[int], histogram: dict[int, int], most: int = GROUPS) -> list[list[int]]:
    """Runs of neighbouring lengths, about equal in tokens, ascending; inside, longest first."""
    if len(lengths) <= most:
        return [[k] for k in lengths]
    mass = np.cumsum([k * histogram[k] for k in lengths])
    number = np.minimum((mass - 1) * most // int(mass[-1]), most - 1)
    return [[lengths[i] for i in np.flatnonzero(number == g)[::-1]] for g in np.unique(number)]


def program_plan(histogram: dict[int, int], capacity: int, rounds: int = ROUNDS) -> Plan:
    """The configuration program's packing, with the program's bound. Sequences that one piece fills come first."""
    filler = Filler(histogram, capacity)
    if filler.left.get(capacity):
        filler.open([capacity], filler.left[capacity])
    lengths = sorted(k for k, n in filler.left.items() if n > 0)
    every = np.array(lengths, np.int64)
    need = np.array([filler.left[k] for k in lengths], float)
    full, bound = filler.plan.sequences, -(-int(need @ every) // capacity) if lengths else 0
    long = [k for k in lengths if k > capacity * SHORT]
    if long:
        groups = grouped(long, filler.left)
        unit = 1 if len(groups) == len(long) else max(1, capacity // GRID)
        tops = np.array([-(-g[0] // unit) for g in groups], np.int64)
        cover = configuration_program(tops, np.array([sum(filler.left[k] for k in g) for g in groups], float), capacity // unit, rounds)
        for counts, amount in sorted(cover.configurations, key=lambda x: -x[1]):
            filler.fill(groups, counts, int(amount))
        prices = np.interp(every, np.concatenate([[0], tops * unit]), np.concatenate([[0.0], cover.prices]))
        bound = max(bound, *(dual_bound(every, need, x, capacity) for x in (prices, np.where(every > capacity * SHORT, prices, 0.0))))
    plan = filler.best_fit()
    plan.lower_bound, plan.method = full + bound, "program"
    return plan


def plan_packing(histogram: dict[int, int], capacity: int = CAPACITY, rounds: int = ROUNDS) -> Plan:
    """The shorter of the program's packing and best fit decreasing; `lower_bound` holds for any packing."""
    plan = program_plan(histogram, capacity, rounds)
    if plan.sequences > plan.lower_bound and (other := Filler(histogram, capacity).best_fit()).sequences < plan.sequences:
        other.lower_bound = plan.lower_bound
        return other
    return plan


def pieces_of(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Token pieces of at most `capacity` ids; only a document that is longer is cut."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer, end_id)
        for batch in batches:
            doc = batch.column(0)
            for lo, hi, ids, at in enc.batches(batch):
                n = np.diff(at)
                k = -(-n // capacity)
                row = np.repeat(np.arange(hi - lo), k)
                piece = np.arange(len(row)) - np.repeat(np.cumsum(k) - k, k)
                start = piece * capacity
                length = np.minimum(n[row] - start, capacity)
                cut = np.append(at[row] + start, at[-1])
                cols = [doc.slice(lo, hi - lo).take(pa.array(row)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc32s(ids, cut))]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if with_ids:
                    cols.append(pa.LargeListArray.from_arrays(pa.array(cut), pa.array(ids.astype(np.int32))).cast(pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


#: Pieces of one length that one task ranks, about.
RANKED_TOGETHER = 50_000


def pack(pieces: DataFrame, capacity: int = CAPACITY, rounds: int = ROUNDS) -> tuple[DataFrame, Plan]:
    """Adds sequence_id and offset to pieces (staged rows with doc_id, piece, start, length, ids_crc32)."""
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    plan = plan_packing(histogram, capacity, rounds)
    total = sum(histogram.values())
    salts = max(16, total // RANKED_TOGETHER)
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    sizes = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = sizes.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32"))
    ranked = salted.withColumn("inside", inside - 1).join(before, ["length", "salt"]).withColumn("rank", F.col("before") + F.col("inside")).drop("salt", "inside", "before")
    shared = pieces.sparkSession.sparkContext.broadcast(plan.arrays())

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs = shared.value
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            seq, off = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for k in np.unique(length):
                rows = np.flatnonzero(length == k)
                r0, _, s0, o = runs[int(k)]
                j = np.searchsorted(r0, rank[rows], "right") - 1
                seq[rows], off[rows] = s0[j] + rank[rows] - r0[j], o[j]
            keep = [c for c in batch.schema.names if c != "rank"]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(seq), pa.array(off)], [*keep, "sequence_id", "offset"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ranked.schema if f.name != "rank")
    return ranked.mapInArrow(place, schema + ", sequence_id long, offset long"), plan


def assemble(pieces_with_ids: DataFrame, placed: DataFrame) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids, and where each document's piece begins."""
    rows = pieces_with_ids.select("doc_id", "piece", "ids").join(placed.select("doc_id", "piece", "sequence_id", "offset"), ["doc_id", "piece"])
    parts = F.sort_array(F.collect_list(F.struct("offset", "doc_id", "piece", "ids")))  # a sequence has `capacity` ids at most
    return rows.groupBy("sequence_id").agg(parts.alias("parts")).select(
        "sequence_id", F.flatten("parts.ids").alias("ids"), F.col("parts.offset").alias("offsets"), F.col("parts.doc_id").alias("doc_ids")
    )


def best_fit_pack(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    pieces = Scratch(docs.sparkSession, "pack").stage(pieces_of(docs, tokenizer, end_id, capacity, id_col, text_col), "pieces")
    return pack(pieces, capacity)[0].select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit_pack(table(spark, sf_dir, "documents"), vocabulary())
