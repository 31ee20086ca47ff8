"""What the engine is compared with: merging, hash probing, search by comparisons, plain hashing, SQL set operators."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import WIDTH
from ..plans.choose import shard_bits_for
from ..plans.expr import Expr, flatten, fold
from . import evaluate as E
from .ladder import with_hash


def leaf_of(family: DataFrame):
    return lambda _, leaf: family.where(F.col("set_id") == leaf.set_id).select("elem")


def merge_sorted(e: Expr | str, family: DataFrame) -> DataFrame:
    """Sorted lists, merged: sort-merge semi-joins and distinct unions."""
    return E.tree(E.as_expr(e), leaf_of(family), "merge")


def hash_probe(e: Expr | str, family: DataFrame) -> DataFrame:
    """Dictionaries: each intersection builds a hash table of one side and probes it with the other."""
    return E.tree(E.as_expr(e), leaf_of(family), "shuffle_hash")


def sql_operators(e: Expr | str, family: DataFrame) -> DataFrame:
    """INTERSECT and UNION as the SQL engine runs them, every intermediate whole."""
    return fold(E.as_expr(e), leaf_of(family), lambda a, b: a.union(b).distinct(), lambda a, b: a.intersect(b), lambda a, b: a.subtract(b))


def full_hashing(e: Expr | str, family: DataFrame) -> DataFrame:
    """Linear-time hashing of the whole input: the finish without a sketch."""
    return E.evaluate(e, family, tier="mask")


def wide_sketch(e: Expr | str, family: DataFrame) -> DataFrame:
    """A sketch of whole hashes, no shorter than the elements."""
    return E.evaluate(e, family, r=WIDTH, mode="global")


def bounded_tree(e: Expr | str, family: DataFrame) -> DataFrame:
    """Alternating unions and intersections of unbounded fan-in over elements themselves, led by size bounds; no hashing, no packing."""
    return E.sketch_by_node(flatten(E.as_expr(e)), family, 0, raw=True).select(F.col("hv").alias("elem"))


def gallop(ids: list[str], family: DataFrame, shard_bits: int | None = None, counts: bool = False) -> DataFrame:
    """The smaller set searched in the larger one by doubling steps, shard by shard; counts=True gives the comparisons made instead.

    Every element starts where the one before it ended, doubles its step until it has passed its place, and halves back.
    """
    card = E.sizes(E.all_of(*ids), family)
    order = sorted(dict.fromkeys(ids), key=lambda s: (card[s], s))
    bits = shard_bits_for(sum(card.values())) if shard_bits is None else shard_bits

    def search(small: np.ndarray, big: np.ndarray) -> tuple[np.ndarray, int]:
        found, spent, at = [], 0, 0
        for x in small.tolist():
            step, low = 1, at
            while at + step <= len(big) and big[at + step - 1] < x:
                spent += 1
                low, step = at + step, step * 2
            spent += at + step <= len(big)
            high = min(at + step - 1, len(big))
            while low < high:
                middle = (low + high) // 2
                spent += 1
                low, high = (middle + 1, high) if big[middle] < x else (low, middle)
            at = low
            if at == len(big):
                break
            spent += 1
            if big[at] == x:
                found.append(x)
        return np.array(found, np.int64), spent

    def run(rows: pa.Table) -> pa.Table:
        sets = {s: np.sort(rows.filter(pa.compute.equal(rows["set_id"], s))["elem"].to_numpy()) for s in order}
        out, spent = sets[order[0]], 0
        for s in order[1:]:
            out, more = search(out, sets[s])
            spent += more
        return pa.table([pa.array([spent] if counts else out, pa.int64())], ["elem"])

    placed = with_hash(family.where(F.col("set_id").isin(ids))).withColumn("shard", F.shiftrightunsigned("hs", WIDTH - bits))
    return placed.select("shard", "set_id", "elem").groupBy("shard").applyInArrow(run, "elem long")


def arrays(ids: list[str], family: DataFrame, shard_bits: int = 6) -> DataFrame:
    """The built-in array_intersect on sorted arrays of each shard."""
    placed = with_hash(family.where(F.col("set_id").isin(ids))).withColumn("shard", F.shiftrightunsigned("hs", WIDTH - shard_bits))
    per = placed.groupBy("shard").pivot("set_id", list(dict.fromkeys(ids))).agg(F.collect_list("elem"))
    out = F.col(f"`{ids[0]}`")
    for s in ids[1:]:
        out = F.array_intersect(out, F.col(f"`{s}`"))
    return per.select(F.explode(out).alias("elem"))


def bitmaps(ids: list[str], family: DataFrame) -> DataFrame:
    """Sizes of an intersection by built-in bitmaps: (k)."""
    marked = family.where(F.col("set_id").isin(ids)).select("set_id", F.call_function("bitmap_bucket_number", F.col("elem")).alias("bucket"), F.call_function("bitmap_bit_position", F.col("elem")).alias("pos"))
    per = marked.groupBy("bucket", "set_id").agg(F.call_function("bitmap_construct_agg", F.col("pos")).alias("bits"))
    both = per.groupBy("bucket").agg(F.call_function("bitmap_and_agg", F.col("bits")).alias("bits"), F.count("*").alias("sets")).where(F.col("sets") == len(set(ids)))
    return both.agg(F.coalesce(F.sum(F.call_function("bitmap_count", F.col("bits"))), F.lit(0)).alias("k"))


def trivial_bits(family: DataFrame) -> DataFrame:
    """Bits of a protocol in which each player sends its whole set as a bit vector over the universe: (player, bits)."""
    top = family.agg((F.max("elem") + 1).alias("n"))
    return family.select("set_id").distinct().crossJoin(F.broadcast(top)).select(F.col("set_id").alias("player"), F.col("n").alias("bits"))
