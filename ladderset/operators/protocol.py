"""Gadgets of the lower bound: disjointness, equality, instances, and what each player's set sends; sampled sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import mother_hash
from ..plans.expr import Expr, Leaf, Node, leaves
from ..sources.families import synthetic
from . import evaluate as E


def is_disjoint(ids: list[str], family: DataFrame) -> DataFrame:
    """(disjoint): whether no element is in all sets; the search stops at the first one."""
    return E.intersect_all(ids, family).limit(1).agg((F.count("*") == 0).alias("disjoint"))


def sets_equal(a: str, b: str, family: DataFrame) -> DataFrame:
    """(equal): fingerprints first (size, sum and xor of hashes), and an exact comparison of what differs."""
    hs = mother_hash("elem")
    prints = family.where(F.col("set_id").isin(a, b)).groupBy("set_id").agg(F.count("*").alias("n"), F.bit_xor(hs).alias("x"), F.sum(F.pmod(hs, F.lit(1 << 31))).alias("s"))
    same = prints.select("n", "x", "s").distinct().agg(F.count("*").alias("kinds"), F.lit(1).alias("j")).join(prints.agg(F.count("*").alias("sets"), F.lit(1).alias("j")), "j")
    differ = family.where(F.col("set_id").isin(a, b)).groupBy("elem").agg(F.count("*").alias("c")).where("c <> 2").limit(1).agg(F.count("*").alias("odd"), F.lit(1).alias("j"))
    return same.join(differ, "j").select(((F.col("kinds") <= 1) & (F.col("sets") != 1) & (F.col("odd") == 0)).alias("equal"))


def equality_instance(e: Expr, one: str = "s0", two: str = "s1") -> Expr:
    """The expression with `one` below the left and `two` below the right side of each topmost intersection: it is one & two."""

    def put(n: Expr, name: str) -> Expr:
        return Leaf(name) if isinstance(n, Leaf) else Node(n.op, tuple(put(c, name) for c in n.children))

    def go(n: Expr) -> Expr:
        if isinstance(n, Leaf):
            raise ValueError("every path needs an intersection")
        if n.op == "and":
            return Node("and", (put(n.children[0], one), *(put(c, two) for c in n.children[1:])))
        return Node(n.op, tuple(map(go, n.children)))

    return go(e)


def unique_intersection(spark: SparkSession, n: int, m: int) -> DataFrame:
    """m sets over n positions that share one position and are otherwise disjoint: n + m - 1 pairs."""
    return synthetic(spark, "unique", n, m)


def transcript(spark: SparkSession, words: dict[str, int], w: int = 64) -> DataFrame:
    """(player, bits): what each set's words, as a run has read them, put on the board."""
    return spark.createDataFrame([(s, n * w) for s, n in words.items()], "player string, bits long")


def coordinated_sample(family: DataFrame, q: int) -> DataFrame:
    """Elements whose lowest q hash bits are 0: the same elements of every set."""
    return family.where(mother_hash("elem").bitwiseAND(F.lit((1 << q) - 1)) == 0)


def sampled_sizes(e: Expr | str, family: DataFrame, q: int) -> DataFrame:
    """(node, sampled, estimate): sizes of all nodes from the coordinated sample, scaled up."""
    e = E.as_expr(e)
    cols = E.mask_columns(len(leaves(e)))
    masks = E.marked(e, coordinated_sample(family, q)).groupBy("elem").agg(*[F.bit_or(c).alias(c) for c in cols])
    m = [F.col(c) for c in cols]
    number = iter(range(1 << 30))
    counts = []

    def conditions(n: Expr):
        """Nodes in the order of plans.expr.walk."""
        at = len(counts)
        counts.append(None)
        if isinstance(n, Leaf):
            c = E.bit_of(next(number), m)
        else:
            kids = [conditions(x) for x in n.children]
            c = kids[0]
            for k in kids[1:]:
                c = {"or": c | k, "and": c & k, "minus": c & ~k}[n.op]
        counts[at] = c
        return c

    conditions(e)
    row = masks.agg(F.array(*[F.count_if(c) for c in counts]).alias("all"))
    return row.select(F.posexplode("all").alias("node", "sampled")).select("node", "sampled", (F.col("sampled") * (1 << q)).alias("estimate"))
