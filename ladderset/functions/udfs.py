"""Vectorised user functions: packing, mask aggregates, table functions over expressions and packed rows."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.packed import compact, layout, pack_run, unpack, unpack_run
from ..plans.expr import fold, parse

QUERIES: dict = {}
SQL: dict[str, str] = {}


@F.pandas_udf(T.ArrayType(T.LongType()))
def pack_values(values: pd.Series, f: pd.Series) -> pd.Series:
    """Packed words of arrays of distinct integers below 2^f - 1."""
    return pd.Series([pack_run(np.sort(np.asarray(v, np.uint64)), int(b)).view(np.int64) for v, b in zip(values, f, strict=True)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def unpack_values(words: pd.Series, f: pd.Series) -> pd.Series:
    return pd.Series([unpack_run(np.asarray(w, np.int64).view(np.uint64), int(b)).astype(np.int64) for w, b in zip(words, f, strict=True)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def compact_values(words: pd.Series, f: pd.Series) -> pd.Series:
    """Packed words without the entries that are multiples of 3, moved to the front."""
    out = []
    for w, b in zip(words, f, strict=True):
        lo, z = layout(int(b)), np.asarray(w, np.int64).view(np.uint64)[None, :]
        v = unpack(z, int(b)).reshape(z.shape[1], lo.k)
        gone = ((v % np.uint64(3) == 0) | (v == lo.none)).astype(np.uint64)
        marks = np.bitwise_or.reduce(gone << (np.arange(lo.k, dtype=np.uint64) * np.uint64(lo.g) + np.uint64(lo.f)), axis=1)[None, :]
        out.append(compact(z, marks, int(b))[0].view(np.int64))
    return pd.Series(out)


def packed_compact(spark: SparkSession, folder: str) -> DataFrame:
    arrays = _families(spark, folder).withColumn("g", F.floor(F.col("elem") / 64)).groupBy("set_id", "g").agg(F.collect_set("elem").alias("v"))
    kept = arrays.withColumn("u", unpack_values(compact_values(pack_values("v", F.lit(40)), F.lit(40)), F.lit(40)))
    return kept.select("set_id", F.posexplode("u").alias("pos", "elem"))


def mask_holds(text: str):
    """A grouped aggregate: whether the or of provenance masks satisfies the expression."""
    e = parse(text)

    @F.pandas_udf(T.BooleanType())
    def holds(mask: pd.Series) -> bool:
        m = int(np.bitwise_or.reduce(mask.to_numpy()))
        return bool(fold(e, lambda i, _: m >> i & 1, lambda a, b: a | b, lambda a, b: a & b, lambda a, b: a & ~b & 1))

    return holds


@F.udtf(returnType=T.StructType([T.StructField("node", T.IntegerType()), T.StructField("parent", T.IntegerType()), T.StructField("op", T.StringType()), T.StructField("set_id", T.StringType())]))
class ExpressionNodes:
    """Rows of an expression's nodes, from its text."""

    def eval(self, text: str):
        from ladderset.plans.expr import Leaf, parse, walk

        for me, parent, n in walk(parse(text)):
            yield me, parent, "leaf" if isinstance(n, Leaf) else n.op, n.set_id if isinstance(n, Leaf) else None


@F.udtf(returnType=T.StructType([T.StructField("hv", T.LongType())]))
class PackedMembers:
    """Values of one stored bucket."""

    def eval(self, r: int, b: int, f: int, bucket: int, words: list):
        import numpy as np

        from ladderset.operators.ladder import decode

        for v in decode(r, b, f, bucket, np.array(words)):
            yield (int(v),)


def _families(spark: SparkSession, folder: str) -> DataFrame:
    from ..sources.families import load_family

    return load_family(spark, folder, "flag_orders")


def udf_pack_unpack(spark: SparkSession, folder: str) -> DataFrame:
    arrays = _families(spark, folder).withColumn("g", F.floor(F.col("elem") / 64)).groupBy("set_id", "g").agg(F.collect_set("elem").alias("v"))
    back = arrays.withColumn("w", pack_values("v", F.lit(40))).withColumn("u", unpack_values("w", F.lit(40)))
    return back.select("set_id", F.explode("u").alias("elem"))


def udaf_mask_eval(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.evaluate import marked

    text = "(AF & AO) | (RF & RO)"
    rows = marked(parse(text), _families(spark, folder))
    return rows.groupBy("elem").agg(mask_holds(text)("m0").alias("ok")).where("ok").select("elem")


def udtf_expr_nodes(spark: SparkSession, folder: str) -> DataFrame:
    return ExpressionNodes(F.lit("(AF & AO) | RF"))


def udtf_set_members(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.ladder import build_rungs

    spark.udtf.register("packed_members", PackedMembers)
    build_rungs(_families(spark, folder), schedule=[16]).createOrReplaceTempView("stored_rungs")
    return spark.sql("SELECT set_id, hv FROM stored_rungs, LATERAL packed_members(r, b, f, bucket, words)")


def _register() -> None:
    from ..functions.hashing import mother_hash_sql
    from ..sources.families import family_sql

    fam = family_sql("flag_orders")
    one = lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'"
    QUERIES.update(packed_compact=packed_compact, udf_pack_unpack=udf_pack_unpack, udaf_mask_eval=udaf_mask_eval, udtf_expr_nodes=udtf_expr_nodes, udtf_set_members=udtf_set_members)
    SQL.update(
        udf_pack_unpack=fam,
        packed_compact=f"SELECT set_id, CAST(row_number() OVER (PARTITION BY set_id, elem // 64 ORDER BY elem) - 1 AS INT) AS pos, elem FROM ({fam}) WHERE elem % 3 <> 0",
        udaf_mask_eval=f"WITH fam AS ({fam}) ({one('AF')} INTERSECT {one('AO')}) UNION ({one('RF')} INTERSECT {one('RO')})",
        udtf_expr_nodes="SELECT * FROM (VALUES (0, -1, 'or', NULL), (1, 0, 'and', NULL), (2, 1, 'leaf', 'AF'), (3, 1, 'leaf', 'AO'), (4, 0, 'leaf', 'RF')) t(node, parent, op, set_id)",
        udtf_set_members=f"SELECT DISTINCT set_id, {mother_hash_sql('elem')} >> 46 AS hv FROM ({fam})",
    )


_register()
__all__ = ["ExpressionNodes", "PackedMembers", "QUERIES", "SQL", "mask_holds", "pack_values", "unpack_values"]
