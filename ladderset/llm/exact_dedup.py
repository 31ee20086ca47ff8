"""Exact duplicates by progressive refinement: length, then prefix hash, then full hash.

Lengths and prefix hashes of all documents are read once into a narrow table. Lengths that occur twice, and
then prefixes that occur twice among those, are counted on it. Whole texts are hashed in a second scan, and
only where a fixed-size bitmap of the surviving (length, prefix) groups says that a document may have an
equal. Groups are counted with partial aggregation before any shuffle, and the documents of large groups
are dealt over many tasks when they meet their group's result, so a group may hold a third of all documents.

Two texts are equal here if length, 64-bit prefix hash and sha256 are.

Defined cases: null text counts as empty; every empty text equals every other; rows that repeat a
doc_id are separate members of their group; a null doc_id never wins over a present one, and in a group
without any present one keep_id is null; exactly one row of each group is kept, also where the largest
doc_id repeats; an empty table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import Scratch, bitmap_of, quoted, table, text_or_empty, with_bitmap

PREFIX_CHARS = 256
#: Members from which a group is dealt over SALTS tasks.
LARGE_GROUP = 1_000
SALTS = 64
GROUP = ("size", "prefix", "full")


def _dealt(rows: DataFrame, large: DataFrame, salt) -> DataFrame:
    """Adds `salt`: 0, or for groups that may be large the given column."""
    return with_bitmap(rows, large, "is_large", *GROUP).withColumn("salt", F.when(F.col("is_large"), salt).otherwise(0)).drop("is_large")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", prefix_chars: int = PREFIX_CHARS, digest: bool = False) -> DataFrame:
    """One row per document: doc_id, keep_id (largest doc_id among equal texts), group_size, kept.

    With digest=True also text_sha256 of every text; the grouping itself hashes only texts that may have an equal.
    """
    scratch = Scratch(docs.sparkSession, "exact-dedup")
    base = docs.select(F.col(quoted(id_col)).alias("doc_id"), text_or_empty(text_col).alias("text"))
    sized = base.withColumns({"size": F.octet_length("text"), "prefix": F.xxhash64(F.substring("text", 1, prefix_chars))})
    heads = scratch.stage(sized.select("size", "prefix"), "heads")
    same_size = heads.groupBy("size").agg(F.count("*").alias("n")).where("n > 1")
    open_heads = with_bitmap(heads, bitmap_of(same_size, "size"), "open", "size").where("open")
    same_prefix = open_heads.groupBy("size", "prefix").agg(F.count("*").alias("n")).where("n > 1")

    sha = F.sha2("text", 256)
    full = F.when(F.col("open"), F.unhex(sha)).alias("full")
    marked = with_bitmap(sized, bitmap_of(same_prefix, "size", "prefix"), "open", "size", "prefix")
    narrow = scratch.stage(
        marked.select("doc_id", "size", "prefix", full, F.monotonically_increasing_id().alias("row"), *([sha.alias("text_sha256")] if digest else [])), "hashed"
    )
    groups = scratch.stage(
        narrow.where("full is not null")
        .groupBy(*GROUP)
        .agg(F.max(F.struct("doc_id", "row")).alias("best"), F.count("*").alias("members"))  # a null doc_id is less than any
        .where("members > 1"),
        "groups",
    )
    large = bitmap_of(groups.where(F.col("members") >= LARGE_GROUP), *GROUP)
    rows = _dealt(narrow, large, F.pmod(F.col("row"), F.lit(SALTS)).cast("int"))
    results = _dealt(groups, large, F.lit(None).cast("int")).withColumn("salt", F.explode(F.when(F.col("salt").isNull(), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array("salt"))))
    alone = F.col("members").isNull()
    return rows.join(results, [*GROUP, "salt"], "left").select(
        "doc_id",
        F.when(alone, F.col("doc_id")).otherwise(F.col("best.doc_id")).alias("keep_id"),
        F.coalesce("members", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("row") == F.col("best.row"))).alias("kept"),
        *(["text_sha256"] if digest else []),
    )


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(table(spark, sf_dir, "documents"), digest=True)


ORACLE = {
    "op1_exact_dedup": """
        SELECT doc_id, max(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size,
               doc_id = max(doc_id) OVER same AS kept, sha256(coalesce(text, '')) AS text_sha256
        FROM documents WINDOW same AS (PARTITION BY coalesce(text, ''))
    """
}
