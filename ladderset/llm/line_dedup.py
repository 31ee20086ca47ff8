"""Line deduplication in DataFrame operations only.

Every text is split at \\n and each line gets a normalised key. A document's distinct keys are hashed and
counted, so counting needs one shuffle of pre-aggregated hashes. Lines whose key is too frequent come back
as narrow (document, position) rows: a bitmap of the frequent hashes is looked at first, so other lines
are never shuffled, and a frequent key is dealt over several tasks. Texts meet their positions once; texts
that a bitmap of marked documents rules out don't move at all. What stays is put together by position,
from the runs of lines between the dropped ones.

Keys and documents are told apart by 128 bits of hashes; two that agreed in all of them would be taken for one.

Defined cases: a null or empty text is one empty line; lines with an empty key always stay; every row counts
as a document, rows that repeat a doc_id included; a null doc_id is kept as it is; an empty table gives an
empty result; further columns of the input, whatever their names, are carried, but `n_lines` and
`n_dropped` replace columns of those names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import Scratch, bitmap_of, quoted, table, with_bitmap

MIN_DOCUMENTS = 10
MIN_KEY_CHARS = 1
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BLANKS = " \t\n\x0b\x0c\r"
#: Tasks over which the lines of one frequent key are dealt.
SALTS = 16
def line_key(line: Column) -> Column:
    """The line without blanks at its ends, A-Z lowered and nothing else.

    The functions for any set of characters build arrays and single characters as they go; where a line has no blank but spaces, and
    where it is ASCII (as many bytes as characters), the common trim() and lower() give the same.
    """
    odd = F.contains(line, F.lit("\t")) | F.contains(line, F.lit("\r")) | F.contains(line, F.lit("\x0b")) | F.contains(line, F.lit("\x0c"))
    ascii = F.octet_length(line) == F.char_length(line)
    bare = F.when(odd, F.btrim(line, F.lit(BLANKS))).otherwise(F.trim(line))
    return F.when(ascii, F.lower(bare)).otherwise(F.translate(bare, UPPER, LOWER))


def _hashes(key: str) -> list[Column]:
    return [F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(17), key).alias("h2")]


def common_lines(docs: DataFrame, min_documents: int, min_key_chars: int) -> DataFrame:
    """(h1, h2) of the keys that so many documents (rows with a text) have."""
    keys = F.array_distinct(F.transform(F.split("text", "\n"), line_key))
    hashed = docs.select(F.explode(keys).alias("key")).where(F.char_length("key") >= min_key_chars).select(*_hashes("key"))
    return hashed.groupBy("h1", "h2").agg(F.count("*").alias("n")).where(F.col("n") >= min_documents).select("h1", "h2")


def common_line_positions(docs: DataFrame, min_documents: int, min_key_chars: int, scratch: Scratch) -> DataFrame:
    """(k1, k2, sorted positions of lines to drop) from columns k1, k2 (document key) and text."""
    common = scratch.stage(common_lines(docs.select("text"), min_documents, min_key_chars), "common")
    lines = docs.select("k1", "k2", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    hashed = lines.select("k1", "k2", "pos", line_key(F.col("line")).alias("key")).select("k1", "k2", "pos", *_hashes("key"))
    near = with_bitmap(hashed, bitmap_of(common, "h1", "h2"), "hit", "h1", "h2").where("hit").withColumn("salt", F.pmod(F.col("k1"), F.lit(SALTS)).cast("int"))
    salted = common.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return near.join(salted, ["h1", "h2", "salt"], "left_semi").groupBy("k1", "k2").agg(F.sort_array(F.collect_set("pos")).alias("dropped"))


#: The lines between dropped ones, joined again; the split text is bound to a lambda variable, so it is made once.
_KEPT = r"""get(transform(array(split(text, '\n')), lines -> array_join(flatten(transform(sequence(0, size(dropped)), j ->
    slice(lines, coalesce(get(dropped, j - 1), -1) + 2, coalesce(get(dropped, j), size(lines)) - coalesce(get(dropped, j - 1), -1) - 1))), '\n')), 0)"""


def drop_common_lines(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_documents: int = MIN_DOCUMENTS, min_key_chars: int = MIN_KEY_CHARS
) -> DataFrame:
    """The documents with their text rewritten, and two more columns: n_lines and n_dropped."""
    carried = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    source = docs.select(
        F.struct(F.lit(0).alias("c"), *[F.col(quoted(c)).alias(f"c{i}") for i, c in enumerate(carried) if c != text_col]).alias("row"),
        F.col(quoted(id_col)).alias("id"),
        F.coalesce(F.col(quoted(text_col)).cast("string"), F.lit("")).alias("text"),
    )
    keyed = source.select("row", "text", F.xxhash64("id", "text").alias("k1"), F.xxhash64(F.lit(29), "text", "id").alias("k2"))
    scratch = Scratch(docs.sparkSession, "line-dedup")
    marks = scratch.stage(common_line_positions(keyed.select("k1", "k2", "text"), min_documents, min_key_chars, scratch), "marks")
    flagged = with_bitmap(keyed, bitmap_of(marks, "k1", "k2"), "hit", "k1", "k2")
    n_lines = (F.octet_length("text") - F.octet_length(F.replace("text", F.lit("\n"), F.lit(""))) + 1).cast("long").alias("n_lines")
    untouched = flagged.where("not hit").select("row", "text", n_lines, F.lit(0).cast("long").alias("n_dropped"))
    met = flagged.where("hit").select("row", "text", "k1", "k2", n_lines).join(marks, ["k1", "k2"], "left")
    rewritten = met.select(
        "row",
        F.when(F.col("dropped").isNull(), F.col("text")).otherwise(F.expr(_KEPT)).alias("text"),
        "n_lines",
        F.coalesce(F.size("dropped"), F.lit(0)).cast("long").alias("n_dropped"),
    )
    both = untouched.unionByName(rewritten)
    return both.select(*[F.col("text").alias(c) if c == text_col else F.col("row").getField(f"c{i}").alias(c) for i, c in enumerate(carried)], "n_lines", "n_dropped")


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = drop_common_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


ORACLE = {
    "op8_line_dedup": """
        WITH cut AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
        line AS (SELECT doc_id, unnest(lines) AS line, unnest(range(len(lines))) AS pos FROM cut),
        keyed AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM line),
        common AS (SELECT k FROM keyed WHERE k <> '' GROUP BY k HAVING count(DISTINCT doc_id) >= 10),
        kept AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY pos) AS body, count(*) AS n
                 FROM keyed WHERE k NOT IN (SELECT k FROM common) GROUP BY doc_id)
        SELECT cut.doc_id, CAST(len(lines) AS BIGINT) AS n_lines, CAST(len(lines) - coalesce(n, 0) AS BIGINT) AS n_dropped,
               sha256(coalesce(body, '')) AS kept_sha256
        FROM cut LEFT JOIN kept USING (doc_id)
    """
}
