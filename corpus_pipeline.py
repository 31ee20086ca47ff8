"""A corpus pipeline out of the operators in ladderset.llm.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; its result is written as Parquet and read
again as the next stage's documents. All but the last return the columns of `documents`.

Defined cases, in every stage: a null text counts as an empty one; rows with a null doc_id and rows that
repeat a doc_id are documents like any other; an empty table gives an empty result; further columns go along.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ladderset.llm.line_dedup import drop_common_lines
from ladderset.llm.ngram_join import similar_groups
from ladderset.llm.packing import best_fit_pack
from ladderset.llm.quality_rules import apply_rules
from ladderset.llm.support import Scratch, table
from ladderset.llm.tokenids import vocabulary
from ladderset.llm.toxicity import CATEGORIES, category_labels, score_toxicity, train_toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the chain, trained on the labelled ones among them, does not call toxic. Unlabelled ones are judged
    too; a text without words is not toxic; if no document has a label, all stay."""
    chain = train_toxicity(docs, category_labels(table(spark, sf_dir, "labels")), CATEGORIES)
    return score_toxicity(docs, chain).where(~F.col("is_toxic")).select(*docs.columns)


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no rule rejects. A text without ten words, a null or empty one among them, is rejected."""
    return apply_rules(docs).where("kept").select(*docs.columns)


def drop_shared_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without lines that ten documents or more have; n_chars follows the text. A document all of whose lines go stays, with
    an empty text."""
    return drop_common_lines(docs).withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8), the first by a number that each row gets here.

    So rows that repeat a doc_id or have none are members of their groups by their text alone. Texts without words are near
    copies of nothing: all stay.
    """
    row = "row"
    while row in docs.columns:
        row += "_"
    numbered = Scratch(spark, "pipeline-near").stage(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    first = similar_groups(numbered, k=5, num=80, den=100, id_col=row).where("doc_id = component_id").select(F.col("doc_id").alias(row))
    return numbered.join(first, row, "left_semi").select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece with its place. A null or empty text is a piece of its end id alone."""
    return best_fit_pack(docs, vocabulary())


STAGES = [
    ("toxicity", drop_toxic),
    ("quality_rules", drop_low_quality),
    ("line_dedup", drop_shared_lines),
    ("ngram_jaccard_join", keep_one_of_near_copies),
    ("best_fit_packing", pack_sequences),
]

#: Trained weights and a packing cannot be told in SQL; tests hold each stage against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`, each from the last one's files."""
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.stage(stage(spark, docs, sf_dir), name)
    return scratch.stage(STAGES[-1][1](spark, docs, sf_dir), STAGES[-1][0])
