"""Session helpers of the corpus operators: the shared scratch folder, staged tables, bounded bitmap filters."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import goes_with_session

_LOCAL: dict[str, str] = {}


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for staged tables: spark.checkpoint.dir, or else one of our own (a local session only)."""
    conf = spark.sparkContext.getConf()
    if root := conf.get("spark.checkpoint.dir", None):
        return root.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return _LOCAL.setdefault("root", "file://" + tempfile.mkdtemp(prefix="ladderset-"))
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"


class Scratch:
    """Staged tables of one operator run. Each is written once as Parquet, so a lost executor costs no earlier work; they go when the
    program ends."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        goes_with_session(spark, self.path)
        self._n = 0

    def new_path(self, label: str) -> str:
        self._n += 1
        return f"{self.path}/{self._n:02d}-{label}"

    def stage(self, df: DataFrame, label: str, rows: int | None = None) -> DataFrame:
        """The same rows, from files; with `rows`, a bound on narrow rows, in no more files than they fill."""
        path = self.new_path(label)
        if rows is not None:
            df = df.coalesce(max(4, -(-rows // ROWS_OF_A_FILE)))
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *staged: DataFrame) -> None:
        """Frees staged tables that nothing lazy still reads."""
        jvm = self.spark.sparkContext._jvm
        for df in staged:
            path = jvm.org.apache.hadoop.fs.Path(df._scratch_path)
            path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


#: Narrow rows of a staged file, about 1 MB.
ROWS_OF_A_FILE = 25_000
BITMAP_BITS = 1 << 21
_WORD = 64


def bitmap_of(keys: DataFrame, *cols: str) -> DataFrame:
    """A fixed-size bitmap of key hashes: at most BITMAP_BITS / 64 rows (word, bits), whatever the number of keys."""
    slot = F.pmod(F.xxhash64(*cols), F.lit(BITMAP_BITS))
    return (
        keys.select((slot / _WORD).cast("int").alias("_bm_word"), F.pmod(slot, F.lit(_WORD)).cast("int").alias("_bm_bit"))
        .groupBy("_bm_word")
        .agg(F.expr("bit_or(shiftleft(1L, _bm_bit))").alias("_bm_bits"))
    )


def with_bitmap(df: DataFrame, bitmap: DataFrame, flag: str, *cols: str) -> DataFrame:
    """Adds a boolean: false only if the row's key is surely not in the bitmap. The bitmap is broadcast (32,768 rows at most)."""
    slot = F.pmod(F.xxhash64(*cols), F.lit(BITMAP_BITS))
    word, bit = (slot / _WORD).cast("int"), F.pmod(slot, F.lit(_WORD)).cast("int")
    out = df.withColumn("_bm_word", word).withColumn("_bm_bit", bit).join(F.broadcast(bitmap), "_bm_word", "left")
    hit = F.coalesce(F.expr("(shiftrightunsigned(_bm_bits, _bm_bit) & 1L) = 1L"), F.lit(False))
    return out.withColumn(flag, hit).drop("_bm_word", "_bm_bit", "_bm_bits")


def quoted(name: str) -> str:
    """A column's name for F.col, whatever characters it has."""
    return "`" + name.replace("`", "``") + "`"


def plainly_named(df: DataFrame, names: list[str]) -> tuple[DataFrame, list[str]]:
    """Some columns as c0, c1, ..., which mapInArrow takes whatever their names hold, and their types."""
    out = df.select(*[F.col(quoted(n)).alias(f"c{i}") for i, n in enumerate(names)])
    return out, [f.dataType.simpleString() for f in out.schema]


def text_or_empty(col: str) -> Column:
    return F.coalesce(F.col(quoted(col)).cast("string"), F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
