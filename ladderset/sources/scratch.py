"""Tables that are written once and read again: they cut lineage, so a lost executor costs no earlier work."""

from __future__ import annotations

import atexit
import contextlib
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []


def goes_with_session(spark: SparkSession, path: str) -> None:
    """Marks a folder to be removed when the program ends."""
    _made.append((spark, path))


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder shared by driver and executors: below spark.checkpoint.dir, or else below the warehouse. It goes with the session."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    path = f"{root.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"
    goes_with_session(spark, path)
    return path


def staged(df: DataFrame, label: str) -> DataFrame:
    """The same rows, from files."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def file_system(spark: SparkSession, path: str):
    """Hadoop's file system of a path, and the path as it wants it."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


@atexit.register
def _remove() -> None:
    for spark, path in _made:
        with contextlib.suppress(Exception):  # the JVM may be gone
            fs, p = file_system(spark, path)
            fs.delete(p, True)
