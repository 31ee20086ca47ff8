"""A Python data source of generated sets, `spark.read.format("ladder_sets")`, and stored ladders as queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .scratch import scratch


class GeneratedSets(DataSource):
    """Options: n (positions), m (sets), k (shared positions), parts. Position i below k is in all sets, any other in set i mod m."""

    @classmethod
    def name(cls) -> str:
        return "ladder_sets"

    def schema(self) -> str:
        return "set_id string, elem long"

    def reader(self, schema):
        return SetReader({k: int(v) for k, v in self.options.items()})


class SetReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.n, self.m, self.k, self.parts = (options.get(o, d) for o, d in (("n", 1000), ("m", 2), ("k", 1), ("parts", 4)))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for i in range(self.n * partition.value // self.parts, self.n * (partition.value + 1) // self.parts):
            for s in range(self.m) if i < self.k else (i % self.m,):
                yield f"s{s}", i


def datasource_sets(spark: SparkSession, folder: str) -> DataFrame:
    spark.dataSource.register(GeneratedSets)
    return spark.read.format("ladder_sets").option("n", 2000).option("m", 3).option("k", 5).load()


def _stored(spark: SparkSession, folder: str):
    from ..operators.ladder import read_ladder, write_ladder
    from .families import load_family

    path = scratch(spark, "ladder")
    write_ladder(load_family(spark, folder, "flag_orders"), path, "flag_orders")
    return read_ladder(spark, path, "flag_orders")


def store_roundtrip(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.evaluate import evaluate_packed

    return evaluate_packed("(AF & AO & NF) | (RF & RO & NO)", _stored(spark, folder))


def partition_pruned_store(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.ladder import members

    return members(_stored(spark, folder).rungs.where("r = 62")).select("set_id", "hv")


def _sql() -> dict[str, str]:
    from ..functions.hashing import mother_hash_sql
    from ..plans.expr import parse, to_sql
    from .families import family_sql

    fam = family_sql("flag_orders")
    body = to_sql(parse("(AF & AO & NF) | (RF & RO & NO)"), lambda s: f"SELECT elem FROM fam WHERE set_id = '{s}'")
    return {
        "datasource_sets": "SELECT concat('s', CAST(s AS STRING)) AS set_id, CAST(i AS BIGINT) AS elem FROM (SELECT unnest(range(2000)) AS i), (SELECT unnest(range(3)) AS s) WHERE i < 5 OR i % 3 = s",
        "store_roundtrip": f"WITH fam AS ({fam}) SELECT * FROM {body}",
        "partition_pruned_store": f"SELECT set_id, {mother_hash_sql('elem')} AS hv FROM ({fam})",
    }


QUERIES = {"datasource_sets": datasource_sets, "store_roundtrip": store_roundtrip, "partition_pruned_store": partition_pruned_store}
SQL = _sql()
