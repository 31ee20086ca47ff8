"""What physical plans must show: pushdown, pruning, few shuffles, no cartesian products; and stream and store behaviour."""

import re

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from ladderset.operators import evaluate as E
from ladderset.operators import ladder as L
from ladderset.operators import measure
from ladderset.sources.families import load_families, load_family
from ladderset.functions.hashing import mother_hash, prefix_hash
from ladderset.plans.expr import parse, set_ids
from ladderset.sources.families import TABLES
from ladderset.streaming import streams
from ladderset.workloads import QUERIES, SQL, WORKLOADS

SF = "/root/testdata/sf0.001"


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_scan_is_pruned_and_pushed(spark):
    from ladderset.operators.relational import QUERIES as R

    text = plan(R["scan_pushdown"](spark, SF))
    assert re.search(r"PushedFilters: \[.*GreaterThan\(l_quantity,45", text) and "l_tax" not in text.split("ReadSchema")[1]


def test_relational_tier_has_no_cartesian_and_reuses_its_partitioning(spark):
    fam = load_family(spark, SF, "flag_orders")
    df = E.evaluate("(AF & AO) | (RF & RO)", fam, r=20)
    text = plan(df)
    assert "Cartesian" not in text and "BroadcastNestedLoop" not in text and "Python" not in text
    # distinct family twice, the sketch, and the join: the finish adds none
    assert text.count("Exchange hashpartitioning(hv") <= 2 and "hashpartitioning(elem" not in text.split("Exchange")[1]


def test_a_build_shuffles_elements_once(spark):
    fam = load_family(spark, SF, "flag_orders")
    text = plan(L.build_rungs(fam, shard_bits=3))
    assert "MapInArrow" in text and "FlatMapGroups" not in text
    # distinct pairs (twice: for the sizes as well), sizes, and the one that places elements
    assert text.count("Exchange hashpartitioning(g") == 1


@pytest.fixture(scope="module")
def store(spark, tmp_path_factory):
    path = f"file://{tmp_path_factory.mktemp('store')}"
    L.write_ladder(load_families(spark, "/root/testdata/sf0.01", ["part_orders", "flag_orders"]), path, "f")
    return L.read_ladder(spark, path, "f")


def test_a_packed_query_reads_few_rows_and_moves_no_elements(spark, store):
    """Rungs and dictionary are pruned by precision, shard and ranges of hashes; the dictionary's elements meet a broadcast."""
    df = E.evaluate_packed("7 & AF", store)
    text = plan(df)
    assert re.search(r"PartitionFilters: \[.*shard", text) and re.search(r"PushedFilters: \[.*hs", text)
    dictionary = text[text.index("shard") - 2000 :]
    assert "BroadcastHashJoin" in dictionary and "SortMergeJoin" not in text
    # the only shuffle is of candidates, by prefix and element, for the finish
    assert text.count("Exchange hashpartitioning") == text.count("Exchange hashpartitioning(hv") + text.count("Exchange hashpartitioning(set_id")
    counters = measure.spark_counters(df)
    read, held = measure.total(counters, "Scan", "numOutputRows"), store.dictionary.count()
    assert 0 < read < held / 3
    rungs = plan(E.packed_candidates(E.plan_packed("7 & AF", store), store))
    assert re.search(r"PartitionFilters: \[.*r#\d+ IN", rungs) and "set_id" in rungs.split("PushedFilters")[1]


def test_lookup_reads_touched_shards_only(spark, store):
    one = store.dictionary.where("set_id = 'AF'").limit(1).select("set_id", F.shiftrightunsigned("hs", 40).alias("hv"))
    df = L.lookup(store.dictionary, one, 22, store.shard_bits)
    assert df.count() >= 1 and re.search(r"PartitionFilters: \[.*shard#\d+L? (=|IN)", plan(df))


def test_every_oracle_has_a_query():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert len(QUERIES) > 100


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 15


def test_known_answers(spark):
    want = {"w01_and": 93, "w02_and_or": 130, "w07_months": 1, "w08_uneven": 38, "w13_alternating": 64, "w14_union_path": 22, "w23_labels": 54, "w20_vectors": 61}
    for name, n in want.items():
        assert QUERIES[name](spark, SF).count() == n, name


@pytest.mark.parametrize("name", list(WORKLOADS))
def test_every_workload_on_every_tier(spark, name):
    """The exact answer, by sketch, node by node, on packed words, by masks and by nested operators."""
    families, text = WORKLOADS[name]
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = sorted(r[0] for r in con.execute(SQL[name]).fetchall())
    fam = load_families(spark, SF, list(families)).where(F.col("set_id").isin(set_ids(parse(text)))).cache()
    ladder = L.build_ladder(fam)
    ways = [E.evaluate(text, fam, mode="global", how="nested"), E.evaluate(text, fam, kind="tabulation"), E.evaluate(text, fam, tier="mask"), E.evaluate_packed(text, ladder, lanes=4), E.evaluate_packed(text, ladder, r=9, cap=False, ordered=False, balanced=False, mode="global")]
    if len(set_ids(parse(text))) < 8:
        ways.append(E.evaluate(text, fam, tier="nodes"))
    for i, way in enumerate(ways):
        assert sorted(r[0] for r in way.collect()) == want, i
    fam.unpersist()


def test_an_interrupted_stream_goes_on(spark, tmp_path):
    """Files that come after a stream has ended are taken up from its checkpoint, on top of what the store holds."""
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    source, path = f"file://{tmp_path}/in", f"file://{tmp_path}/out"
    read = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(source)
    for half in (0, 1):
        events.where(F.col("event_id") % 2 == half).repartition(2).write.mode("append").parquet(source)
        got = sorted(map(tuple, streams.grow_ladder(read(), 18, path).select("set_id", "hv").collect()))
        seen = events if half else events.where("event_id % 2 = 0")
        want = sorted(map(tuple, seen.select("event_type", prefix_hash(mother_hash("user_id"), 18)).distinct().collect()))
        assert got == want
        once = streams.run_to_end(read().withWatermark("ts", "36500 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"), path=f"{path}-d")
        assert once.count() == seen.select("user_id", "event_type").distinct().count()


def test_late_rows_are_dropped(spark):
    """Some held-back rows come too late, and those that do are missing."""
    rows = {r["start"]: r["n"] for r in streams.late_data(spark, SF).collect()}
    events = spark.read.parquet(f"{SF}/events.parquet").select(((F.unix_seconds(F.col("ts").cast("timestamp")) / 3600).cast("long") * 3600).alias("start"))
    every = {r["start"]: r["count"] for r in events.groupBy("start").count().collect()}
    assert all(n <= every[s] for s, n in rows.items()) and sum(rows.values()) < sum(every.values())
    assert any(n < every[s] for s, n in rows.items())
