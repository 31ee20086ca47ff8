"""Queries over whole tables give the rows of their SQL, and rows that the filtered ones leave out."""

import duckdb
import pytest

import __spark_entry__ as entry

FOLDER = "/root/testdata/sf0.01"
NAMES = ["join_lateral", "fn_array", "agg_collect_sets", "join_outer_full", "fn_struct_nested", "dict_lookup", "fn_map", "hash_prefix_r", "join_inner_hash", "join_sort_merge"]


@pytest.mark.parametrize("name", NAMES)
def test_whole(spark, name):
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem", "documents", "labels", "benchmark", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{FOLDER}/{t}.parquet'")
    frame = entry.queries()[name](spark, FOLDER)
    got, want = (sorted(map(tuple, x), key=str) for x in (frame.collect(), con.execute(entry.oracle_sql()[name]).fetchall()))
    assert got == want and got
