"""Queries whose rows come from a given table: right by their SQL, and other at another size of the tables."""

import duckdb
import pytest

from edgemill import catalogue

NAMES = [
    "perm_hash",
    "perm_hash_million",
    "perm_hash_above_power",
    "normalized_time",
    "memory_model",
    "locality",
    "io_model",
    "degree_histogram",
    "capped_memory",
    "biased_vs_relabelled_skew",
    "agg_pivot",
]


@pytest.mark.parametrize("name", NAMES)
def test_results_follow_the_tables(spark, name):
    catalogue.queries()
    entry, seen = catalogue.ENTRIES[name], []
    for sf in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        con = duckdb.connect()
        for table in ("part", "supplier", "orders", "lineitem", "events"):
            con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
        found = entry.query(spark, sf)
        want = con.execute(entry.sql)
        assert found.columns == [c[0] for c in want.description]
        seen.append(sorted(map(tuple, found.collect()), key=str))
        assert seen[-1] == sorted(want.fetchall(), key=str)
    assert seen[0] != seen[1]
