"""Pairs of sources with common targets: against brute force, and without a shuffle that grows with the pairs' common targets."""

import random
from itertools import combinations

import pytest

from edgemill import catalogue
from edgemill.operators.graphops import common_neighbors


@pytest.mark.parametrize("least, block, joined, spread", [(1, 4096, True, 60), (1, 7, False, 60), (3, 16, False, 12), (3, 4096, None, 12), (2, 5, False, 2000)])
def test_against_brute_force(spark, least, block, joined, spread):
    rng = random.Random(least * block)
    targets = {s: set(rng.choices(range(spread), k=rng.randint(1, 9))) for s in range(-20, 60)}
    targets |= {s: set(targets[s - 200]) for s in range(200, 240)} | {300: set(), 301: set(range(spread))}
    rows = [(s, d) for s, held in targets.items() for d in held for _ in range(1 + (s % 3 == 0))] + [(None, 1), (5, None), (None, None)]
    found = common_neighbors(spark.createDataFrame(rows, "src long, dst long"), least, block, joined).collect()
    want = {(a, b, len(targets[a] & targets[b])) for a, b in combinations(sorted(targets), 2) if len(targets[a] & targets[b]) >= least}
    assert len(found) == len(want) and {tuple(r) for r in found} == want


def test_no_edges(spark):
    assert common_neighbors(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_shuffles_lists_and_not_pairs(spark):
    """Every source shares all but one target with every other."""
    def written() -> int:
        executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        return sum(executors.apply(k).totalShuffleWrite() for k in range(executors.size()))

    edges = spark.range(1200 * 100).selectExpr("id div 100 AS src", "IF(id % 100 = 0, 100 + id, id % 100) AS dst")
    before = written()
    assert common_neighbors(edges, 90).count() == 1200 * 1199 // 2
    assert written() - before < 4_000_000


def test_query_agrees_with_its_sql(spark):
    import duckdb

    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    want = con.execute(catalogue.ENTRIES["common_neighbors"].sql).fetchall()
    assert {tuple(r) for r in catalogue.ENTRIES["common_neighbors"].query(spark, sf).collect()} == set(want) and len(want) > 1000
