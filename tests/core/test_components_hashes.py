"""Few edges whose hashes, all near the largest 64-bit number, add up to more than 64 bits."""

import pytest
from pyspark.sql import functions as F

from __spark_entry__ import queries
from edgemill.operators.components import connected_components

LARGE = int(0.9 * (1 << 63))


def test_components_iter_of_links_with_large_hashes(spark, tmp_path):
    """A conversation goes on from turn i to i + 1 only where that edge has a large hash."""
    n = 20_000
    large = {r.id for r in spark.range(n).where(F.xxhash64(F.col("id") + 1, "id") > LARGE).collect()}
    assert sum(large) and len(large) > 600
    rows, conv, turn = [], 0, 0
    for i in range(n):
        rows.append((conv, turn, "user", ""))
        conv, turn = (conv, turn + 1) if i in large else (conv + 1, 0)
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    table.repartition(4).write.parquet(f"{tmp_path}/conversations.parquet")
    want = {}
    for i in range(n):
        if i in large or i - 1 in large:
            want[i] = want[i - 1] if i - 1 in large else i
    assert {(r.node, r.root) for r in queries()["components_iter"](spark, str(tmp_path)).collect()} == set(want.items())


@pytest.mark.parametrize("first", [0, 5 << 33])
def test_links_between_texts_with_large_hashes(spark, first):
    """Pairs of node numbers as the pipeline's stage of near copies gives them out: gaps of 2^33 between partitions."""
    ends = spark.range(20_000).select((F.col("id") * 2 + 1 + first).alias("a"), (F.col("id") * 2).alias("b"))
    edges = ends.where(F.xxhash64("a", "b") > LARGE)
    want = {x for r in edges.collect() for x in ((r.a, r.b), (r.b, r.b))}
    assert len(want) > 1200
    assert {(r.node, r.root) for r in connected_components(edges).collect()} == want
