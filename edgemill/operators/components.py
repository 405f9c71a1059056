"""Connected components by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.scratch import materialise


def _digest(edges: DataFrame) -> tuple:
    """Number and mixed hash of different edges. Hashes are combined by exclusive or: their sum leaves 64 bits at some 100,000 edges."""
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("h")).first()
    return r.n, r.h


def _to_least(sides: DataFrame) -> DataFrame:
    """Each row (u, v) of a neighbour list with the least id m among u and its neighbours.

    The minima are a table of their own: the join's both sides then come straight from
    an exchange, so adaptive execution can split the list of a hub.
    """
    least = materialise(sides.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "star-least")
    return sides.join(least, "u")


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 64) -> DataFrame:
    """(node, root) for every node of the undirected edges; root is the least id of its component.

    Large-star joins the larger neighbours of each node to the least id nearby,
    small-star the smaller ones; the edges become one star a component
    after a number of rounds that grows with the logarithm of the size. Edges
    are deduplicated each round, none passes through the driver, and each round
    is a table in the shared folder, so lineage stays short.
    """
    ends = edges.select(F.greatest(a, b).cast("long").alias("a"), F.least(a, b).cast("long").alias("b"))
    now = materialise(ends.where("a <> b").groupBy("a", "b").agg(F.lit(0).alias("x")).select("a", "b"), "star")
    before = _digest(now)
    for _ in range(rounds):
        if not before[0]:
            break
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = _to_least(both).where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b")
        large = materialise(large.groupBy("a", "b").agg(F.lit(0).alias("x")).select("a", "b"), "star-large")
        down = large.select(F.col("a").alias("u"), F.col("b").alias("v"))
        own = down.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("a"), F.col("m").alias("b"))
        small = _to_least(down).where("v <> m").select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(own).where("a <> b")
        now = materialise(small.groupBy("a", "b").agg(F.lit(0).alias("x")).select("a", "b"), "star")
        after = _digest(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle; give more rounds")
    roots = now.select(F.col("b").alias("node")).distinct().select("node", F.col("node").alias("root"))
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)
