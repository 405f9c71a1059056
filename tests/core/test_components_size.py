"""Components of more edges than a sum of their 64-bit hashes can hold."""

from pyspark.sql import functions as F

from edgemill.operators.components import _digest, connected_components


def test_many_edges_settle(spark):
    n = 1 << 20  # stars of 8 nodes: 917,504 edges
    edges = spark.range(n).select(F.col("id").alias("a"), (F.col("id") - F.col("id") % 8).alias("b"))
    found = connected_components(edges)
    wrong = F.sum((F.col("root") != F.col("node") - F.col("node") % 8).cast("long"))
    assert tuple(found.agg(F.count(F.lit(1)), F.countDistinct("node"), wrong).first()) == (n, n, 0)


def test_digest_tells_edges_apart(spark):
    edges = spark.range(1 << 20).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert _digest(edges) == _digest(edges.repartition(5))
    other = edges.withColumn("b", F.when(F.col("a") == 77, F.lit(5)).otherwise(F.col("b")))
    assert _digest(edges) != _digest(other)
