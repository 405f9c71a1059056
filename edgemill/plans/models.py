"""Printed cost formulas and scaling measures as small tables."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

INT_BYTES, EDGE_BYTES = 8, 16


def io_model(sizes: DataFrame, nb: int, nc: int, block_edges: int) -> DataFrame:
    """(step, variant, unit, blocks): block reads by step for each graph of `sizes` (n vertices, m edges); B = n / nb, b = B / nc and f = m / n, rounded down."""
    rows = [
        ("generate", "per core", "sequential", "small * f"), ("relabel", "per core", "sequential", f"2 * small * f * {INT_BYTES}"),
        ("redistribute", "per node", "sequential", "big * f"), ("redistribute", "per core", "sequential", "small * f"),
        ("csr", "unordered", "random", f"small * {block_edges}"), ("csr", "ordered per node", "sequential", "big"), ("csr", "ordered per core", "sequential", "small"),
        ("csr", "ordered per node, with f", "sequential", "big * f"),
    ]
    parts = sizes.selectExpr(f"n div {nb} AS big", f"n div {nb} div {nc} AS small", "m div n AS f")
    each = ", ".join(f"struct('{step}' AS step, '{variant}' AS variant, '{unit}' AS unit, ({edges}) div {block_edges} AS blocks)" for step, variant, unit, edges in rows)
    return parts.selectExpr(f"inline(array({each}))")


def shuffle_model(spark: SparkSession, n: int, nbs: list[int]) -> DataFrame:
    """(nb, rounds, messages_a_round, work_a_round, total): the shuffle's cost as printed; logs are to base 2, products rounded down."""
    rows = []
    for nb in nbs:
        rounds = 1 if nb < 2 else max(1, math.ceil(math.log(n) / math.log(nb) - 1e-12))
        part = n // nb
        rows.append((nb, rounds, nb * nb, int(part * math.log2(part)), int(n * nb * nb * math.log2(n) ** 2)))
    return spark.createDataFrame(rows, "nb int, rounds int, messages_a_round long, work_a_round long, total long")


def memory_model(sizes: DataFrame, doublings: list[int], bytes_per_vertex: int = 512, node_gib: int = 64) -> DataFrame:
    """(doublings, vertices, gib, nodes) for holding a graph of n vertices, as `sizes` has it, in memory after so many doublings."""
    each = sizes.select("n", F.explode(F.array(*map(F.lit, doublings))).alias("doublings"))
    vertices = F.col("n") * F.expr("shiftleft(1L, doublings)")
    sized = each.select("doublings", vertices.alias("vertices"), F.shiftright(F.lit(bytes_per_vertex).cast("long") * vertices, 30).alias("gib"))
    return sized.withColumn("nodes", F.ceil(F.col("gib") / node_gib).cast("long"))


def shuffle_memory(spark: SparkSession, scale: int, nbs: list[int]) -> DataFrame:
    """(nb, gib_a_node): two buffers of n / nb ids of 8 bytes."""
    return spark.createDataFrame([(nb, 2 * INT_BYTES * ((1 << scale) // nb) >> 30) for nb in nbs], "nb int, gib_a_node long")


def normalize(timings: DataFrame) -> DataFrame:
    """Add seconds / 2^(scale - 16)."""
    return timings.withColumn("norm_seconds", F.col("seconds") / F.pow(F.lit(2.0), F.col("scale") - 16))


def strong_scaling(timings: DataFrame) -> DataFrame:
    """(step, scale, nb, speedup, efficiency) against the fewest nodes of the same step and scale."""
    w = Window.partitionBy("step", "scale").orderBy("nb")
    base = timings.withColumn("t0", F.first("seconds").over(w)).withColumn("nb0", F.first("nb").over(w))
    speedup = F.col("t0") / F.col("seconds")
    return base.select("step", "scale", "nb", speedup.alias("speedup"), (speedup * F.col("nb0") / F.col("nb")).alias("efficiency"))


def weak_scaling(timings: DataFrame) -> DataFrame:
    """(step, scale, nb, ratio) against the smallest scale of the step."""
    w = Window.partitionBy("step").orderBy("scale")
    return timings.select("step", "scale", "nb", (F.col("seconds") / F.first("seconds").over(w)).alias("ratio"))


def throughput(timings: DataFrame, edge_factor: int = 16) -> DataFrame:
    """(run, scale, edges_per_second) of total times."""
    total = timings.groupBy("run", "scale").agg(F.sum("seconds").alias("seconds"))
    return total.select("run", "scale", (F.lit(edge_factor) * F.pow(F.lit(2.0), "scale") / F.col("seconds")).alias("edges_per_second"))
