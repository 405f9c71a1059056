"""Counted costs, balance, locality and degree measures of edge tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.functions.partition import int_div, owner_of
from edgemill.operators.redistribute import sender_of, with_owner


def count_blocks(df: DataFrame, groups: list[str], block: int) -> DataFrame:
    """(groups, rows, blocks): blocks of `block` rows that a sequential pass of each group touches."""
    return df.groupBy(*groups).agg(F.count(F.lit(1)).alias("rows")).withColumn("blocks", F.ceil(F.col("rows") / block).cast("long"))


def block_switches(edges: DataFrame, key: str, block: int, parts: int = 64, order: str = "eid") -> DataFrame:
    """One row: rows, and how often consecutive rows by `order` (dense from 0) touch different target blocks.

    The order is cut into `parts` contiguous pieces, each its own window; a piece's first row meets the last one of the piece before through its stored end.
    """
    total = edges.count()
    piece = F.least(int_div(F.col(order) * F.lit(parts).cast("long"), max(1, total)), F.lit(parts - 1))
    marked = edges.select(piece.alias("piece"), F.col(order).alias("at"), int_div(F.col(key), block).alias("blk"))
    inside = Window.partitionBy("piece").orderBy("at")
    rows = marked.withColumn("last", F.lag("blk").over(inside))
    within = rows.agg(F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum((F.col("last") != F.col("blk")).cast("long")), F.lit(0)).alias("inside"))
    ends = marked.groupBy("piece").agg(F.min_by("blk", "at").alias("first"), F.max_by("blk", "at").alias("final"))  # a row a piece
    edge = Window.partitionBy(F.lit(0)).orderBy("piece")
    between = ends.withColumn("before", F.lag("final").over(edge)).agg(F.coalesce(F.sum((F.col("before") != F.col("first")).cast("long")), F.lit(0)).alias("between"))
    return within.crossJoin(between).select("rows", (F.col("inside") + F.col("between")).alias("switches"))


def message_matrix(edges: DataFrame, layout: Layout, m: int, zeros: bool = True) -> DataFrame:
    """(from_bucket, to_bucket, edges, packets) of shipping generated edges to owners; pairs without edges have zeros."""
    counts = edges.groupBy(sender_of(F.col("eid"), m, layout.nb).alias("from_bucket"), owner_of(F.col("src"), layout.n, layout.nb).alias("to_bucket")).agg(F.count(F.lit(1)).alias("edges"))
    if zeros:
        spark = edges.sparkSession
        cells = spark.range(layout.nb * layout.nb).select(int_div(F.col("id"), layout.nb).alias("from_bucket"), F.pmod("id", F.lit(layout.nb)).alias("to_bucket"))
        counts = cells.join(counts, ["from_bucket", "to_bucket"], "left").select("from_bucket", "to_bucket", F.coalesce("edges", F.lit(0)).alias("edges"))
    return counts.withColumn("packets", F.ceil(F.col("edges") / layout.packet_edges).cast("long"))


def degree_histogram(degrees: DataFrame, value: str = "deg") -> DataFrame:
    """(log2_bin, vertices, total): bin 0 holds degree 0, bin k degrees of k binary digits."""
    return degrees.groupBy(F.when(F.col(value) == 0, 0).otherwise(F.length(F.bin(value))).cast("int").alias("log2_bin")).agg(F.count(F.lit(1)).alias("vertices"), F.sum(value).alias("total"))


def prefix_mass(edges: DataFrame, n: int, parts: int) -> DataFrame:
    """(part, sources, targets): ends in each of `parts` equal id ranges; a biased graph crowds the first."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("s"), F.lit(0).alias("t")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("s"), F.lit(1).alias("t")))).alias("e"))
    return ends.groupBy(owner_of(F.col("e.id"), n, parts).alias("part")).agg(F.sum("e.s").alias("sources"), F.sum("e.t").alias("targets"))


def owner_skew(edges: DataFrame, layout: Layout) -> DataFrame:
    """One row of integers: owners, edges, the largest owner's, and max * owners / edges in thousandths."""
    counts = with_owner(edges, layout).groupBy("bucket").agg(F.count(F.lit(1)).alias("c"))
    return counts.agg(F.sum("c").alias("edges"), F.max("c").alias("most")).select(F.lit(layout.nb).alias("owners"), "edges", "most", int_div(F.col("most") * (1000 * layout.nb), F.col("edges")).alias("skew_milli"))


def owner_gini(edges: DataFrame, layout: Layout) -> DataFrame:
    """Gini coefficient of edges per owner, in a grouped pandas aggregate over nb rows."""
    import pandas as pd

    spark = edges.sparkSession
    counts = with_owner(edges, layout).groupBy("bucket").agg(F.count(F.lit(1)).alias("c"))
    every = spark.range(layout.nb).select(F.col("id").cast("int").alias("bucket")).join(counts, "bucket", "left").select(F.coalesce("c", F.lit(0)).alias("c"))

    def gini(c):
        x = c.sort_values().to_numpy(dtype=float)
        return float((2 * (range(1, len(x) + 1) * x).sum() / x.sum() - (len(x) + 1)) / len(x)) if x.sum() else 0.0

    gini.__annotations__ = {"c": pd.Series, "return": float}  # a grouped aggregate, told by its types
    return every.agg(F.pandas_udf(gini, "double")("c").alias("gini"))


def edge_locality(edges: DataFrame, layout: Layout) -> DataFrame:
    """One row: edges, and those with both ends in one bucket."""
    same = owner_of(F.col("src"), layout.n, layout.nb) == owner_of(F.col("dst"), layout.n, layout.nb)
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.sum(same.cast("long")).alias("local_edges"))


def checksum(edges: DataFrame) -> DataFrame:
    """Order-free sums that differ when an edge does."""
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.sum("src").alias("src_sum"), F.sum("dst").alias("dst_sum"), F.sum(F.pmod(F.col("src") * 31 + F.col("dst") * 17, F.lit(1009))).alias("mixed"))
