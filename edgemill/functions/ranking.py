"""Gapless ranks without a task that holds a whole key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def cells_for(df: DataFrame) -> int:
    """Pieces that a key is cut into; follows the shuffle width of the session."""
    return max(64, 4 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def rank_within(df: DataFrame, keys: list[str], order: list[str], name: str = "rank", cells: int | None = None) -> DataFrame:
    """Add `name`: 0-based position of each row among the rows with equal `keys`.

    A key may hold most of all rows, so each key is cut into hash cells of the
    ordering columns: cells are counted (map-side combined), the counts of a
    key's cells are summed up (at most `cells` rows a key), and rows are
    numbered inside their cell. The order is by cell, then by `order`; rows
    equal in all of `order` get different numbers. df must not change between
    reads (materialise it if it holds anything nondeterministic).
    """
    cells = cells or cells_for(df)
    cell: Column = F.pmod(F.xxhash64(*order), F.lit(cells)).cast("int")
    marked = df.withColumn("_cell", cell)
    counts = marked.groupBy(*keys, "_cell").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*keys).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(*keys, "_cell", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    inside = Window.partitionBy(*keys, "_cell").orderBy(*order)
    return (
        marked.join(starts, [*keys, "_cell"])
        .withColumn(name, F.col("_start") + F.row_number().over(inside) - 1)
        .drop("_cell", "_start")
    )
