"""Dense positions and prefix sums in two levels."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgemill.scratch import materialise


def starts_of(counts: DataFrame, part: str, count: str = "n", start: str = "start") -> DataFrame:
    """Exclusive running sums over a table with one row per partition or bucket (small by construction)."""
    before = Window.partitionBy(F.lit(0)).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn(start, F.coalesce(F.sum(count).over(before), F.lit(0)))


def dense_position(df: DataFrame, order: list[str], name: str = "eid", partitions: int | None = None) -> DataFrame:
    """Add the 0-based position of each row in the given order (a total one, for a determined result).

    Rows are range partitioned once and stored with their partition; partitions are
    counted, counts summed up, and rows numbered inside their partition.
    """
    spark = df.sparkSession
    partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    stored = materialise(df.repartitionByRange(partitions, *order).withColumn("_part", F.spark_partition_id()), "ranges")
    starts = starts_of(stored.groupBy("_part").agg(F.count(F.lit(1)).alias("n")), "_part").select("_part", "start")
    inside = Window.partitionBy("_part").orderBy(*order)
    # one row a partition: at most `partitions` rows are broadcast
    return stored.join(F.broadcast(starts), "_part").withColumn(name, F.col("start") + F.row_number().over(inside) - 1).drop("_part", "start")
