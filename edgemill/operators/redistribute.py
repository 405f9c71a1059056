"""Shipping edges to the owners of their sources: plain, in packets, sorted, and salted."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.functions.partition import bin_of, int_div, lane_of, owner_of
from edgemill.operators.positions import starts_of


def with_owner(edges: DataFrame, layout: Layout) -> DataFrame:
    """Add bucket and lane of the source."""
    return edges.withColumn("bucket", owner_of(F.col("src"), layout.n, layout.nb).cast("int")).withColumn("lane", lane_of(F.col("src"), layout).cast("int"))


def ship_to_owner(edges: DataFrame, layout: Layout, level: str = "bucket") -> DataFrame:
    """One exchange by exact range: partition i holds bucket (or lane) i and nothing else. No bounds are sampled, no ids hashed."""
    owned = with_owner(edges, layout)
    if level == "bucket":
        return owned.repartitionById(layout.nb, F.col("bucket"))
    return owned.repartitionById(layout.nb * layout.nc, bin_of(F.col("src"), layout).cast("int"))


def ship_sorted(edges: DataFrame, layout: Layout) -> DataFrame:
    """The ordered form: the receiver merges sorted runs, so a bucket is one sequence by (src, dst, eid). The sort begins with bucket, which later windows reuse."""
    return ship_to_owner(edges, layout).sortWithinPartitions("bucket", "src", "dst", "eid")


#: The place in a partition is what monotonically_increasing_id keeps below this bit.
_PLACE_BITS = 33


def ship_ranked(edges: DataFrame, layout: Layout) -> DataFrame:
    """(bucket, rank, eid, src, dst): sorted shipping with each edge's 0-based place in its bucket.

    A partition is a bucket and sorted, so the place is a running counter of the task: no window
    holds a bucket. One exchange and one sort of the edges; store the result, and compression is a scan.
    """
    shipped = ship_sorted(edges, layout)
    return shipped.select("bucket", F.monotonically_increasing_id().bitwiseAND((1 << _PLACE_BITS) - 1).alias("rank"), "eid", "src", "dst")


def sorted_runs(edges: DataFrame, layout: Layout) -> DataFrame:
    """(run, bucket, eid, src, dst): the sender's side of the ordered form. Each partition sorts its edges by (bucket, src, dst, eid); a run is what one sender has."""
    owned = with_owner(edges, layout).select(F.spark_partition_id().alias("run"), "bucket", "eid", "src", "dst")
    return owned.sortWithinPartitions("bucket", "src", "dst", "eid")


def _merged(runs: list[np.ndarray]) -> np.ndarray:
    """Sorted runs of rows (src, dst, eid) as one, two by two: every level moves each row once, to its own place plus those of the other run before it."""
    while len(runs) > 1:
        paired = []
        for a, b in zip(runs[::2], runs[1::2]):
            out = np.empty(len(a) + len(b), a.dtype)
            out[np.arange(len(a)) + np.searchsorted(b, a, "left")] = a
            out[np.arange(len(b)) + np.searchsorted(a, b, "right")] = b
            paired.append(out)
        runs = paired + runs[len(runs) // 2 * 2 :]
    return runs[0]


def merge_sorted_runs(runs: DataFrame, layout: Layout) -> DataFrame:
    """(bucket, rank, eid, src, dst): the collector merges the sorted runs it has received, without sorting again.

    A bucket is one Arrow call, so buckets should be of some hundred megabytes (Layout.for_edges).
    A run that arrives out of order raises.
    """
    from edgemill.shipping import ship_package

    ship_package(runs.sparkSession)
    order = np.dtype([("src", ">u8"), ("dst", ">u8"), ("eid", ">u8")])

    def collect(rows: pa.Table) -> pa.Table:
        wide = np.empty(rows.num_rows, order)
        for c in order.names:
            wide[c] = rows.column(c).to_numpy()
        # big-endian bytes of non-negative numbers compare like the numbers
        keys = wide.view("S24")
        sender = rows.column("run").to_numpy()
        held = [keys[sender == k] for k in np.unique(sender)]
        for run in held:
            if (run[1:] < run[:-1]).any():
                raise ValueError("a run is not sorted")
        whole = _merged(held).view(order)
        columns = {"bucket": rows.column("bucket"), "rank": np.arange(len(whole))} | {c: whole[c].astype(np.int64) for c in ("eid", "src", "dst")}
        return pa.table(columns)

    return runs.groupBy("bucket").applyInArrow(collect, "bucket int, rank long, eid long, src long, dst long")


def sender_of(eid, m: int, parts: int):
    """The bucket that generated an edge: contiguous shares of the edge positions."""
    return int_div(eid * F.lit(parts).cast("long"), m)


def packetize(edges: DataFrame, layout: Layout, m: int) -> DataFrame:
    """(src_bucket, dst_bucket, packet_no, edges): packets of at most packet_bytes for each pair of buckets, full but for the last.

    A pair of buckets may hold most edges, so positions inside a pair are counted by chunk first and numbered inside a chunk.
    """
    keys = ["src_bucket", "dst_bucket"]
    routed = edges.select(
        "eid", "src", "dst", sender_of(F.col("eid"), m, layout.nb).cast("int").alias("src_bucket"), owner_of(F.col("src"), layout.n, layout.nb).cast("int").alias("dst_bucket"), int_div(F.col("eid"), layout.chunk_edges).alias("chunk")
    )
    counts = routed.groupBy(*keys, "chunk").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy(*keys).orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(*keys, "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    nth = F.col("start") + F.row_number().over(Window.partitionBy(*keys, "chunk").orderBy("eid")) - 1
    placed = routed.join(starts, [*keys, "chunk"]).withColumn("packet_no", int_div(nth, layout.packet_edges))
    return placed.groupBy(*keys, "packet_no").agg(F.sort_array(F.collect_list(F.struct("eid", "src", "dst"))).alias("edges"))


def collect_packets(packets: DataFrame) -> DataFrame:
    """The edges of packets, with the bucket that received them."""
    return packets.select(F.col("dst_bucket").alias("bucket"), F.explode("edges").alias("e")).select("e.eid", "e.src", "e.dst", "bucket")


def all_arrived(packets: DataFrame, m: int) -> bool:
    return packets.agg(F.sum(F.size("edges"))).first()[0] == m


def ship_balanced(edges: DataFrame, layout: Layout, most: int) -> DataFrame:
    """Owners of more than `most` edges get several partitions: (bucket, part), at most `most` edges each.

    Sources are counted, sources of a bucket laid end to end by id, and positions cut at `most`; a hub's edges may span parts.
    """
    owned = with_owner(edges, layout)
    degrees = owned.groupBy("bucket", "src").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("bucket").orderBy("src").rowsBetween(Window.unboundedPreceding, -1)
    starts = degrees.select("bucket", "src", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    chunked = owned.withColumn("chunk", int_div(F.col("eid"), layout.chunk_edges))
    counts = chunked.groupBy("bucket", "src", "chunk").agg(F.count(F.lit(1)).alias("n"))
    inside = Window.partitionBy("bucket", "src").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("bucket", "src", "chunk", F.coalesce(F.sum("n").over(inside), F.lit(0)).alias("skip"))
    nth = F.row_number().over(Window.partitionBy("bucket", "src", "chunk").orderBy("eid")) - 1
    placed = chunked.join(offsets, ["bucket", "src", "chunk"]).withColumn("nth", nth).join(starts, ["bucket", "src"])
    return placed.select("eid", "src", "dst", "bucket", int_div(F.col("start") + F.col("skip") + F.col("nth"), most).alias("part"))


def scatter_gather(df: DataFrame, key, gatherers: int) -> DataFrame:
    """k scatter tasks and one gather partition for each owner: one exchange by partition number."""
    return df.repartitionById(gatherers, key.cast("int"))


def bucket_bases(owned: DataFrame) -> DataFrame:
    """(bucket, base): edges in all buckets before; one row a bucket."""
    return starts_of(owned.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")), "bucket", start="base").select("bucket", "base")
