"""Compressed sparse rows as two tables, offsets (id, off) with n + 1 rows and neighbors (pos, dst) with m rows."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.functions.partition import int_div, owner_of
from edgemill.operators.positions import starts_of
from edgemill.operators.redistribute import bucket_bases, merge_sorted_runs, ship_ranked, sorted_runs
from edgemill.scratch import materialise


@dataclass(frozen=True)
class Csr:
    offsets: DataFrame
    neighbors: DataFrame
    layout: Layout
    m: int


def out_degrees(edges: DataFrame, layout: Layout, endpoint: str = "src") -> DataFrame:
    """(bucket, id, deg) of every vertex, isolated ones among them.

    Vertices enter as rows of zero before the only exchange, which costs less than a join.
    """
    spark = edges.sparkSession
    zeros = spark.range(layout.n).select("id", F.lit(0).cast("long").alias("one"))
    ones = edges.select(F.col(endpoint).alias("id"), F.lit(1).cast("long").alias("one"))
    partial = zeros.unionByName(ones).groupBy(owner_of(F.col("id"), layout.n, layout.nb).cast("int").alias("bucket"), "id")
    return partial.agg(F.sum("one").alias("deg"))


def in_degrees(edges: DataFrame, layout: Layout) -> DataFrame:
    return out_degrees(edges, layout, "dst")


def prefix_offsets(degrees: DataFrame, layout: Layout) -> DataFrame:
    """Offsets by two-level prefix sums: nb bucket totals, then running sums inside each bucket, and the last row (n, m)."""
    totals = starts_of(degrees.groupBy("bucket").agg(F.sum("deg").alias("n")), "bucket", start="base")
    before = Window.partitionBy("bucket").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    # one row a bucket is broadcast
    inner = degrees.join(F.broadcast(totals.select("bucket", "base")), "bucket").select("id", (F.col("base") + F.coalesce(F.sum("deg").over(before), F.lit(0))).alias("off"))
    last = degrees.agg(F.coalesce(F.sum("deg"), F.lit(0)).alias("off")).select(F.lit(layout.n).cast("long").alias("id"), "off")
    return inner.unionByName(last)


def csr_from_sorted(ranked: DataFrame, layout: Layout) -> Csr:
    """One linear scan of stored buckets in order (bucket, rank, eid, src, dst): a neighbour's place is its bucket's base plus its rank.

    No edge is exchanged or sorted: bases are one row a bucket and broadcast, and degrees are partial sums of
    each file before they move. Edges without ranks are shipped first.
    """
    if "rank" not in ranked.columns:
        ranked = materialise(ship_ranked(ranked.select("eid", "src", "dst"), layout), "owned")
    bases = bucket_bases(ranked)
    neighbors = ranked.select("bucket", "rank", "dst").join(F.broadcast(bases), "bucket").select((F.col("base") + F.col("rank")).alias("pos"), "dst")
    return Csr(prefix_offsets(out_degrees(ranked, layout), layout), neighbors, layout, -1)


def csr_ordered(edges: DataFrame, layout: Layout) -> Csr:
    """Sorted shipping into a stored table, then the scan. Upstream is computed once, edges are exchanged once."""
    return csr_from_sorted(materialise(ship_ranked(edges, layout), "owned"), layout)


def csr_merged(edges: DataFrame, layout: Layout) -> Csr:
    """The ordered form with runs sorted by their senders and merged by the collector, then the scan."""
    return csr_from_sorted(materialise(merge_sorted_runs(sorted_runs(edges, layout), layout), "owned"), layout)


def _slotted(edges: DataFrame, offsets: DataFrame, layout: Layout) -> DataFrame:
    """(eid, pos, dst): each edge's own slot in its source's slice, in order of eid.

    The slot counts in two levels, edges of the source in earlier chunks and earlier edges of its chunk, so a hub is in no single window.
    """
    chunked = edges.withColumn("chunk", int_div(F.col("eid"), layout.chunk_edges))
    counts = chunked.groupBy("src", "chunk").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("src").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    cursors = counts.select("src", "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("cursor")).join(offsets.withColumnRenamed("id", "src"), "src")
    nth = F.row_number().over(Window.partitionBy("src", "chunk").orderBy("eid")) - 1
    return chunked.join(cursors, ["src", "chunk"]).select("eid", (F.col("off") + F.col("cursor") + nth).alias("pos"), "dst")


def csr_unordered(edges: DataFrame, layout: Layout) -> Csr:
    """Degrees, prefix sums, scatter: each edge gets its own slot in its source's slice, in order of eid, without a sort of the edge list. `edges` is read three times; store it first."""
    offsets = materialise(prefix_offsets(out_degrees(edges, layout), layout), "offsets")
    return Csr(offsets, _slotted(edges, offsets, layout).select("pos", "dst"), layout, -1)


def naive_external_csr(edges: DataFrame, layout: Layout) -> DataFrame:
    """(eid, pos, dst): the writes of a hash kernel put on disk as it is, in the order in which edges arrive (measures.block_switches of pos counts its random accesses)."""
    return _slotted(edges, prefix_offsets(out_degrees(edges, layout), layout), layout)


def degrees_flushed(edges: DataFrame, layout: Layout, threshold: int) -> DataFrame:
    """(chunk, flushes): how often a map of at most `threshold` sources empties while a chunk streams by, its last time included.

    Sequential by definition, so each chunk (chunk_edges edges) is one Arrow call; inside, a flush is one search in an array.
    """
    import numpy as np
    import pyarrow as pa

    def count(rows: pa.Table) -> pa.Table:
        src = rows.sort_by("eid").column("src").to_numpy()
        order = np.argsort(src, kind="stable")
        former = np.full(len(src), -1)
        repeat = src[order][1:] == src[order][:-1]
        former[order[1:][repeat]] = order[:-1][repeat]
        flushes = at = 0
        while at < len(src):
            fresh = np.cumsum(former[at:] < at)  # sources that the map has not held since it was last empty
            at += int(np.searchsorted(fresh, threshold)) + 1
            flushes += 1
        return pa.table({"chunk": rows.column("chunk")[:1], "flushes": pa.array([flushes], pa.int64())})

    chunked = edges.select("eid", "src", int_div(F.col("eid"), layout.chunk_edges).alias("chunk"))
    return chunked.groupBy("chunk").applyInArrow(count, "chunk long, flushes long")


def adjacency_flushed(edges: DataFrame, layout: Layout, threshold: int) -> DataFrame:
    """(chunk, flushes): the same for the map of neighbour lists, which empties whenever it holds `threshold` neighbours."""
    chunked = edges.groupBy(int_div(F.col("eid"), layout.chunk_edges).alias("chunk")).agg(F.count(F.lit(1)).alias("n"))
    return chunked.select("chunk", F.ceil(F.col("n") / threshold).cast("long").alias("flushes"))


def edges_from_csr(csr: Csr) -> DataFrame:
    """(src, dst) back: each position belongs to the last vertex whose slice begins at or before it.

    Slices and positions meet in blocks of positions; a slice is listed in each block it reaches into, so a hub's slice is spread.
    """
    block = csr.layout.block_edges
    reach = reach_of(csr)
    at = csr.neighbors.withColumn("block", int_div(F.col("pos"), block))
    return at.join(reach, "block").where("pos >= lo AND pos < hi").select(F.col("id").alias("src"), "dst")


def _slices(offsets: DataFrame) -> DataFrame:
    """(id, lo, hi): a vertex's slice ends where the next one's begins."""
    after = offsets.select((F.col("id") - 1).alias("id"), F.col("off").alias("hi"))
    return offsets.join(after, "id").select("id", F.col("off").alias("lo"), "hi")


def reach_of(csr: Csr, ids: DataFrame | None = None) -> DataFrame:
    """(id, lo, hi, block): each slice, or those of some vertices, once for every block of positions it reaches into."""
    block = csr.layout.block_edges
    wanted = _slices(csr.offsets) if ids is None else _slices(csr.offsets).join(ids, "id")
    return wanted.where("hi > lo").withColumn("block", F.explode(F.sequence(int_div(F.col("lo"), block), int_div(F.col("hi") - 1, block))))


def neighbors_of(csr: Csr, ids: DataFrame) -> DataFrame:
    """(id, pos, dst) of the slices of some vertices (column id)."""
    block = csr.layout.block_edges
    reach = reach_of(csr, ids)
    return csr.neighbors.withColumn("block", int_div(F.col("pos"), block)).join(reach, "block").where("pos >= lo AND pos < hi").select("id", "pos", "dst")


def adjacency_lists(csr: Csr, cap: int) -> DataFrame:
    """(id, part, nbrs): neighbour lists cut at `cap`, so no row holds a hub."""
    flat = _slices(csr.offsets).where("hi > lo")
    rows = neighbors_of(csr, flat.select("id")).join(flat.select("id", "lo"), "id")
    part = rows.withColumn("part", int_div(F.col("pos") - F.col("lo"), cap))
    return part.groupBy("id", "part").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "dst"))), lambda x: x["dst"]).alias("nbrs"))


def prepared(edges: DataFrame, symmetrize: bool = False, drop_self_loops: bool = False, dedup: bool = False) -> DataFrame:
    """Options of the graph model: both directions, no loops, no repeated edges (the least eid of equal ones stays)."""
    if symmetrize:
        edges = edges.select((F.col("eid") * 2).alias("eid"), "src", "dst").unionByName(edges.select((F.col("eid") * 2 + 1).alias("eid"), F.col("dst").alias("src"), F.col("src").alias("dst")))
    if drop_self_loops:
        edges = edges.where("src <> dst")
    if dedup:
        edges = edges.groupBy("src", "dst").agg(F.min("eid").alias("eid")).select("eid", "src", "dst")
    return edges
