"""Relabelling both ends of every edge through a permutation: the merge, its lock-step form, and the ways it is measured against.

All take edges (eid, src, dst) and perm (id, label) and return (eid, src, dst) with new ids.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.functions.partition import chunk_of, int_div, owner_of, range_lo
from edgemill.functions.prng import mixed_columns
from edgemill.operators.permute import range_of, store_ranges
from edgemill.scratch import fresh_path, materialise

#: Largest permutation, in bytes at 16 bytes a vertex, that may be broadcast; checked before every broadcast of one.
BROADCAST_BYTES = 64 << 20


def relabel_endpoint(edges: DataFrame, perm: DataFrame, endpoint: str = "dst", hint: str | None = "merge") -> DataFrame:
    """Replace one end by its label; every end must be in perm (checked by `check_complete`)."""
    side = perm.select(F.col("id").alias(endpoint), F.col("label").alias("_label"))
    if hint:
        side = side.hint(hint)
    joined = edges.join(side, endpoint)
    return joined.select("eid", *(F.col("_label").alias(c) if c == endpoint else F.col(c) for c in ("src", "dst")))


def relabel_merge(edges: DataFrame, perm: DataFrame, order: tuple[str, str] = ("dst", "src")) -> DataFrame:
    """Sort-merge joins of edges with the permutation, first one end, then the other: two shuffles of the edges.

    The joins hash-partition their keys, since raw recursive-matrix ids crowd at the
    low end of any range partitioning; adaptive execution splits what is still skewed.
    """
    for endpoint in order:
        edges = relabel_endpoint(edges, perm, endpoint, "merge")
    return edges


def check_size(n: int) -> None:
    if 16 * n > BROADCAST_BYTES:
        raise ValueError(f"a permutation of {n} vertices is too large to broadcast; relabel by merge")


def relabel_broadcast(edges: DataFrame, perm: DataFrame, n: int) -> DataFrame:
    """Hash joins with a broadcast permutation; only where its size is within the limit."""
    check_size(n)
    for endpoint in ("dst", "src"):
        edges = relabel_endpoint(edges, perm, endpoint, "broadcast")
    return edges


def relabel_hash_join(edges: DataFrame, perm: DataFrame) -> DataFrame:
    """Shuffled hash joins: no sort, a hash table of each partition's labels."""
    for endpoint in ("dst", "src"):
        edges = relabel_endpoint(edges, perm, endpoint, "shuffle_hash")
    return edges


def relabel_hashed(edges: DataFrame, n: int, key: int = 7, rounds: int = 4) -> DataFrame:
    """The in-memory baseline: both ends through a collision-free hash, projections only."""
    return mixed_columns(edges.select("eid", "src", "dst"), ["src", "dst"], n, key, rounds)


def relabel_unpivot(edges: DataFrame, perm: DataFrame) -> DataFrame:
    """Both ends as rows, one join, and back by eid: wider shuffles than the merge."""
    ends = edges.select("eid", F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("src").alias("id")), F.struct(F.lit(1).alias("side"), F.col("dst").alias("id")))).alias("e"))
    labelled = ends.select("eid", "e.side", "e.id").join(perm, "id")
    pick = lambda s: F.max(F.when(F.col("side") == s, F.col("label")))
    return labelled.groupBy("eid").agg(pick(0).alias("src"), pick(1).alias("dst"))


def heavy_ends(edges: DataFrame, endpoint: str, top: int) -> DataFrame:
    """The `top` most frequent ids of an end (ties to smaller ids)."""
    return edges.groupBy(F.col(endpoint).alias("id")).agg(F.count(F.lit(1)).alias("deg")).orderBy(F.desc("deg"), "id").limit(top).select("id")


def relabel_hub_split(edges: DataFrame, perm: DataFrame, top: int = 64) -> DataFrame:
    """Hubs' edges take a broadcast of `top` labels and stay where they are; the others are merged."""
    for endpoint in ("dst", "src"):
        hubs = materialise(heavy_ends(edges, endpoint, top).join(perm, "id"), "hubs")  # top rows
        marked = edges.join(F.broadcast(hubs.select(F.col("id").alias(endpoint), F.col("label").alias("_hub"))), endpoint, "left")
        heavy = marked.where(F.col("_hub").isNotNull()).select("eid", *(F.col("_hub").alias(c) if c == endpoint else F.col(c) for c in ("src", "dst")))
        light = marked.where(F.col("_hub").isNull()).select("eid", "src", "dst")
        edges = heavy.unionByName(relabel_endpoint(light, perm, endpoint, "merge"))
    return edges


def chunk_edges(edges: DataFrame, chunk: int) -> DataFrame:
    """Add the chunk of each edge by its position."""
    return edges.withColumn("chunk", chunk_of(F.col("eid"), chunk))


def group_chunks(chunked: DataFrame, groups: int, chunks: int) -> DataFrame:
    """Add the contiguous group, one for each core, of each chunk."""
    return chunked.withColumn("chunk_group", int_div(F.col("chunk"), -(-chunks // groups)))


def sort_chunks(chunked: DataFrame, endpoint: str, partitions: int) -> DataFrame:
    """Every chunk sorted by one end; a chunk lies in one partition, sorted runs spill to disk."""
    return chunked.repartition(partitions, "chunk").sortWithinPartitions("chunk", endpoint, "eid")


def relabel_range_rounds(edges: DataFrame, perm: DataFrame, layout: Layout, together: int = 16) -> DataFrame:
    """The lock-step form: sorted chunks stay put, the permutation's ranges come by one after another.

    The permutation is stored by range once, and a round reads the folder of its range (permute.range_of). It filters
    the stored, sorted edges to that range (row groups outside it are skipped) and joins the broadcast range,
    checked for size. No edge is shuffled by the joins; each executor sees the whole permutation once. `together` rounds
    are one plan; where there are more, each such plan appends to a table.
    """
    check_size(-(-layout.n // layout.nb))
    spark = edges.sparkSession
    partitions = int(spark.conf.get("spark.sql.shuffle.partitions"))
    served = store_ranges(perm, layout.n, layout.nb)
    for endpoint in ("dst", "src"):
        stored = materialise(sort_chunks(chunk_edges(edges, layout.chunk_edges), endpoint, partitions), "sorted-chunks")
        done, path = None, fresh_path(spark, "range-rounds")
        for t in range(layout.nb):
            lo, hi = range_lo(t, layout.n, layout.nb), range_lo(t + 1, layout.n, layout.nb)
            mine = stored.where((F.col(endpoint) >= lo) & (F.col(endpoint) < hi))
            turn = relabel_endpoint(mine, range_of(served, t), endpoint, "broadcast")
            done = turn if done is None else done.unionByName(turn)
            if layout.nb > together and (t % together == together - 1 or t == layout.nb - 1):
                done.write.mode("append").parquet(path)
                done = None
        edges = spark.read.schema(edges.select("eid", "src", "dst").schema).parquet(path) if done is None else done
    return edges


def relabel_aligned(parts: list[DataFrame], perm: DataFrame, layout: Layout) -> DataFrame:
    """Edges born in the range of their destination (rmat.aligned_parts): each part joins its broadcast range where it is, only the source end is merged.

    One edge shuffle fewer than relabel_merge.
    """
    check_size(-(-layout.n // layout.nb))
    served = store_ranges(perm, layout.n, layout.nb)
    named = [relabel_endpoint(part.select("eid", "src", "dst"), range_of(served, t), "dst", "broadcast") for t, part in enumerate(parts)]
    return relabel_endpoint(reduce(DataFrame.unionByName, named), perm, "src", "merge")


def merge_trace(edges: DataFrame, layout: Layout, endpoint: str = "dst") -> DataFrame:
    """(chunk, turn, consumed): how far each chunk's cursor moves when a range comes by."""
    return chunk_edges(edges, layout.chunk_edges).groupBy("chunk", owner_of(F.col(endpoint), layout.n, layout.nb).alias("turn")).agg(F.count(F.lit(1)).alias("consumed"))


def _filling(endpoint: str):
    """A cogroup function that indexes a range's labels by the ends of its edges."""
    import pyarrow as pa

    def fill(left: pa.Table, right: pa.Table) -> pa.Table:
        import numpy as np

        if not left.num_rows:
            return pa.table({c: pa.array([], pa.int64()) for c in ("eid", "src", "dst")})
        ids, labels = right.column("id").to_numpy(), right.column("label").to_numpy()
        lo = int(ids.min())
        dense = np.full(int(ids.max()) - lo + 1, -1)
        dense[ids - lo] = labels
        return pa.table({c: pa.array(dense[left.column(c).to_numpy() - lo]) if c == endpoint else left.column(c) for c in ("eid", "src", "dst")})

    return fill


def relabel_gather(edges: DataFrame, perm: DataFrame, layout: Layout) -> DataFrame:
    """The merge without sorting: ids are dense, so a range of labels is an array that edges index.

    Both sides are grouped by range; a range's labels and edges meet in one Arrow call, so
    ranges should hold at most some million edges (see Layout.for_edges). Raw ids
    crowd low ranges; skewed inputs take relabel_merge.
    """
    from edgemill.shipping import ship_package

    ship_package(edges.sparkSession)
    for endpoint in ("dst", "src"):
        a = edges.select("eid", "src", "dst", owner_of(F.col(endpoint), layout.n, layout.nb).alias("bucket")).groupBy("bucket")
        b = perm.select("id", "label", owner_of(F.col("id"), layout.n, layout.nb).alias("bucket")).groupBy("bucket")
        edges = a.cogroup(b).applyInArrow(_filling(endpoint), "eid long, src long, dst long")
    return edges


def choose(n: int, m: int, executors: int, any_permutation: bool = False, top_share: float = 0.0, advisory_bytes: int = 256 << 20) -> str:
    """The cheapest relabel for the sizes: broadcast, hashed, range_rounds, hub_split or merge."""
    if 16 * n <= BROADCAST_BYTES:
        return "broadcast"
    if any_permutation:
        return "hashed"
    if executors * n * 16 < 2 * m * 24 and 16 * n // max(1, executors) <= BROADCAST_BYTES:
        return "range_rounds"
    return "hub_split" if top_share * m * 24 > 5 * advisory_bytes else "merge"


def relabel(edges: DataFrame, perm: DataFrame, layout: Layout, m: int, strategy: str = "auto", executors: int = 8, **facts) -> DataFrame:
    """Relabel by name or by `choose`."""
    name = choose(layout.n, m, executors, **facts) if strategy == "auto" else strategy
    if name == "broadcast":
        return relabel_broadcast(edges, perm, layout.n)
    if name == "hashed":
        return relabel_hashed(edges, layout.n)
    if name == "range_rounds":
        return relabel_range_rounds(edges, perm, layout)
    if name == "gather":
        return relabel_gather(edges, perm, layout)
    ways = {"merge": relabel_merge, "hash_join": relabel_hash_join, "unpivot": relabel_unpivot, "hub_split": relabel_hub_split}
    return ways[name](edges, perm)


def check_complete(before: int, after: DataFrame) -> None:
    """Every edge found both labels."""
    if (n := after.count()) != before:
        raise ValueError(f"{before - n} edges have an end that the permutation lacks")
