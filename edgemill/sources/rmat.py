"""Recursive-matrix edges as a narrow plan over a range."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from edgemill.config import GenSpec
from edgemill.functions.prng import block_hash, draw, draw_bits, draws_per_block


def thresholds(spec: GenSpec, level: int) -> tuple[int, int, int]:
    """Integer bounds of the quadrants at a level; noise tilts the first probability up and down in turn."""
    a, b, c, _ = spec.probs
    if spec.noise:
        tilt = spec.noise * (1 if level % 2 else -1)
        a, b, c = a * (1 - 2 * tilt), b * (1 + tilt), c * (1 + tilt)
        total = a + b + c + spec.probs[3]
        a, b, c = a / total, b / total, c / total
    top = 1 << draw_bits(spec.backend)
    return int(a * top), int((a + b) * top), int((a + b + c) * top)


def ends_of(edges: DataFrame, spec: GenSpec, purpose: str = "edge") -> DataFrame:
    """src and dst of each eid: a level picks a quadrant, its two bits go to the ends."""
    per, levels = draws_per_block(spec.backend), spec.levels
    hashed = edges.select("*", *(block_hash(spec.seed, purpose, F.col("eid"), k, spec.backend).alias(f"_h{k}") for k in range(-(-levels // per))))
    # draws are columns of their own: each is used more than once, and the planner then keeps their projection
    drawn = hashed.select(*edges.columns, *(draw(F.col(f"_h{k // per}"), k % per, spec.backend).alias(f"_u{k}") for k in range(levels)))
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(levels):
        u = F.col(f"_u{level}")
        t1, t2, t3 = thresholds(spec, level)
        weight = F.lit(1 << (levels - 1 - level)).cast("long")
        src = src + F.when(u >= t2, weight).otherwise(0)
        dst = dst + F.when(((u >= t1) & (u < t2)) | (u >= t3), weight).otherwise(0)
    return drawn.select(*edges.columns, src.alias("src"), dst.alias("dst"))


def rmat_edges(spark: SparkSession, spec: GenSpec, partitions: int | None = None, redraws: int = 8) -> DataFrame:
    """(eid, src, dst), m = f * n independent edges. No shuffle; partitions hold contiguous eids.

    Where n is no power of two, an edge outside n x n is drawn anew, `redraws` times at
    most; what is still outside is folded by the remainder.
    """
    edges = spark.range(0, spec.edges, 1, partitions or spark.sparkContext.defaultParallelism).withColumnRenamed("id", "eid")
    out = ends_of(edges, spec, "edge")
    n = spec.vertices
    if n == 1 << spec.levels:
        return out
    outside: Column = (F.col("src") >= n) | (F.col("dst") >= n)
    for attempt in range(1, redraws + 1):
        again = ends_of(out.select("eid", F.col("src").alias("s0"), F.col("dst").alias("d0")), spec, f"edge{attempt}")
        keep = (F.col("s0") < n) & (F.col("d0") < n)
        out = again.select("eid", F.when(keep, F.col("s0")).otherwise(F.col("src")).alias("src"), F.when(keep, F.col("d0")).otherwise(F.col("dst")).alias("dst"))
    return out.select("eid", F.when(outside, F.pmod("src", F.lit(n))).otherwise(F.col("src")).alias("src"), F.when(outside, F.pmod("dst", F.lit(n))).otherwise(F.col("dst")).alias("dst"))


def rmat_edges_arrow(spark: SparkSession, spec: GenSpec, partitions: int | None = None) -> DataFrame:
    """The same distribution from a counter-based NumPy generator in Arrow batches."""
    from edgemill.shipping import ship_package

    ship_package(spark)
    import pyarrow as pa

    bounds, levels, seed = [thresholds(spec, k) for k in range(spec.levels)], spec.levels, spec.seed
    shift = 64 - draw_bits(spec.backend)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        mix = lambda x: (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        for batch in batches:
            eid = batch.column(0).to_numpy()
            src, dst = np.zeros(len(eid), np.int64), np.zeros(len(eid), np.int64)
            for level, (t1, t2, t3) in enumerate(bounds):
                x = mix(mix(eid.astype(np.uint64) + np.uint64((seed * 1_000_003 + level + 1) * 0x9E3779B97F4A7C15 % 2**64)))
                u = ((x ^ (x >> np.uint64(31))) >> np.uint64(shift)).astype(np.int64)
                weight = 1 << (levels - 1 - level)
                src += weight * (u >= t2)
                dst += weight * (((u >= t1) & (u < t2)) | (u >= t3))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(src), pa.array(dst)], ["eid", "src", "dst"])

    return spark.range(0, spec.edges, 1, partitions or spark.sparkContext.defaultParallelism).mapInArrow(run, "eid long, src long, dst long")


def aligned_counts(spec: GenSpec, nb: int) -> list[int]:
    """Edges for each of nb destination prefixes (nb a power of two), drawn from the multinomial law that independent edges follow; decided by the seed."""
    import numpy as np

    a, b, c, d = spec.probs
    left, shares = a + c, [1.0]
    for _ in range((nb - 1).bit_length()):
        shares = [s * p for s in shares for p in (left, 1 - left)]
    return np.random.default_rng(spec.seed).multinomial(spec.edges, shares).tolist()


def aligned_parts(spark: SparkSession, spec: GenSpec, nb: int) -> list[DataFrame]:
    """(bucket, eid, src, dst) of each bucket: edges born in the range of their destination, so the first relabel needs no edge shuffle.

    The destination prefix of each edge is fixed by its bucket; the source bits of those
    levels follow their conditional probability. n and nb are powers of two; the driver holds nb counts. A bucket has
    its share of the default parallelism as partitions.
    """
    if nb & (nb - 1) or spec.vertices != 1 << spec.levels or nb > spec.vertices:
        raise ValueError("aligned generation needs powers of two")
    counts, lead = aligned_counts(spec, nb), (nb - 1).bit_length()
    parts, start, wide = [], 0, spark.sparkContext.defaultParallelism
    a, b, c, d = spec.probs
    top = 1 << draw_bits(spec.backend)
    for bucket, count in enumerate(counts):
        base = spark.range(start, start + count, 1, max(1, round(wide * count / max(1, spec.edges)))).select(F.lit(bucket).alias("bucket"), F.col("id").alias("eid"))
        start += count
        per = draws_per_block(spec.backend)
        free = ends_of(base, spec, "edge")
        hashed = free.select("*", *(block_hash(spec.seed, "lead", F.col("eid"), k, spec.backend).alias(f"_l{k}") for k in range(max(1, -(-lead // per)))))
        low = spec.levels - lead
        src, dst = F.pmod("src", F.lit(1 << low)), F.pmod("dst", F.lit(1 << low)) + (bucket << low)
        for level in range(lead):
            right = (bucket >> (lead - 1 - level)) & 1
            down = d / (b + d) if right else c / (a + c)
            u = draw(F.col(f"_l{level // per}"), level % per, spec.backend)
            src = src + F.when(u < int(down * top), F.lit(1 << (spec.levels - 1 - level)).cast("long")).otherwise(0)
        parts.append(hashed.select("bucket", "eid", src.alias("src"), dst.alias("dst")))
    return parts


def rmat_edges_aligned(spark: SparkSession, spec: GenSpec, nb: int) -> DataFrame:
    """The parts of aligned_parts as one table."""
    return reduce(DataFrame.unionByName, aligned_parts(spark, spec, nb))
