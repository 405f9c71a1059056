"""Random permutations of [0, n): rounds of local shuffles and exchanges, one external sort, controls and quality."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgemill.functions.partition import int_div, owner_of, range_lo
from edgemill.functions.prng import key_bucket, mixed_columns, sort_key
from edgemill.operators.positions import starts_of
from edgemill.scratch import materialise


def identity(spark: SparkSession, n: int) -> DataFrame:
    """The biased control: every vertex keeps its id."""
    return spark.range(n).select("id", F.col("id").alias("label"))


def invert(perm: DataFrame) -> DataFrame:
    return perm.select(F.col("label").alias("id"), F.col("id").alias("label"))


def default_rounds(n: int, nb: int) -> int:
    """ceil(log_nb n), at least one; one bucket needs one."""
    return 1 if nb < 2 or n < 2 else max(1, math.ceil(math.log(n) / math.log(nb) - 1e-12))


def _dealt(state: DataFrame, n: int, nb: int, seed: int, turn: int, backend: str) -> DataFrame:
    """One round: shuffle each bucket, then deal its labels to all buckets in turn."""
    bucket = owner_of(F.col("slot"), n, nb)
    keyed = state.select("label", bucket.alias("bucket"), sort_key(seed, f"round{turn}", F.col("label"), backend).alias("key"))
    # one exchange a round: the window finds rows partitioned by bucket and sorted
    local = keyed.repartitionById(nb, F.col("bucket").cast("int")).sortWithinPartitions("bucket", "key", "label")
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy("key", "label")) - 1
    place = range_lo(F.col("bucket"), n, nb) + rank
    to, quotient, rest = F.pmod(F.col("place"), F.lit(nb)), n // nb, n % nb
    slot = to * quotient + F.least(to, F.lit(rest)) + int_div(F.col("place"), nb)
    return local.select("label", "bucket", place.alias("place")).select("label", F.col("bucket").alias("came_from"), slot.alias("slot"))


def by_rounds(spark: SparkSession, n: int, nb: int, rounds: int | None = None, seed: int = 0, backend: str = "fast", store_every: int = 4) -> DataFrame:
    """(id, label): `rounds` local shuffles with equal exchanges between nb buckets.

    A bucket must hold a piece for each other bucket (nb * nb <= n). The state is
    stored every few rounds, so the plan stays short when nb is small.
    """
    if nb > 1 and nb * nb > n:
        raise ValueError(f"{nb} buckets of {n} vertices have no vertex for every other bucket; use fewer or permute by sort")
    state = spark.range(n).select(F.col("id").alias("slot"), F.col("id").alias("label"))
    rounds = default_rounds(n, nb) if rounds is None else rounds
    for turn in range(1, rounds + 1):
        state = _dealt(state, n, nb, seed, turn, backend).select("slot", "label")
        if turn % store_every == 0 and turn < rounds:
            state = materialise(state, "permutation-round")
    return state.select(F.col("slot").alias("id"), "label")


def rounds_trace(spark: SparkSession, n: int, nb: int, rounds: int, seed: int = 0, backend: str = "fast") -> DataFrame:
    """(round, from_bucket, to_bucket, moved) of every exchange."""
    state = spark.range(n).select(F.col("id").alias("slot"), F.col("id").alias("label"))
    out = None
    for turn in range(1, rounds + 1):
        state = _dealt(state, n, nb, seed, turn, backend)
        moved = state.groupBy(F.lit(turn).alias("round"), F.col("came_from").alias("from_bucket"), owner_of(F.col("slot"), n, nb).alias("to_bucket")).agg(F.count(F.lit(1)).alias("moved"))
        out = moved if out is None else out.unionByName(moved)
        state = state.select("slot", "label")
    return out


def by_sort(spark: SparkSession, n: int, seed: int = 0, backend: str = "fast", bits: int = 8) -> DataFrame:
    """A fair permutation in one round and one shuffle: the label of a vertex is its rank by a random key.

    Keys are uniform, so their high bits cut them into even ordered buckets without sampling;
    buckets are counted (2^bits rows, broadcast) and ranked on their own. The sort spills to disk, so memory does not bound n.
    """
    keyed = spark.range(n).select("id", sort_key(seed, "perm", F.col("id"), backend).alias("key"))
    keyed = keyed.withColumn("bucket", key_bucket(F.col("key"), bits, backend))
    starts = starts_of(keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")), "bucket").select("bucket", "start")
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy("key", "id")) - 1
    return keyed.join(F.broadcast(starts), "bucket").select("id", (F.col("start") + rank).alias("label"))


def sequential(spark: SparkSession, n: int, seed: int = 0, backend: str = "fast") -> DataFrame:
    """The specification: one sorted partition, for small n."""
    if n > 1 << 22:
        raise ValueError("the sequential permutation is for n up to 2^22")
    keyed = spark.range(n).select("id", sort_key(seed, "perm", F.col("id"), backend).alias("key"))
    return keyed.select("id", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("key", "id")) - 1).cast("long").alias("label"))


def by_hash(spark: SparkSession, n: int, key: int = 7, rounds: int = 4) -> DataFrame:
    """The collision-free hash in place of a permutation: projections, a bijection on [0, n) for any n."""
    return mixed_columns(spark.range(n).select("id", F.col("id").alias("label")), ["label"], n, key, rounds)


def check_bijection(perm: DataFrame, n: int) -> None:
    """Raises unless perm has n rows with all labels of [0, n)."""
    r = perm.agg(F.count(F.lit(1)).alias("rows"), F.countDistinct("label").alias("labels"), F.min("label").alias("least"), F.max("label").alias("most")).first()
    if (r.rows, r.labels) != (n, n) or n and (r.least, r.most) != (0, n - 1):
        raise ValueError(f"not a permutation of [0, {n}): {r.asDict()}")


def store_ranges(perm: DataFrame, n: int, nb: int) -> DataFrame:
    """The permutation stored by range bucket, so one range is one partition folder."""
    return materialise(perm.withColumn("bucket", owner_of(F.col("id"), n, nb).cast("int")), "permutation", ["bucket"])


def range_of(stored: DataFrame, bucket: int) -> DataFrame:
    """One ordered range, as the range server would hand it out; reads its folder alone."""
    return stored.where(F.col("bucket") == bucket).select("id", "label")


def quality(perm: DataFrame, n: int, nb: int) -> DataFrame:
    """One row of integers: bijection, fixed points, scaled chi-square of origin by destination bucket, displacement, product sum."""
    flat = perm.agg(
        F.count(F.lit(1)).alias("vertices"), F.countDistinct("label").alias("labels"), F.min("label").alias("least"), F.max("label").alias("most"),
        F.sum((F.col("id") == F.col("label")).cast("long")).alias("fixed"), F.sum(F.abs(F.col("id") - F.col("label"))).alias("displacement"), F.sum(F.col("id") * F.col("label")).alias("products"),
    )
    spark = perm.sparkSession
    cells = spark.range(nb).select(F.col("id").alias("i")).crossJoin(spark.range(nb).select(F.col("id").alias("j")))  # nb * nb rows
    counts = perm.groupBy(owner_of(F.col("id"), n, nb).alias("i"), owner_of(F.col("label"), n, nb).alias("j")).agg(F.count(F.lit(1)).alias("c"))
    off = F.coalesce("c", F.lit(0)) * (nb * nb) - n
    chi = cells.join(counts, ["i", "j"], "left").agg(F.sum(off * off).alias("chi_scaled"))
    return flat.crossJoin(chi)
