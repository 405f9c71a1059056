"""Shards of near-equal bytes by longest-processing-time scheduling.

Documents with equal texts form a group that stays together. Groups are taken
by falling size and each goes to the least-loaded shard. Groups of one size are
interchangeable, so the schedule needs only how many groups each size has. The
driver streams this histogram by falling size, `most` sizes at a time, through a heap (a long
run of one size in closed form, with the same loads) and appends the plan to a
table, so it holds `most` sizes whatever the corpus. The groups of a size then
take the shards by their rank, which no single task has to compute.

Law of the result: bytes. Null text counts as the empty text (size 1, crc32 0)
and is in its group. Repeated rows are separate documents, and rows with null doc_id are
documents like any other (first in their shard). An empty table gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import heapq
from itertools import accumulate, islice

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.functions.ranking import rank_within
from edgemill.llm.common import fresh_path, id_and_text, materialise


def schedule(sizes: list[tuple[int, int]], shards: int, before: list[int] | None = None) -> tuple[list[tuple[int, list[int]]], list[int]]:
    """(size, number of groups) to (size, groups for each shard), and the loads, which start at those `before`.

    Exactly the loads of one-by-one scheduling: within a run of equal sizes the
    shards take turns, so c groups go to the c lowest of the values load + j * size.
    """
    heap = [(load, k) for k, load in enumerate(before or [0] * shards)]
    heapq.heapify(heap)
    plan = []
    for size, count in sorted(sizes, reverse=True):
        taken, left = [0] * shards, count
        if count > 4 * shards:
            lo, hi = heap[0][0], heap[0][0] + size * (count + 1)
            while lo < hi:  # the highest level below which at most `count` values lie
                mid = (lo + hi + 1) // 2
                if sum(-(-(mid - load) // size) for load, _ in heap if load < mid) <= count:
                    lo = mid
                else:
                    hi = mid - 1
            level = []
            for load, k in heap:
                n = -(-(lo - load) // size) if load < lo else 0
                taken[k] += n
                left -= n
                level.append((load + n * size, k))
            heap = level
            heapq.heapify(heap)
        for _ in range(left):
            load, k = heap[0]
            heapq.heapreplace(heap, (load + size, k))
            taken[k] += 1
        plan.append((size, taken))
    loads = [load for load, _ in sorted(heap, key=lambda x: x[1])]
    return plan, loads


def _planned(groups: DataFrame, shards: int, most: int) -> DataFrame:
    """(group_size, ends): a group of the size with rank r goes to the first shard whose end is above r."""
    spark = groups.sparkSession
    histogram = materialise(groups.groupBy("group_size").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("group_size")), "size-histogram")
    path, loads = fresh_path(spark, "shard-plan"), [0] * shards
    schema = "group_size long, ends array<long>"
    spark.createDataFrame([], schema).write.mode("append").parquet(path)
    rows = histogram.orderBy(F.desc("group_size")).toLocalIterator()
    while chunk := [(r.group_size, r.n) for r in islice(rows, most)]:
        plan, loads = schedule(chunk, shards, loads)
        spark.createDataFrame([(size, list(accumulate(taken))) for size, taken in plan], schema).write.mode("append").parquet(path)
    return spark.read.schema(schema).parquet(path)


def shard_documents(docs: DataFrame, shards: int = 16, most: int = 100_000) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every document.

    Shuffles: document digests (no texts) by group and by shard. The histogram of group
    sizes passes through the driver, `most` sizes at a time; the plan meets the groups in a join.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    digests = materialise(
        id_and_text(docs).select(
            "doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.unhex(F.md5(text.cast("binary"))).alias("group_key")
        ),
        "digests",
    )
    groups = materialise(digests.groupBy("group_key").agg((F.count(F.lit(1)) * F.first("size")).alias("group_size")), "groups")
    plan = _planned(groups, shards, most)
    ranked = rank_within(groups, ["group_size"], ["group_key"])
    shard = F.size(F.filter("ends", lambda end: end <= F.col("rank"))).cast("int")
    placed = ranked.join(plan, "group_size").select("group_key", shard.alias("shard"))
    assigned = materialise(digests.join(placed, "group_key").drop("group_key"), "assigned")
    return rank_within(assigned, ["shard"], ["doc_id", "text_crc32"], "slot").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
