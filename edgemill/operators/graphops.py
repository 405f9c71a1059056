"""Kernels that consume generated graphs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.scratch import materialise
from edgemill.shipping import ship_package

BLOCK_SOURCES, BLOCK_TARGETS = 4096, 1 << 22  # sources and their targets in a block of common_neighbors


def bfs_levels(edges: DataFrame, source: int, max_depth: int = 1000) -> DataFrame:
    """(id, level) of the vertices within reach; a round joins the frontier with the edges, and stops when it is empty. A frontier left after max_depth raises."""
    spark = edges.sparkSession
    links = materialise(edges.select("src", "dst").distinct(), "links")
    seen = spark.range(source, source + 1).select("id", F.lit(0).alias("level"))
    frontier = seen
    for level in range(1, max_depth + 1):
        reached = frontier.join(links, F.col("id") == F.col("src")).select(F.col("dst").alias("id")).distinct()
        frontier = materialise(reached.join(seen.select("id"), "id", "left_anti").select("id", F.lit(level).alias("level")), "frontier")
        if frontier.isEmpty():
            break
        seen = materialise(seen.unionByName(frontier), "seen")
    else:
        raise RuntimeError(f"vertices beyond level {max_depth} are left; give a larger max_depth")
    return seen


def two_hop(edges: DataFrame) -> DataFrame:
    """(src, dst, paths): numbers of two-edge paths."""
    weighted = edges.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))
    second = weighted.select(F.col("src").alias("mid"), F.col("dst").alias("end"), F.col("w").alias("w2"))
    return weighted.join(second, F.col("dst") == F.col("mid")).groupBy("src", F.col("end").alias("dst")).agg(F.sum(F.col("w") * F.col("w2")).alias("paths"))


def _simple(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()


def oriented(edges: DataFrame) -> DataFrame:
    """(u, v): each simple edge from the end of lower degree (ties: lower id), which bounds a hub's out-degree by sqrt(2 m)."""
    pairs = _simple(edges)
    deg = pairs.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("d"))
    both = pairs.join(deg.select(F.col("id").alias("a"), F.col("d").alias("da")), "a").join(deg.select(F.col("id").alias("b"), F.col("d").alias("db")), "b")
    first = (F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") < F.col("b")))
    return both.select(F.when(first, F.col("a")).otherwise(F.col("b")).alias("u"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("v"))


def triangles(edges: DataFrame) -> DataFrame:
    """One row: triangles of the simple undirected graph."""
    e = materialise(oriented(edges), "oriented")
    wedges = e.select("u", F.col("v").alias("v1")).join(e.select("u", F.col("v").alias("v2")), "u").where("v1 < v2")
    closing = _simple(edges)
    return wedges.join(closing, (F.col("v1") == F.col("a")) & (F.col("v2") == F.col("b"))).agg(F.count(F.lit(1)).alias("triangles"))


def _shared(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """Numbers of common targets of all lists of a with all of b. Targets that many lists hold are multiplied as columns, others are added where they meet."""
    out = np.zeros(len(a) * len(b), np.int64)
    owner = np.repeat(np.arange(len(a) + len(b)), [len(x) for x in (*a, *b)])
    if not len(owner):
        return out.reshape(len(a), len(b))
    held = np.concatenate([*a, *b])
    order = np.argsort(held, kind="stable")
    held, owner = held[order], owner[order]
    starts = np.flatnonzero(np.concatenate([[True], held[1:] != held[:-1]]))
    sizes = np.diff(np.append(starts, len(held)))
    in_a = np.add.reduceat((owner < len(a)).astype(np.int64), starts)
    work = in_a * (sizes - in_a)
    many = work > max(64, len(a) * len(b) // 128)
    for part in np.array_split(dense := np.flatnonzero(many), max(1, -(-len(dense) // 512))):
        matrix = np.zeros((len(a) + len(b), len(part)), np.float32)
        for column, k in enumerate(part.tolist()):
            matrix[owner[starts[k] : starts[k] + sizes[k]], column] = 1
        out += (matrix[: len(a)] @ matrix[len(a) :].T).astype(np.int64).reshape(-1)
    sparse = np.flatnonzero((work > 0) & ~many)
    # owners are sorted inside a target, those of a first; so many pairs at a time
    for part in np.split(sparse, np.flatnonzero(np.diff(np.cumsum(work[sparse]) >> 21)) + 1):
        n_a, n_b, first, pairs = in_a[part], (sizes - in_a)[part], starts[part], work[part]
        which = np.repeat(np.arange(len(part)), pairs)
        nth = np.arange(len(which)) - np.repeat(np.cumsum(pairs) - pairs, pairs)
        left, right = owner[first[which] + nth // n_b[which]], owner[first[which] + n_a[which] + nth % n_b[which]] - len(a)
        np.add.at(out, left * len(b) + right, 1)
    return out.reshape(len(a), len(b))


def _compare_blocks(least: int, strip: int = 512):
    """Rows (first block, second block, own block, node, targets) sorted by pair of blocks to (x, y, common) of the pairs that share at least `least` targets."""

    def compare(rows: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, node = (np.concatenate([r.column(k).to_numpy() for r in rows]) for k in (2, 3))
        lists = [x.values.to_numpy() for r in rows for x in r.column(4)]
        a = np.flatnonzero(own == own.min())
        b = a if own.min() == own.max() else np.flatnonzero(own != own.min())
        if own.min() == own.max() and rows[0].column(0)[0].as_py() != rows[0].column(1)[0].as_py():
            return  # the other block is empty; pairs inside this one have their own group
        for at in range(0, len(a), strip):
            some = a[at : at + strip]
            common = _shared([lists[k] for k in some.tolist()], [lists[k] for k in b.tolist()])
            if b is a:
                common[np.arange(at, at + len(some))[:, None] >= np.arange(len(b))] = 0
            i, j = np.nonzero(common >= least)
            if len(i):
                yield pa.RecordBatch.from_pydict({"x": node[some[i]], "y": node[b[j]], "common": common[i, j]})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            first, second = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            cuts = [0, *(np.flatnonzero((first[1:] != first[:-1]) | (second[1:] != second[:-1])) + 1).tolist(), len(first)]
            for lo, hi in zip(cuts, cuts[1:]):
                if held and last != (first[lo], second[lo]):
                    yield from compare(held)
                    held = []
                held.append(batch.slice(lo, hi - lo))
                last = first[lo], second[lo]
        if held:
            yield from compare(held)

    return run


def common_neighbors(edges: DataFrame, least: int = 1, block: int = BLOCK_SOURCES, joined: bool | None = None) -> DataFrame:
    """(a, b, common) for sources that share at least `least` different targets (1 at least).

    Sources with equal targets are compared once and their pairs written out last. Where targets are
    rare the lists meet in a join; where a join would make many rows more than there are pairs, blocks of
    sources are compared as arrays and only the pairs found become rows. Both ways are exact; `joined` sets one.
    """
    spark = edges.sparkSession
    ship_package(spark)
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    links = edges.where("src IS NOT NULL AND dst IS NOT NULL").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    lists = materialise(links.groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("targets")).where(F.size("targets") >= least), "target-lists")
    sets = materialise(lists.groupBy("targets").agg(F.min("src").alias("node"), F.count(F.lit(1)).alias("members")).withColumn("held", F.size("targets").cast("long")), "target-sets")
    total = sets.agg(F.count(F.lit(1)).alias("nodes"), F.coalesce(F.sum("held"), F.lit(0)).alias("links"), F.coalesce(F.max("members"), F.lit(0)).alias("members")).first()
    many = max(1, -(-total.nodes // block), -(-total.links // BLOCK_TARGETS))
    each = sets.select("node", F.explode("targets").alias("dst"))
    if joined is None:
        meet = each.groupBy("dst").agg(F.count(F.lit(1)).cast("double").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0] or 0
        joined = meet <= 8 * total.links * many
    if joined:
        other = each.select(F.col("node").alias("y"), "dst")
        pairs = each.withColumnRenamed("node", "x").join(other, "dst").where("x < y").groupBy("x", "y").agg(F.count(F.lit(1)).alias("common")).where(F.col("common") >= least)
    else:
        own = F.pmod(F.xxhash64("node"), F.lit(many)).cast("int")
        cut = sets.select("node", "targets", own.alias("own"), F.explode(F.sequence(F.lit(0), F.lit(many - 1))).alias("other"))
        cut = cut.select(F.least("own", "other").alias("first_block"), F.greatest("own", "other").alias("second_block"), "own", "node", "targets")
        dealt = cut.repartition(max(width, min(many * (many + 1) // 2, 1024)), "first_block", "second_block").sortWithinPartitions("first_block", "second_block")
        pairs = dealt.mapInArrow(_compare_blocks(least), "x long, y long, common long")
    if total.members < 2:
        return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "common")
    pairs = materialise(pairs, "common-pairs")
    same = sets.where("members > 1").select(F.col("node").alias("x"), F.col("node").alias("y"), F.col("held").alias("common"))
    members = materialise(lists.join(sets, "targets").select("node", "src"), "set-members")
    left, right = members.select(F.col("node").alias("x"), F.col("src").alias("s")), members.select(F.col("node").alias("y"), F.col("src").alias("t"))
    spread = pairs.unionByName(same).repartition(width, "x", "y")  # each row becomes as many as its two classes have pairs
    return spread.join(left, "x").join(right, "y").where("x <> y OR s < t").select(F.least("s", "t").alias("a"), F.greatest("s", "t").alias("b"), "common")


def reciprocity(edges: DataFrame) -> DataFrame:
    """One row: different directed edges without loops, and those whose reverse is there too."""
    links = edges.where("src <> dst").select("src", "dst").distinct()
    back = links.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("back"))
    return links.join(back, ["src", "dst"], "left").agg(F.count(F.lit(1)).alias("links"), F.count("back").alias("returned"))
