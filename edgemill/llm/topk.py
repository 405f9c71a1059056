"""Exact top-k inner products by a three-phase uniform threshold.

The score of a query and a row is a sum over slices of the dimensions; each slice
is a list of partial scores that every task holds for its own rows. Phase one: each
task takes, per list, its best k rows and their whole scores; the k-th best of
all these, over all tasks, is a cutoff t that k rows are known to reach. Phase
two: with m lists, a row that reaches t has a partial score of at least t / m in
some list, so tasks collect just the rows that do. Phase three: their
whole scores are resolved exactly, those below t go, and the best k stay.

Queries are the rows with id divisible by `every`; they pass in blocks of
`block` vectors (a bounded broadcast), each against all rows, so no pair of vectors is
shuffled. Vectors that are null, empty or hold a null or non-finite component take
no part, as query or as row, nor do rows with null id. Vectors of another length than the query's
are not comparable and take no part in its result. Ties go to the smaller
id; rows with one id more than once are each a candidate, but a query never meets
its own id; a query id that repeats is answered once, for its first vector in
component order. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgemill.llm.common import fresh_path, materialise, ship_package

OUT_SCHEMA = "query_id long, rank int, vec_id long, score long"
EXACT = float(1 << 52)
NO_CUTOFF = -(1 << 62)  # for queries that meet fewer than k rows; below any score


def usable(vectors: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """id and quantised components of the vectors that take part; a row with null id has no name to be listed by and takes none."""
    ok = F.col(id_col).isNotNull() & F.col(vec_col).isNotNull() & (F.size(vec_col) > 0) & F.forall(vec_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    cells = F.transform(vec_col, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))
    return vectors.where(ok).select(F.col(id_col).cast("long").alias("vec_id"), cells.alias("cells"))


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a times b transposed in exact integers: floating point where that is exact, else 64-bit integers, else Python's."""
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[1])
    if most < EXACT:
        return (a.astype(np.float64) @ b.astype(np.float64).T).astype(np.int64)
    if most < float(1 << 62):
        return a @ b.T
    exact = a.astype(object) @ b.astype(object).T
    if max(map(abs, exact.ravel()), default=0) >= 1 << 62:
        raise ValueError("an inner product does not fit 63 bits")
    return exact.astype(np.int64)


def _matrices(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, vectors) of a batch for each vector length."""
    cells = batch.column(1)
    ids = batch.column(0).to_numpy()
    offsets = cells.offsets.to_numpy()
    flat = cells.values.to_numpy()
    lengths = np.diff(offsets)
    for n in np.unique(lengths):
        rows = np.flatnonzero(lengths == n)
        yield ids[rows], flat[offsets[rows][:, None] + np.arange(n)]


def _slices(dims: int, lists: int) -> list[slice]:
    cuts = np.linspace(0, dims, min(lists, dims) + 1).astype(int)
    return [slice(a, b) for a, b in zip(cuts, cuts[1:])]


def _best(scores: np.ndarray, k: int) -> np.ndarray:
    """Row by row, places of the k highest (all, if fewer), in any order."""
    if scores.shape[1] <= k:
        return np.tile(np.arange(scores.shape[1]), (len(scores), 1))
    return np.argpartition(scores, scores.shape[1] - k, axis=1)[:, -k:]


def _block_top(spark, rows: DataFrame, query_ids: list[int], query_cells: list[list[int]], k: int, lists: int, chunk: int) -> DataFrame:
    groups: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for n in sorted({len(c) for c in query_cells}):
        picked = [i for i, c in enumerate(query_cells) if len(c) == n]
        groups[n] = np.array([query_ids[i] for i in picked], np.int64), np.array([query_cells[i] for i in picked], np.int64).reshape(len(picked), n)
    queries = spark.sparkContext.broadcast(groups)

    def chunks(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for ids, cells in _matrices(batch):
                if cells.shape[1] in queries.value:
                    q_ids, q = queries.value[cells.shape[1]]
                    for at in range(0, len(ids), chunk):
                        yield q_ids, q, ids[at : at + chunk], cells[at : at + chunk]

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Phase one: a task's best known whole scores of each query, k at most."""
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for q_ids, q, ids, cells in chunks(batches):
            own = ids[None, :] == q_ids[:, None]
            whole = np.zeros((len(q_ids), len(ids)), np.int64)
            seen = np.zeros_like(own)
            for s in _slices(q.shape[1], lists):
                part = _product(q[:, s], cells[:, s])
                whole += part
                part[own] = np.iinfo(np.int64).min
                np.put_along_axis(seen, _best(part, k), True, axis=1)
            whole[~seen | own] = np.iinfo(np.int64).min
            top = np.take_along_axis(whole, _best(whole, k), axis=1)
            n = q.shape[1]
            if n in held:
                joined = np.concatenate([held[n][1], top], axis=1)
                top = np.take_along_axis(joined, _best(joined, k), axis=1)
            held[n] = (q_ids, top)
        for q_ids, top in held.values():
            row, col = np.nonzero(top > np.iinfo(np.int64).min)
            yield pa.RecordBatch.from_pydict({"query_id": q_ids[row], "score": top[row, col]})

    known = rows.mapInArrow(gather, "query_id long, score long")
    # a task gives each query of the block k scores at most: tasks * block * k numbers to the driver's side of a small aggregate
    ranked = known.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"))))
    cutoff = {r.query_id: r.score for r in ranked.where(F.col("r") == k).select("query_id", "score").collect()}
    cutoffs = spark.sparkContext.broadcast({n: np.array([cutoff.get(i, NO_CUTOFF) for i in q_ids.tolist()]) for n, (q_ids, _) in groups.items()})

    def collect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Phases two and three: rows at or above t / m in some list, resolved."""
        for q_ids, q, ids, cells in chunks(batches):
            least = cutoffs.value[q.shape[1]]
            parts = [_product(q[:, s], cells[:, s]) for s in _slices(q.shape[1], lists)]
            uniform = -(-least // len(parts))[:, None]  # rounded up: some integer partial score reaches the mean
            keep = np.zeros(parts[0].shape, bool)
            for part in parts:
                keep |= part >= uniform
            keep &= ids[None, :] != q_ids[:, None]
            row, col = np.nonzero(keep)
            score = sum(part[row, col] for part in parts)
            fine = score >= least[row]
            row, col, score = row[fine], col[fine], score[fine]
            # of equal queries' survivors a task needs no more than k, by score and then id
            order = np.lexsort((ids[col], -score, row))
            row, col, score = row[order], col[order], score[order]
            first = np.searchsorted(row, row, "left")
            short = np.arange(len(row)) - first < k
            yield pa.RecordBatch.from_pydict({"query_id": q_ids[row[short]], "vec_id": ids[col[short]], "score": score[short]})

    survivors = rows.mapInArrow(collect, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return survivors.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_k(vectors: DataFrame, k: int = 10, every: int = 100, scale: int = 1024, lists: int = 4, block: int = 4096, chunk: int = 2048, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of each query."""
    spark = vectors.sparkSession
    ship_package(spark)
    rows = materialise(usable(vectors, id_col, vec_col, scale), "vectors")
    queries = rows.where(F.pmod("vec_id", F.lit(every)) == 0).groupBy("vec_id").agg(F.min("cells").alias("cells"))
    numbered = materialise(queries, "queries")
    found, ids, cells = fresh_path(spark, "top-k"), [], []

    def store() -> None:
        _block_top(spark, rows, ids, cells, k, lists, chunk).write.mode("append").parquet(found)
        ids.clear()
        cells.clear()

    # one block of query vectors at a time passes through the driver; its ranks are appended to one table, whose plan no number of blocks makes longer
    for r in numbered.toLocalIterator():
        ids.append(r.vec_id)
        cells.append(r.cells)
        if len(ids) == block:
            store()
    if ids:
        store()
    spark.createDataFrame([], OUT_SCHEMA).write.mode("append").parquet(found)  # the table is there without queries as well
    return spark.read.schema(OUT_SCHEMA).parquet(found)
