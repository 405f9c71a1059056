"""Table functions for SQL: generated edges, and ranges of a stored permutation."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="eid: bigint, src: bigint, dst: bigint")
class RmatRows:
    """SELECT * FROM rmat(scale, edge_factor, seed); for small graphs, row by row in one task."""

    def eval(self, scale: int, edge_factor: int, seed: int):
        from edgemill.sources.datasource import numpy_ends

        src, dst = numpy_ends(0, edge_factor << scale, scale, seed, (0.57, 0.19, 0.19, 0.05))
        yield from zip(range(len(src)), src.tolist(), dst.tolist())


def register(spark: SparkSession, permutation_view: str | None = None) -> None:
    """rmat(..) and, where a view (id, label, bucket) is given, perm_range(t), which the optimizer turns into a pruned scan."""
    from edgemill.shipping import ship_package

    ship_package(spark)
    spark.udtf.register("rmat", RmatRows)
    if permutation_view:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION perm_range(t INT) RETURNS TABLE(id BIGINT, label BIGINT) RETURN SELECT id, label FROM {permutation_view} WHERE bucket = t")


def register_csr(spark: SparkSession, csr) -> None:
    """csr_neighbors(v): (pos, dst) of a vertex's slice, for LATERAL use; the optimizer makes it a join of slices and positions by block."""
    from edgemill.operators.csr import reach_of

    reach_of(csr).createOrReplaceTempView("csr_reach")
    csr.neighbors.createOrReplaceTempView("csr_neighbor_vector")
    block = csr.layout.block_edges
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION csr_neighbors(v BIGINT) RETURNS TABLE(pos BIGINT, dst BIGINT) RETURN "
        f"SELECT n.pos, n.dst FROM csr_reach r JOIN csr_neighbor_vector n ON n.pos div {block} = r.block AND n.pos >= r.lo AND n.pos < r.hi WHERE r.id = v"
    )
