"""The hand-computed example, edge cases and invariants of the generator."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgemill.config import GenSpec, Layout
from edgemill.functions.partition import bin_of, lane_of, owner_of, range_lo
from edgemill.operators import csr, measures, permute, redistribute, relabel
from edgemill.operators.components import connected_components
from edgemill.plans.generate import generate_graph, generate_sequential
from edgemill.plans.inspect import plan_summary
from edgemill.sources import rmat
from edgemill.sources.tables import require_endpoints

EDGES, PERM = [(0, 0, 1), (1, 0, 2), (2, 1, 2), (3, 3, 0)], [(0, 2), (1, 0), (2, 3), (3, 1)]


@pytest.fixture()
def example(spark):
    return spark.createDataFrame(EDGES, "eid long, src long, dst long"), spark.createDataFrame(PERM, "id long, label long"), Layout(4, nb=2, nc=1, block_edges=2, chunk_edges=2)


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


@pytest.mark.parametrize("strategy", ["merge", "range_rounds", "gather", "broadcast", "hash_join", "unpivot", "hub_split", "auto"])
def test_relabel(example, strategy):
    edges, perm, layout = example
    assert rows(relabel.relabel(edges, perm, layout, 4, strategy), "eid", "src", "dst") == [(0, 2, 0), (1, 2, 3), (2, 0, 3), (3, 1, 2)]


def test_redistribute_and_compress(example):
    edges, perm, layout = example
    new = relabel.relabel_merge(edges, perm)
    owned = redistribute.ship_sorted(new, layout)
    assert rows(owned, "bucket", "src", "dst") == [(0, 0, 3), (0, 1, 2), (1, 2, 0), (1, 2, 3)]
    for built in (csr.csr_ordered(new, layout), csr.csr_unordered(new, layout), csr.csr_from_sorted(owned, layout)):
        assert rows(built.offsets, "id", "off") == [(0, 0), (1, 1), (2, 2), (3, 4), (4, 4)]
        assert rows(built.neighbors, "pos", "dst") == [(0, 3), (1, 2), (2, 0), (3, 3)]
        assert rows(csr.edges_from_csr(built), "src", "dst") == [(0, 3), (1, 2), (2, 0), (2, 3)]
    assert measures.block_switches(new, "src", 2, parts=2).first().switches == 1
    assert measures.block_switches(new, "dst", 2, parts=3).first().switches == 1


@pytest.mark.parametrize("n,nb", [(10, 3), (64, 4), (150, 4), (1, 1), (7, 1)])
def test_rounds_are_bijections(spark, n, nb):
    for r in (1, 2, 5):
        got = rows(permute.by_rounds(spark, n, nb, r, 1, "portable"), "id", "label")
        assert [i for i, _ in got] == list(range(n)) and sorted(x for _, x in got) == list(range(n))


def test_rounds_refuse_too_many_buckets(spark):
    with pytest.raises(ValueError):
        permute.by_rounds(spark, 10, 4)


def test_quality_sees_equal_quotas_of_one_round(spark):
    """One round exchanges equal shares, which is too even for a fair permutation; sorting is not."""
    once = permute.quality(permute.by_rounds(spark, 256, 4, 1, 3), 256, 4).first()
    assert once.chi_scaled == 0 and once.labels == 256
    assert permute.quality(permute.by_sort(spark, 256, 3), 256, 4).first().chi_scaled > 0


@pytest.mark.parametrize("n", [1, 2, 3, 5, 6, 7, 1000, 1024, 1500, 4097, (1 << 16) + 1])
def test_hash_is_a_bijection(spark, n):
    assert sorted(r.label for r in permute.by_hash(spark, n).collect()) == list(range(n))


def test_sort_does_not_depend_on_partitions_and_equals_sequential(spark):
    want = rows(permute.sequential(spark, 500, 9), "id", "label")
    assert rows(permute.by_sort(spark, 500, 9, bits=3), "id", "label") == want == rows(permute.by_sort(spark, 500, 9, bits=10), "id", "label")


def test_generators_agree(spark):
    spec = GenSpec(scale=6, edge_factor=8, seed=5)
    want = generate_sequential(spark, spec)
    for options in (dict(strategy="merge"), dict(strategy="range_rounds"), dict(csr="unordered", strategy="gather")):
        got = generate_graph(spark, spec, Layout(64, 4, 2, 16, 64), **options)
        assert rows(got.tables["offsets"], "id", "off") == rows(want.tables["offsets"], "id", "off")
        a, b = (np.array([d for _, d in rows(g.tables["neighbors"], "pos", "dst")]) for g in (got, want))
        off = [o for _, o in rows(want.tables["offsets"], "id", "off")]
        assert all(sorted(a[x:y]) == sorted(b[x:y]) for x, y in zip(off, off[1:]))


def test_resume_reads_finished_steps(spark, tmp_path):
    spec = GenSpec(scale=5, edge_factor=4)
    at = f"file://{tmp_path}/g"
    generate_graph(spark, spec, Layout(32, 2, 1), out_dir=at, strategy="merge", stop_after="relabel")
    run = generate_graph(spark, spec, Layout(32, 2, 1), out_dir=at, strategy="merge", resume=True)
    assert run.tables["neighbors"].count() == spec.edges and set(run.seconds) == {"permute", "generate", "relabel", "redistribute", "csr"}


def test_rmat_mean_and_range(spark):
    spec = GenSpec(scale=10, seed=42)
    for df in (rmat.rmat_edges(spark, spec), rmat.rmat_edges_arrow(spark, spec), rmat.rmat_edges_aligned(spark, spec, 8)):
        r = df.agg(F.avg("src").alias("m"), F.max("src").alias("x"), F.min("dst").alias("y"), F.count(F.lit(1)).alias("c")).first()
        assert r.c == spec.edges and r.x < 1024 and r.y >= 0 and abs(r.m - 0.24 * 1023) < 12


def test_odd_vertex_counts_and_options(spark):
    spec = GenSpec(n=100, edge_factor=5)
    r = rmat.rmat_edges(spark, spec).agg(F.max("src").alias("a"), F.max("dst").alias("b"), F.count(F.lit(1)).alias("c")).first()
    assert r.a < 100 and r.b < 100 and r.c == 500
    loops = spark.createDataFrame([(0, 1, 1), (1, 1, 2), (2, 1, 2)], "eid long, src long, dst long")
    assert rows(csr.prepared(loops, True, True, True), "src", "dst") == [(1, 2), (2, 1)]


def test_no_edges_and_one_vertex(spark):
    none = spark.createDataFrame([], "eid long, src long, dst long")
    built = csr.csr_ordered(none, Layout(1, 1, 1))
    assert rows(built.offsets, "id", "off") == [(0, 0), (1, 0)] and built.neighbors.count() == 0


def test_hub_and_isolated_ends(spark):
    hub = spark.createDataFrame([(k, 3, k % 7) for k in range(500)], "eid long, src long, dst long")
    layout = Layout(10, nb=3, nc=2, block_edges=32, chunk_edges=64)
    built = csr.csr_unordered(hub, layout)
    assert [o for _, o in rows(built.offsets, "id", "off")] == [0] * 4 + [500] * 7
    assert rows(csr.adjacency_lists(built, 100).select("part", F.size("nbrs").alias("n")), "part", "n") == [(k, 100) for k in range(5)]
    parts = redistribute.ship_balanced(hub, layout, 90)
    assert parts.groupBy("bucket", "part").count().agg(F.max("count")).first()[0] == 90
    packets = redistribute.packetize(hub, Layout(10, 3, 2, 32, 64, packet_bytes=160), 500)
    assert redistribute.all_arrived(packets, 500) and packets.agg(F.max(F.size("edges"))).first()[0] == 10


def test_endpoints_are_checked(spark):
    bad = spark.createDataFrame([(0, None, 1), (1, -1, 2), (2, 0, 9)], "eid long, src long, dst long")
    with pytest.raises(ValueError, match="'null': 1, 'negative': 1, 'too_large': 1"):
        require_endpoints(bad, 5)


def test_arithmetic_at_scale_38(spark):
    n, layout = 1 << 38, Layout(1 << 38, 8192, 64)
    r = spark.range(1).select(F.lit(n - 1).alias("v")).select(owner_of(F.col("v"), n, 8192).alias("b"), bin_of(F.col("v"), layout).alias("g"), lane_of(F.col("v"), layout).alias("l"), range_lo(F.lit(8191).cast("long"), n, 8192).alias("lo")).first()
    assert (r.b, r.g, r.l, r.lo) == (8191, 8192 * 64 - 1, 63, n - n // 8192)


def test_plan_of_scale_38_has_three_edge_exchanges(spark):
    """Nothing runs: relabelling twice and shipping are the edge shuffles; the permutation adds its own."""
    spec = GenSpec(scale=38)
    edges = rmat.rmat_edges(spark, spec, 16)
    perm = spark.range(spec.vertices).select("id", F.col("id").alias("label"))
    shipped = redistribute.ship_sorted(relabel.relabel_merge(edges, perm), Layout(spec.vertices, 64, 1))
    got = plan_summary(shipped)
    assert got["exchanges"] == 5 and got["merge_joins"] == 2  # 3 of edges, 2 of the permutation
    assert plan_summary(relabel.relabel_hashed(edges, spec.vertices))["exchanges"] == 0


def test_shipping_then_ranking_needs_one_exchange(spark):
    from pyspark.sql import Window

    edges = spark.createDataFrame(EDGES, "eid long, src long, dst long")
    ranked = redistribute.ship_sorted(edges, Layout(4, 2, 1)).withColumn("r", F.row_number().over(Window.partitionBy("bucket").orderBy("src", "dst", "eid")))
    assert plan_summary(ranked)["exchanges"] == 1 and plan_summary(ranked)["sorts"] == 1


def test_components(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(0, 60) if k % 20 != 19] + [(100, 100)], "a long, b long")
    assert {(r.node, r.root) for r in connected_components(edges).collect()} == {(k, k // 20 * 20) for k in range(60)}


def test_hash_of_a_million_and_its_check(spark):
    n = (1 << 20) + 1
    permute.check_bijection(permute.by_hash(spark, n), n)
    with pytest.raises(ValueError, match="not a permutation"):
        permute.check_bijection(permute.by_hash(spark, 100).withColumn("label", F.col("label") % 99), 100)
    ends = relabel.relabel_hashed(rmat.rmat_edges(spark, GenSpec(n=700, edge_factor=4)), 700).agg(F.max("src"), F.max("dst"), F.min("src"), F.min("dst")).first()
    assert max(ends) < 700 and min(ends) >= 0


def test_torn_step_runs_again(spark, tmp_path):
    """A driver lost while a step was writing leaves a folder without the marker of its end."""
    spec, layout, at = GenSpec(scale=5, edge_factor=4), Layout(32, 2, 1), f"file://{tmp_path}/g"
    generate_graph(spark, spec, layout, out_dir=at, strategy="merge", stop_after="relabel")
    (tmp_path / "g" / "owned" / "_temporary" / "0").mkdir(parents=True)
    (tmp_path / "g" / "relabelled" / "_SUCCESS").unlink()
    run = generate_graph(spark, spec, layout, out_dir=at, strategy="merge", resume=True)
    want = generate_sequential(spark, spec)
    assert rows(run.tables["neighbors"], "pos", "dst") == rows(want.tables["neighbors"], "pos", "dst")


def test_runs_merge_to_what_sorting_gives(spark):
    edges = rmat.rmat_edges(spark, GenSpec(scale=8, edge_factor=9), 7)
    layout = Layout(256, nb=3, nc=1)
    want = rows(redistribute.ship_ranked(edges, layout), "bucket", "rank", "src", "dst", "eid")
    assert rows(redistribute.merge_sorted_runs(redistribute.sorted_runs(edges, layout), layout), "bucket", "rank", "src", "dst", "eid") == want
    by = {}
    for b, rank, s, d, e in want:
        by.setdefault(b, []).append((rank, (s, d, e)))
    assert all([r for r, _ in v] == list(range(len(v))) and [k for _, k in v] == sorted(k for _, k in v) for v in by.values())
    unsorted = redistribute.sorted_runs(edges, layout).withColumn("run", F.lit(1))
    with pytest.raises(Exception, match="not sorted"):
        redistribute.merge_sorted_runs(unsorted.repartition(1), layout).collect()


def test_ordered_compression_exchanges_edges_once(spark):
    """After shipping, the neighbours are a scan: no exchange, no sort; only the degrees, a row a vertex, move."""
    run = generate_graph(spark, GenSpec(scale=6), Layout(64, 4, 1), strategy="merge", stop_after="redistribute")
    built = csr.csr_from_sorted(run.tables["owned"], run.layout)
    got = plan_summary(built.neighbors.select("pos", "dst"))
    assert got["sorts"] <= 1 and got["merge_joins"] == 0  # the sort is that of the bases, a row a bucket
    shipped = plan_summary(redistribute.ship_ranked(run.tables["relabelled"], run.layout))
    assert shipped["exchanges"] == 1 and shipped["sorts"] == 1 and shipped["windows"] == 0


def flushes(chunk, threshold):
    held, n = set(), 0
    for s in chunk:
        held.add(s)
        if len(held) == threshold:
            held, n = set(), n + 1
    return n + bool(held)


def test_flushes_equal_streaming_by_hand(spark):
    rng = np.random.default_rng(1)
    src = rng.integers(0, 40, 1000).tolist()
    edges = spark.createDataFrame([(k, s, 0) for k, s in enumerate(src)], "eid long, src long, dst long").repartition(5)
    layout = Layout(40, nb=2, nc=1, chunk_edges=128)
    for threshold in (1, 7, 25, 1000):
        want = [(k, flushes(src[128 * k : 128 * k + 128], threshold)) for k in range(8)]
        assert rows(csr.degrees_flushed(edges, layout, threshold), "chunk", "flushes") == want
    assert rows(csr.adjacency_flushed(edges, layout, 50), "chunk", "flushes") == [(k, -(-min(128, 1000 - 128 * k) // 50)) for k in range(8)]


def test_range_rounds_in_several_plans(spark):
    edges = rmat.rmat_edges(spark, GenSpec(scale=7, edge_factor=6))
    perm = permute.by_sort(spark, 128, 3)
    want = rows(relabel.relabel_merge(edges, perm), "eid", "src", "dst")
    assert rows(relabel.relabel_range_rounds(edges, perm, Layout(128, nb=7), together=3), "eid", "src", "dst") == want
    assert rows(relabel.relabel_range_rounds(edges, perm, Layout(128, nb=6), together=3), "eid", "src", "dst") == want


def test_depth_limit_raises(spark):
    from edgemill.operators.graphops import bfs_levels

    path = spark.createDataFrame([(k, k + 1) for k in range(5)], "src long, dst long")
    assert rows(bfs_levels(path, 0), "id", "level") == [(k, k) for k in range(6)]
    with pytest.raises(RuntimeError, match="beyond level 3"):
        bfs_levels(path, 0, 3)


def test_deep_generator_compiles(spark):
    """Scale 38: the unrolled levels stay within the limits of generated code."""
    edges = rmat.ends_of(spark.range(1000).withColumnRenamed("id", "eid"), GenSpec(scale=38))
    ends = relabel.relabel_hashed(edges, 1 << 38).agg(F.max("src"), F.max("dst"), F.min("src"), F.min("dst")).first()
    assert 0 <= min(ends) and 1 << 32 < max(ends) < 1 << 38


@pytest.mark.parametrize("bits", [1, 7, 24, 38])
def test_hash_columns_equal_the_expression(spark, bits):
    from edgemill.functions.prng import bijective_hash, mixed_columns

    n = 1 << bits
    ids = spark.range(0, n, max(1, n // 300)).select("id", F.col("id").alias("label"))
    bad = mixed_columns(ids, ["label"], n).where((F.col("label") != bijective_hash(F.col("id"), bits)) | ~F.col("label").between(0, n - 1))
    assert bad.count() == 0
