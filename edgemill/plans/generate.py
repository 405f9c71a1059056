"""The whole generator as steps with stored results: permute, generate, relabel, redistribute, compress."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from edgemill.config import GenSpec, Layout
from edgemill.operators import csr as csr_ops
from edgemill.operators import permute, redistribute, relabel
from edgemill.scratch import exists, fresh_path
from edgemill.sources.rmat import rmat_edges

STEPS = ("permute", "generate", "relabel", "redistribute", "csr")


@dataclass
class Run:
    """Tables by step and seconds by step."""

    spec: GenSpec
    layout: Layout
    tables: dict[str, DataFrame] = field(default_factory=dict)
    seconds: dict[str, float] = field(default_factory=dict)

    def timings(self, spark: SparkSession, name: str, cores: int) -> DataFrame:
        rows = [(name, step, self.spec.levels, self.layout.nb, cores, s, s / 2.0 ** (self.spec.levels - 16)) for step, s in self.seconds.items()]
        return spark.createDataFrame(rows, "run string, step string, scale int, nb int, cores int, seconds double, norm_seconds double")


def generate_graph(
    spark: SparkSession, spec: GenSpec, layout: Layout | None = None, out_dir: str | None = None, shuffle: str = "sort", strategy: str = "auto",
    csr: str = "ordered", stop_after: str | None = None, edges: DataFrame | None = None, options: dict | None = None, resume: bool = False,
) -> Run:
    """Run the steps in order; each ends when its tables are stored, as the distributed generator's steps end at a barrier.

    shuffle: sort, rounds, sequential, identity or hash. strategy: see relabel.relabel.
    csr: ordered (the collector sorts), merged (senders sort, the collector merges) or unordered. With resume, steps whose tables are already in out_dir are read, not run, so a lost
    driver repeats one step. `edges` replaces the generated list.
    """
    layout = layout or Layout.for_edges(spec.vertices, spec.edges)
    out_dir = out_dir or fresh_path(spark, "graph")
    run = Run(spec, layout)

    def step(name: str, **tables) -> None:
        began = time.perf_counter()
        for table, make in tables.items():
            path = f"{out_dir}/{table}"
            # a folder without the marker of a finished write is what a lost driver left: the step runs again
            if not (resume and exists(spark, f"{path}/_SUCCESS")):
                make().write.mode("overwrite").parquet(path)
            run.tables[table] = spark.read.parquet(path)
        run.seconds[name] = time.perf_counter() - began

    def labels() -> DataFrame:
        n = spec.vertices
        return {
            "sort": lambda: permute.by_sort(spark, n, spec.seed, spec.backend), "rounds": lambda: permute.by_rounds(spark, n, layout.nb, None, spec.seed, spec.backend),
            "sequential": lambda: permute.sequential(spark, n, spec.seed, spec.backend), "identity": lambda: permute.identity(spark, n), "hash": lambda: permute.by_hash(spark, n),
        }[shuffle]()

    def compressed():
        if "built" not in run.__dict__:
            make = csr_ops.csr_unordered if csr == "unordered" else csr_ops.csr_from_sorted
            run.built = make(run.tables["owned"], layout)
        return run.built

    # unordered edges are appended as they arrive; ordered ones keep their places, so that compression is a scan
    ship = {
        "ordered": lambda e: redistribute.ship_ranked(e, layout), "merged": lambda e: redistribute.merge_sorted_runs(redistribute.sorted_runs(e, layout), layout),
        "unordered": lambda e: redistribute.ship_to_owner(e, layout).select("bucket", "eid", "src", "dst"),
    }[csr]

    todo = {
        "permute": dict(perm=labels),
        "generate": dict(edges=lambda: csr_ops.prepared(edges if edges is not None else rmat_edges(spark, spec), **(options or {}))),
        "relabel": dict(relabelled=lambda: relabel.relabel(run.tables["edges"], run.tables["perm"], layout, spec.edges, strategy)),
        "redistribute": dict(owned=lambda: ship(run.tables["relabelled"])),
        "csr": dict(offsets=lambda: compressed().offsets, neighbors=lambda: compressed().neighbors),
    }
    for name in STEPS:
        step(name, **todo[name])
        if name == stop_after:
            break
    return run


def generate_sequential(spark: SparkSession, spec: GenSpec, **options) -> Run:
    """The specification: one bucket, one sorted permutation, merge, sort, scan."""
    return generate_graph(spark, spec, Layout(spec.vertices, nb=1, nc=1), shuffle="sequential", strategy="merge", **options)


def generate_hashed(spark: SparkSession, spec: GenSpec, layout: Layout | None = None, key: int = 7) -> csr_ops.Csr:
    """The in-memory baseline: edges, hash of both ends, compressed rows; one plan, one edge shuffle, no permutation."""
    layout = layout or Layout.for_edges(spec.vertices, spec.edges)
    return csr_ops.csr_ordered(relabel.relabel_hashed(rmat_edges(spark, spec), spec.vertices, key), layout)
