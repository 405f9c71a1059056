"""Headline timings: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import functions as F

from edgemill import catalogue
from edgemill.config import GenSpec, Layout
from edgemill.functions.prng import mixed_columns
from edgemill.operators import csr, permute, redistribute, relabel
from edgemill.plans.generate import generate_graph
from edgemill.session import build_session
from edgemill.sources.rmat import rmat_edges

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def consumed(df) -> None:
    """Compute every row and column; nothing is collected."""
    df.write.format("noop").mode("overwrite").save()


def main() -> None:
    spark = build_session("edgemill-bench", f"local[{CPUS}]", spark__sql__shuffle__partitions=CPUS, spark__ui__enabled="false", spark__driver__memory="12g", spark__ui__showConsoleProgress="false")
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}

    def timed(name: str, make) -> None:
        began = time.perf_counter()
        made = make()
        if made is not None:
            consumed(made)
        seconds[name] = round(time.perf_counter() - began, 3)

    consumed(spark.range(1000))  # start the executors before the clock
    catalogue.queries()
    for name in ("perm_sort", "edges_part_supplier", "relabel_merge", "relabel_hash_join", "relabel_broadcast", "relabel_range_rounds", "ship_sorted", "csr_ordered_neighbors", "csr_unordered_neighbors", "generate_hash_kernel"):
        timed(name, lambda: catalogue.ENTRIES[name].query(spark, SF_DIR))
    numbers = 1 << 22
    timed("hash_2e22_ints", lambda: mixed_columns(spark.range(numbers).select(F.col("id").alias("h")), ["h"], 1 << 24))
    timed("chunk_sort_2e22_ints", lambda: spark.range(numbers).select(F.xxhash64("id").alias("k")).repartition(numbers >> 16).sortWithinPartitions("k"))
    norm: dict[str, float] = {}
    for scale in (14, 16, 18):
        spec, layout = GenSpec(scale=scale), Layout(1 << scale, 8, 1)
        for variant in ("ordered", "unordered"):
            run = generate_graph(spark, spec, layout, strategy="merge", csr=variant)
            for step, s in run.seconds.items():
                if variant == "ordered" or step == "csr":
                    seconds[f"s{scale}_{step}{'_unordered' if variant == 'unordered' else ''}"] = round(s, 3)
            norm[f"s{scale}_{variant}"] = round(sum(run.seconds.values()) / 2.0 ** (scale - 16), 3)
    spec = GenSpec(scale=18)
    timed("s18_rmat_only", lambda: rmat_edges(spark, spec))
    timed("s18_permutation_rounds", lambda: permute.by_rounds(spark, 1 << 18, 8))
    timed("s18_hash_kernel", lambda: csr.csr_ordered(relabel.relabel_hashed(rmat_edges(spark, spec), 1 << 18), Layout(1 << 18, 8, 1)).neighbors)
    timed("s18_ship_unsorted", lambda: redistribute.ship_to_owner(rmat_edges(spark, spec), Layout(1 << 18, 8, 1)))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "norm_seconds": norm, "sf": SF_DIR.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
