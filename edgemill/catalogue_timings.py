"""The experiment workloads over measured seconds (plans/timings.csv, written by experiments.py): single node, strong and weak scaling, throughput. Capped memory is counted over a given table."""

from __future__ import annotations

import csv
import os

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

import edgemill.plans.models as models
from edgemill.catalogue import NB, SQL_BASE, entry, relabelled
from edgemill.operators import redistribute

_FILE = os.path.join(os.path.dirname(models.__file__), "timings.csv")
_SCHEMA = "workload string, variant string, step string, scale int, nb int, cores int, seconds double, spilled_mb long, heap_mb int"


def measured() -> list[tuple]:
    with open(_FILE, newline="") as f:
        return [(r["workload"], r["variant"], r["step"], int(r["scale"]), int(r["nb"]), int(r["cores"]), float(r["seconds"]), int(r["spilled_mb"]), int(r["heap_mb"])) for r in csv.DictReader(f)]


ROWS = measured()
_NAMES = [c.split()[0] for c in _SCHEMA.split(", ")]
SQL_ROWS = "t AS (SELECT workload, variant, step, scale, nb, cores, CAST(seconds AS DOUBLE) AS seconds, CAST(spilled_mb AS BIGINT) AS spilled_mb, heap_mb FROM (VALUES " + ", ".join(
    "(" + ", ".join(f"'{v}'" if isinstance(v, str) else repr(v) for v in row) + ")" for row in ROWS
) + f") v({', '.join(_NAMES)}))"


def timings(spark, workload: str) -> DataFrame:
    return spark.createDataFrame(ROWS, _SCHEMA).where(F.col("workload") == workload)


def _total(df: DataFrame) -> DataFrame:
    return df.groupBy("variant", "scale", "nb", "cores").agg(F.round(F.sum("seconds"), 6).alias("seconds"))


@entry("W2 C9", f"WITH {SQL_ROWS} SELECT variant, step, scale, seconds, round(seconds / (2.0 ** (scale - 16)), 6) AS norm_seconds FROM t WHERE workload = 'single'")
def single_node_steps(spark, sf_dir):
    """Seconds of each step on one node for growing scale, and normalised; flat curves are linear steps."""
    return models.normalize(timings(spark, "single")).select("variant", "step", "scale", "seconds", F.round("norm_seconds", 6).alias("norm_seconds"))


@entry("W2 B5", f"""WITH {SQL_ROWS}, c AS (SELECT variant, scale, seconds FROM t WHERE workload = 'single' AND step = 'csr')
SELECT o.scale, round(u.seconds / o.seconds, 6) AS unordered_over_ordered FROM c o JOIN c u ON u.scale = o.scale AND u.variant = 'unordered' AND o.variant = 'ordered'""")
def single_node_csr(spark, sf_dir):
    """How many times the unordered compression takes what the scan of sorted buckets takes."""
    c = timings(spark, "single").where("step = 'csr'")
    ordered, unordered = (c.where(F.col("variant") == v).select("scale", F.col("seconds").alias(v)) for v in ("ordered", "unordered"))
    return ordered.join(unordered, "scale").select("scale", F.round(F.col("unordered") / F.col("ordered"), 6).alias("unordered_over_ordered"))


@entry("W4 C10", f"""WITH {SQL_ROWS}, s AS (SELECT scale, cores, round(sum(seconds), 6) AS seconds FROM t WHERE workload = 'strong' GROUP BY ALL)
SELECT scale, cores, seconds, round(first_value(seconds) OVER w / seconds, 6) AS speedup, round(first_value(seconds) OVER w / seconds / cores, 6) AS efficiency FROM s WINDOW w AS (PARTITION BY scale ORDER BY cores)""")
def strong_scaling_total(spark, sf_dir):
    """Total seconds at 1, 2, 4 and 8 cores; small scales saturate first."""
    whole = _total(timings(spark, "strong")).select(F.lit("total").alias("step"), "scale", F.col("cores").alias("nb"), "seconds")
    return models.strong_scaling(whole).join(whole, ["scale", "nb"]).select("scale", F.col("nb").alias("cores"), "seconds", F.round("speedup", 6).alias("speedup"), F.round("efficiency", 6).alias("efficiency"))


@entry("W5 C10", f"""WITH {SQL_ROWS} SELECT step, scale, cores, seconds, round(first_value(seconds) OVER w / seconds, 6) AS speedup FROM t WHERE workload = 'strong' WINDOW w AS (PARTITION BY step, scale ORDER BY cores)""")
def strong_scaling_steps(spark, sf_dir):
    rows = timings(spark, "strong").select("step", "scale", F.col("cores").alias("nb"), "seconds")
    return models.strong_scaling(rows).join(rows, ["step", "scale", "nb"]).select("step", "scale", F.col("nb").alias("cores"), "seconds", F.round("speedup", 6).alias("speedup"))


@entry("W6 C11", f"WITH {SQL_ROWS} SELECT step, scale, cores, round(seconds / first_value(seconds) OVER (PARTITION BY step ORDER BY scale), 6) AS ratio FROM t WHERE workload = 'weak'")
def weak_scaling_steps(spark, sf_dir):
    """Seconds against the smallest run as vertices and cores double; constant steps scale."""
    rows = timings(spark, "weak").select("step", "scale", F.col("cores").alias("nb"), "seconds")
    return models.weak_scaling(rows).select("step", "scale", F.col("nb").alias("cores"), F.round("ratio", 6).alias("ratio"))


HEAP = 4096  # edges that an owner may hold


@entry("W3 C17", f"""{SQL_BASE}, c AS (SELECT (src * {NB}) // n AS bucket, count(*) AS c FROM relabelled, dims GROUP BY 1)
SELECT {NB} AS nb, CAST({HEAP} AS BIGINT) AS heap_edges, CAST(sum(c) AS BIGINT) AS edges, CAST(sum((c + {HEAP - 1}) // {HEAP}) AS BIGINT) AS fills, CAST(sum(greatest(c - {HEAP}, 0)) AS BIGINT) AS spilled_edges FROM c""")
def capped_memory(spark, sf_dir):
    """A run over the part-supplier edges whose owners get many times what they may hold: how often they fill up, what goes to disk, and all edges come out of the merge of runs."""
    edges, layout, _ = relabelled(spark, sf_dir)
    done = redistribute.merge_sorted_runs(redistribute.sorted_runs(edges, layout), layout)
    owners = done.groupBy("bucket").agg(F.count(F.lit(1)).alias("c"))
    fills, over = F.call_function("div", F.col("c") + (HEAP - 1), F.lit(HEAP).cast("long")), F.greatest(F.col("c") - HEAP, F.lit(0).cast("long"))
    return owners.agg(F.sum("c").alias("edges"), F.sum(fills).alias("fills"), F.sum(over).alias("spilled_edges")).select(
        F.lit(NB).alias("nb"), F.lit(HEAP).cast("long").alias("heap_edges"), "edges", "fills", "spilled_edges"
    )


@entry("C16", f"WITH {SQL_ROWS} SELECT variant AS run, scale, round(16 * (2.0 ** scale) / sum(seconds), 3) AS edges_per_second FROM t WHERE workload = 'single' GROUP BY variant, scale")
def throughput(spark, sf_dir):
    rows = timings(spark, "single").withColumnRenamed("variant", "run")
    return models.throughput(rows).select("run", "scale", F.round("edges_per_second", 3).alias("edges_per_second"))
