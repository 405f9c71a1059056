"""What a plan will do, counted from its description."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame, mode: str = "simple") -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode))


def plan_summary(df: DataFrame) -> dict[str, int]:
    """Numbers of exchanges (broadcasts apart), sorts, joins, windows and Python nodes of the physical plan."""
    names = [m[1] for m in re.finditer(r"(?m)^[\s:+*()\d-]*?([A-Z][A-Za-z]+)", plan_text(df))]
    count = lambda pattern: sum(bool(re.fullmatch(pattern, x)) for x in names)
    return {
        "exchanges": count("Exchange"), "broadcasts": count("BroadcastExchange"), "sorts": count("Sort"), "merge_joins": count("SortMergeJoin"), "hash_joins": count("ShuffledHashJoin"),
        "broadcast_joins": count("BroadcastHashJoin"), "windows": count("Window"), "python": count(r".*(Arrow|Pandas|Python).*"),
    }


def plan_table(df: DataFrame) -> DataFrame:
    return df.sparkSession.createDataFrame(sorted(plan_summary(df).items()), "node string, times int")
