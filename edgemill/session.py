"""A session with the settings that edge-sized plans want."""

from __future__ import annotations

from pyspark.sql import SparkSession


def build_session(app: str = "edgemill", master: str | None = None, **settings: str) -> SparkSession:
    """hugeMethodLimit keeps deep recursive-matrix expressions compiled; the rest are adaptive defaults for large shuffles."""
    builder = SparkSession.builder.appName(app)
    if master:
        builder = builder.master(master)
    base = {
        "spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.skewJoin.enabled": "true", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "256m",
        "spark.sql.codegen.hugeMethodLimit": "8000", "spark.sql.session.timeZone": "UTC", "spark.sql.parquet.compression.codec": "zstd",
    }
    for k, v in (base | {k.replace("__", "."): str(v) for k, v in settings.items()}).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()
