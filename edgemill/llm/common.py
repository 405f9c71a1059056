"""Shared helpers of the training-data operators."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgemill.scratch import discard, fresh_path, materialise, shared_folder
from edgemill.shipping import ship_package

__all__ = ["discard", "fresh_path", "materialise", "shared_folder", "ship_package", "documents", "texts_of", "frame_batches"]


def documents(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    """Texts of a batch; null counts as empty."""
    return [t or "" for t in batch.column(column).to_pylist()]


def id_and_text(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns an operator reads, whatever else the table has."""
    return df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))


def frame_batches(batches: Iterator[pa.RecordBatch], schema: pa.Schema, rows: Iterator[dict], size: int = 4096) -> Iterator[pa.RecordBatch]:
    held: list[dict] = []
    for row in rows:
        held.append(row)
        if len(held) >= size:
            yield pa.RecordBatch.from_pylist(held, schema=schema)
            held = []
    if held:
        yield pa.RecordBatch.from_pylist(held, schema=schema)
