"""Edge lists that arrive as streams: generation, relabelling, shipping to owners, degrees, windows, late edges, packets.

Every function takes a streaming DataFrame and is one Structured Streaming plan; `run_to_end`
drives it over all that a source holds now. What a plan keeps between batches is bounded by its watermark, by
the number of vertices (degrees) or by a packet a bucket. Sinks write by batch
number, so a batch that is repeated after a failure leaves the same rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from edgemill.config import GenSpec, Layout
from edgemill.operators.redistribute import with_owner
from edgemill.scratch import exists, fresh_path
from edgemill.sources.rmat import ends_of

PACKET_SCHEMA = "bucket int, packet_no long, edges long, first_eid long"


def staged(df: DataFrame, part: str, parts: int, name: str = "stream") -> DataFrame:
    """df as a stream of `parts` batches: rows with column `part` = 0 come first, then 1, ... (the column is not part of the stream)."""
    path = fresh_path(df.sparkSession, name)
    for k in range(parts):
        df.where(F.col(part) == k).drop(part).coalesce(1).write.mode("append").parquet(path)
    return file_stream(df.sparkSession, path, df.drop(part).schema)


def file_stream(spark: SparkSession, path: str, schema: StructType, files: int = 1) -> DataFrame:
    """Parquet files as they come, oldest first, `files` a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def run_to_end(stream: DataFrame, sink: Callable[[DataFrame, int], None], mode: str = "append", checkpoint: str | None = None) -> None:
    """All batches that the sources hold now, through `sink(batch, number)`."""
    writer = stream.writeStream.foreachBatch(sink).outputMode(mode).trigger(availableNow=True)
    writer.option("checkpointLocation", checkpoint or fresh_path(stream.sparkSession, "stream-state")).start().awaitTermination()


def into_batches(path: str, by: list[str] | None = None) -> Callable[[DataFrame, int], None]:
    """A sink that keeps each batch in a folder of its own and replaces it when the batch is repeated."""

    def put(batch: DataFrame, number: int) -> None:
        writer = batch.write.mode("overwrite")
        (writer.partitionBy(*by) if by else writer).parquet(f"{path}/batch={number}")

    return put


def stored(spark: SparkSession, path: str, schema: StructType) -> DataFrame:
    """What into_batches has written, with the column batch."""
    whole = StructType(schema.fields).add("batch", "long")
    return spark.read.schema(whole).option("basePath", path).parquet(path) if exists(spark, path) else spark.createDataFrame([], whole)


def collected(stream: DataFrame, mode: str = "append", name: str = "stream-out", by: list[str] | None = None) -> DataFrame:
    """Run a stream to its end into the shared folder and read it back, with the column batch."""
    path = fresh_path(stream.sparkSession, name)
    run_to_end(stream, into_batches(path, by), mode)
    return stored(stream.sparkSession, path, stream.schema)


def generate_edges(eids: DataFrame, spec: GenSpec) -> DataFrame:
    """A continuous generator: (eid, src, dst) of edge numbers as they arrive, equal to those of the batch generator."""
    return ends_of(eids.select("eid"), spec)


def relabel_stream(edges: DataFrame, perm: DataFrame, endpoint: str = "src") -> DataFrame:
    """One end of arriving edges through a static permutation (a stream-static join, no state)."""
    side = perm.select(F.col("id").alias(endpoint), F.col("label").alias("_label"))
    return edges.join(side, endpoint).select(*(F.col("_label").alias(c) if c == endpoint else F.col(c) for c in edges.columns))


def route_to_owners(edges: DataFrame, layout: Layout, path: str, checkpoint: str | None = None) -> DataFrame:
    """Append arriving edges to the owners' folders; a repeated batch replaces itself. Returns the edge list."""
    owned = with_owner(edges, layout)
    run_to_end(owned, into_batches(path, ["bucket"]), checkpoint=checkpoint)
    return stored(edges.sparkSession, path, owned.schema)


def running_degrees(edges: DataFrame) -> DataFrame:
    """(src, deg) kept up to date: a stream of changed counts, of which the latest batch holds good for each vertex."""
    counts = edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    changes = collected(counts, "update", "degree-changes")
    return changes.groupBy("src").agg(F.max_by("deg", "batch").alias("deg"))


def _latest(windows: DataFrame) -> DataFrame:
    out = collected(windows, "complete", "windows")
    return out.where(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")


def _spelled(df: DataFrame, *names: str) -> list:
    return [F.date_format(f"window.{n}", "yyyy-MM-dd HH:mm:ss").alias(n) for n in names]


def windowed_degrees(edges: DataFrame, width: str, slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(start, end, src, deg) of tumbling or sliding windows over ts."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    counts = edges.withWatermark("ts", delay).groupBy(window, "src").agg(F.count(F.lit(1)).alias("deg"))
    return _latest(counts.select(*_spelled(counts, "start", "end"), "src", "deg"))


def session_degrees(edges: DataFrame, gap: str, delay: str = "1 day") -> DataFrame:
    """(start, src, deg) of sessions: edges of a source with less than `gap` between them."""
    window = F.session_window("ts", gap).alias("window")
    counts = edges.withWatermark("ts", delay).groupBy(window, "src").agg(F.count(F.lit(1)).alias("deg"))
    return _latest(counts.select(*_spelled(counts, "start"), "src", "deg"))


def split_late(edges: DataFrame, delay: str, path: str) -> DataFrame:
    """(columns of edges, late, batch): an edge is late when it is more than `delay` behind the newest of the batches before its own.

    Late edges are kept apart (column late), not lost. The newest time so far is the maximum over stored batches, so a repeated batch is judged alike.
    """
    spark, schema = edges.sparkSession, StructType(edges.schema.fields).add("late", "boolean")

    def judge(batch: DataFrame, number: int) -> None:
        before = stored(spark, path, schema).where(F.col("batch") < number).agg(F.max("ts").alias("newest"))  # one row
        late = F.coalesce(F.col("ts") < F.col("newest") - F.expr(f"INTERVAL {delay}"), F.lit(False))
        batch.crossJoin(F.broadcast(before)).withColumn("late", late).drop("newest").write.mode("overwrite").parquet(f"{path}/batch={number}")

    run_to_end(edges, judge)
    return stored(spark, path, schema)


def without_copies(edges: DataFrame, keys: list[str], delay: str) -> DataFrame:
    """Arriving edges without repeats inside the watermark's delay."""
    return edges.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def packets(edges: DataFrame, capacity: int) -> DataFrame:
    """(bucket, packet_no, edges, first_eid): a bucket's packet leaves when it holds `capacity` edges, and when the sender's end (a row with null eid) arrives.

    Between batches a bucket keeps its packet's number, size and first edge.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def send(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, held, first = state.get if state.exists else (0, 0, -1)
        rows = pd.concat(list(parts))["eid"]
        ended, eids = rows.isna().any(), sorted(rows.dropna().astype("int64").tolist())
        out, at = [], 0
        while at < len(eids):
            taken = min(capacity - held, len(eids) - at)
            first = eids[at] if not held else first
            held, at = held + taken, at + taken
            if held == capacity:
                out.append((key[0], number, held, first))
                number, held = number + 1, 0
        if ended and held:
            out.append((key[0], number, held, first))
            number, held = number + 1, 0
        state.update((number, held, first))
        yield pd.DataFrame(out, columns=["bucket", "packet_no", "edges", "first_eid"])

    keyed = edges.select("bucket", "eid").groupBy("bucket")
    return keyed.applyInPandasWithState(send, PACKET_SCHEMA, "number long, held long, first long", "append", GroupStateTimeout.NoTimeout)


def followed_by(first: DataFrame, second: DataFrame, within: str, delay: str = "1 day") -> DataFrame:
    """(src, eid, next_eid): edges of the first stream and those of the second from the same source at most `within` later."""
    a = first.select("src", "eid", F.col("ts").alias("ts_a")).withWatermark("ts_a", delay)
    b = second.select(F.col("src").alias("src_b"), F.col("eid").alias("next_eid"), F.col("ts").alias("ts_b")).withWatermark("ts_b", delay)
    soon = (F.col("src") == F.col("src_b")) & (F.col("ts_b") >= F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr(f"INTERVAL {within}"))
    return a.join(b, soon).select("src", "eid", "next_eid")


def batch_of(column: str, order: list[str], parts: int):
    """The batch of each row, `parts` equal runs in order; for small tables that are staged as streams."""
    return (F.ntile(parts).over(Window.partitionBy(F.lit(0)).orderBy(*order)) - 1).alias(column)
