"""spark.read.format("rmat"): edges as a custom data source, batch and stream."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def numpy_ends(first: int, last: int, scale: int, seed: int, probs: tuple[float, ...]):
    """(src, dst) of edges first to last, as arrays; counter based."""
    import numpy as np

    eid = np.arange(first, last).astype(np.uint64)
    src, dst = np.zeros(len(eid), np.int64), np.zeros(len(eid), np.int64)
    a, b, c, _ = probs
    t1, t2, t3 = (int(x * 2**32) for x in (a, a + b, a + b + c))
    for level in range(scale):
        x = eid + np.uint64((seed * 1_000_003 + level + 1) * 0x9E3779B97F4A7C15 % 2**64)
        for _ in range(2):
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        u = ((x ^ (x >> np.uint64(31))) >> np.uint64(32)).astype(np.int64)
        src += (u >= t2).astype(np.int64) << (scale - 1 - level)
        dst += (((u >= t1) & (u < t2)) | (u >= t3)).astype(np.int64) << (scale - 1 - level)
    return src, dst


class _Span(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


def _params(options) -> tuple[int, int, int, tuple[float, ...]]:
    probs = tuple(float(x) for x in options.get("probs", "0.57,0.19,0.19,0.05").split(","))
    return int(options.get("scale", "10")), int(options.get("edgeFactor", "16")), int(options.get("seed", "42")), probs


def _batch(first: int, last: int, scale: int, seed: int, probs):
    import numpy as np
    import pyarrow as pa

    src, dst = numpy_ends(first, last, scale, seed, probs)
    return pa.RecordBatch.from_arrays([pa.array(np.arange(first, last)), pa.array(src), pa.array(dst)], ["eid", "src", "dst"])


class RmatReader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.factor, self.seed, self.probs = _params(options)
        self.parts = int(options.get("partitions", "8"))

    def partitions(self):
        m = self.factor << self.scale
        return [_Span(m * k // self.parts, m * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, span: _Span) -> Iterator:
        for at in range(span.first, span.last, 1 << 16):
            yield _batch(at, min(span.last, at + (1 << 16)), self.scale, self.seed, self.probs)


class RmatStream(SimpleDataSourceStreamReader):
    """`rowsPerBatch` further edges each time it is asked."""

    def __init__(self, options):
        self.scale, self.factor, self.seed, self.probs = _params(options)
        self.step, self.total = int(options.get("rowsPerBatch", "1000")), self.factor << self.scale

    def initialOffset(self) -> dict:
        return {"eid": 0}

    def _rows(self, first: int, last: int):
        src, dst = numpy_ends(first, last, self.scale, self.seed, self.probs)
        return iter(list(zip(range(first, last), src.tolist(), dst.tolist())))

    def read(self, start: dict):
        first = start["eid"]
        last = min(self.total, first + self.step)
        return self._rows(first, last), {"eid": last}

    def readBetweenOffsets(self, start: dict, end: dict):
        return self._rows(start["eid"], end["eid"])


class RmatSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "eid long, src long, dst long"

    def reader(self, schema) -> RmatReader:
        return RmatReader(self.options)

    def simpleStreamReader(self, schema) -> RmatStream:
        return RmatStream(self.options)


def register(spark: SparkSession) -> None:
    from edgemill.shipping import ship_package

    ship_package(spark)
    spark.dataSource.register(RmatSource)
