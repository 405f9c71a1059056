"""Tables that cut lineage, in the folder that the whole cluster shares."""

from __future__ import annotations

import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
_PATHS: weakref.WeakKeyDictionary[DataFrame, str] = weakref.WeakKeyDictionary()
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; where unset, a temporary one of this application, on a single machine only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the whole cluster shares")
        app = spark.sparkContext.applicationId
        folder = _OWN.setdefault(app, "file://" + tempfile.mkdtemp(prefix="edgemill-scratch-"))
    return folder.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/edgemill/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: later plans start from the files.

    The shuffle files of the write go when it has ended, as nothing reads them any more.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    writer = df.write.mode("error")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        writer.parquet(path)
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        else:
            spark.conf.set(_CLEANUP, before)
    stored = spark.read.schema(df.schema).parquet(path)
    _PATHS[stored] = path
    return stored


def _store_of(spark: SparkSession, path: str):
    """(file system, path) as Hadoop has them."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()), at


def exists(spark: SparkSession, path: str) -> bool:
    store, at = _store_of(spark, path)
    return store.exists(at)


def discard(*stored: DataFrame) -> None:
    """Delete the files of tables from materialise(). Only for those that no later plan reads, not even to recompute a lost part."""
    for df in stored:
        store, at = _store_of(df.sparkSession, _PATHS.pop(df))
        store.delete(at, True)
