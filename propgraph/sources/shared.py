"""Storage that the driver and all executors see: paths, tables that cut the lineage, and their removal."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Where the session names none, a local folder stands in, but only
    where driver and executors are one process; on a cluster an executor's files would be lost to the others."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        if sc.master != "local" and not sc.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="propgraph-"))
    return sc.getCheckpointDir().rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A new folder name in shared storage."""
    return f"{shared_dir(spark)}/propgraph/{name}-{uuid.uuid4().hex}"


def checkpoint_dir(spark: SparkSession) -> None:
    """From now on checkpoint() works."""
    base = shared_dir(spark)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(base)


@contextlib.contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Writes inside delete their shuffle files when they end, rather than when the driver collects garbage."""
    was = spark.conf.get(_CLEANUP)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(_CLEANUP, was)


def written(df: DataFrame, name: str, files: int | None = None) -> DataFrame:
    """Cut the lineage with a table in shared storage; release() deletes it. files: at most so many, where rows are few for the session's partitions."""
    spark = df.sparkSession
    df = df.coalesce(files) if files else df
    path = shared_path(spark, name)
    with shuffles_dropped(spark):
        df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def release(*frames: DataFrame | None) -> None:
    """Deletes the tables of frames that written() returned and that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_written_path", None)
        if path:
            remove(df.sparkSession, path)
