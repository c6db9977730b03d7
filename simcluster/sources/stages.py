"""Stages that are kept: written to the shared folder and read again, so that loss of executors costs nothing."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which the side of a join is broadcast after a count.
SMALL_ROWS = 200_000
#: Setting under which Spark deletes the shuffle files of a query at its end.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_WRITING: dict = {"lock": Lock(), "stages": 0, "before": None}


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where unset, a temporary folder under a local master only."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="simcluster-")
        atexit.register(shutil.rmtree, root, True)
        root = f"file://{root}"
        spark.conf.set("spark.checkpoint.dir", root)
    return root.rstrip("/")


@contextmanager
def shuffles_deleted(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of queries that run inside are deleted at their end, not when the driver's heap is next collected.

    For writes, whose plans nothing runs again. Several threads may be inside; the setting goes back with the last.
    """
    with _WRITING["lock"]:
        if not _WRITING["stages"]:
            _WRITING["before"] = spark.conf.get(CLEANUP, None)
            spark.conf.set(CLEANUP, "true")
        _WRITING["stages"] += 1
    try:
        yield
    finally:
        with _WRITING["lock"]:
            _WRITING["stages"] -= 1
            if not _WRITING["stages"]:
                spark.conf.unset(CLEANUP) if _WRITING["before"] is None else spark.conf.set(CLEANUP, _WRITING["before"])


def stage_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def stage(df: DataFrame, name: str, path: str | None = None, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """df, written once: later plans read the files instead of running the joins before them again."""
    spark = df.sparkSession
    path = path or stage_path(spark, name)
    writer = df.write.option("compression", "zstd")
    with shuffles_deleted(spark):
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_stage(spark: SparkSession, path: str) -> None:
    """Delete a stage that nothing reads any more."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def is_small(df: DataFrame, max_rows: int = SMALL_ROWS) -> bool:
    return df.limit(max_rows + 1).count() <= max_rows


def small(df: DataFrame, max_rows: int = SMALL_ROWS) -> DataFrame:
    """df with a broadcast hint if it is known to be small, else as it is."""
    return F.broadcast(df) if is_small(df, max_rows) else df
