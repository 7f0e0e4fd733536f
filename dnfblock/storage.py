"""Intermediate tables in the folder that the whole cluster shares.

Every cut of lineage in this library goes through :func:`materialize`: the rows are written as
Parquet under ``spark.checkpoint.dir`` and read back, so that a lost executor costs the tasks it
ran and nothing else.
"""

from __future__ import annotations

import getpass
import tempfile
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a local folder only where it is unset (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = f"file://{tempfile.gettempdir()}/dnfblock-{getpass.getuser()}"
    return root.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    """A fresh path below the shared folder; it is deleted when the application ends."""
    path = f"{shared_root(spark)}/{spark.sparkContext.applicationId}/{label}-{uuid.uuid4().hex}"
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jpath)
    return path


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def files_of_shuffles_removed(spark: SparkSession) -> Iterator[None]:
    """What runs inside leaves no shuffle files behind; otherwise they stay until the driver happens to collect garbage."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, before)


def materialize(df: DataFrame, label: str, codec: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder, compressed by ``codec`` if given, and return a scan of what was written."""
    spark = df.sparkSession
    path = new_path(spark, label)
    with files_of_shuffles_removed(spark):
        df.write.parquet(path, compression=codec)
    made = spark.read.schema(df.schema).parquet(path)
    made.kept_at = path
    return made


def together(spark: SparkSession, *jobs: Callable[[], object]) -> list:
    """What independent ``jobs`` return, run at once: where jobs are small, tasks of one fill the waits of another."""
    if len(jobs) < 2:
        return [job() for job in jobs]
    with files_of_shuffles_removed(spark), ThreadPoolExecutor(len(jobs)) as pool:
        return list(pool.map(lambda job: job(), jobs))


def discard(*made: DataFrame) -> None:
    """Delete what :func:`materialize` wrote for these frames; nothing may read them any more."""
    for df in made:
        remove(df.sparkSession, df.kept_at)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path of :func:`new_path` before the application ends."""
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)
