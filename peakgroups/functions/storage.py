"""Cutting lineage through written tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
#: Whether a query's shuffle files are deleted when it ends.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; where that is unset and all runs on one machine
    (tests), a folder of our own. On a cluster executors would not see it: an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = _OWN.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="peakgroups-"))
    return folder.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_folder(spark)}/peakgroups/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again.

    Later jobs start from the files, so the loss of an executor repeats no earlier
    stage. The reread table has no known partitioning, so a join on it exchanges both
    sides and AQE may split a skewed key. The job's shuffle files go as soon as the table
    is written, and not when the driver next happens to collect its garbage.
    """
    spark = df.sparkSession
    path = shared_path(spark, name)
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before) if before is not None else spark.conf.unset(_CLEANUP)
    return spark.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a path written by this module, through Hadoop's file system API."""
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def collect_garbage(spark: SparkSession) -> None:
    """Let the shuffle files of finished jobs go.

    Spark deletes them once nothing on the driver refers to the job; a large driver that
    collects seldom would otherwise keep those of a whole chain of jobs.
    """
    spark._jvm.System.gc()


def release(df: DataFrame) -> None:
    """Delete the files behind a table made by :func:`materialize`."""
    files = df.inputFiles()
    if files:
        drop_path(df.sparkSession, files[0].rsplit("/", 1)[0])
    collect_garbage(df.sparkSession)
