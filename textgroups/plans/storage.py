"""Shared storage for intermediate results.

Lineage is cut by writing Parquet below the folder that ``spark.checkpoint.dir`` names, which the driver and every
executor can read, so a lost executor costs a re-read and nothing else.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

CHECKPOINT_KEY = "spark.checkpoint.dir"


def shared_dir(spark: SparkSession) -> str:
    """The shared folder; a folder of our own only where the session names none (tests, local mode)."""
    named = spark.sparkContext.getConf().get(CHECKPOINT_KEY) or spark.conf.get(CHECKPOINT_KEY, None)
    if named:
        return named.rstrip("/")
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise ValueError(f"set {CHECKPOINT_KEY}: executors on other machines need a folder that all can read")
        context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="textgroups-"))
    return context.getCheckpointDir().rstrip("/")


def workspace(spark: SparkSession, name: str) -> str:
    """A fresh path below the application's own part of the shared folder."""
    return f"{_own(spark)}/{name}-{uuid.uuid4().hex}"


def _own(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/textgroups-{spark.sparkContext.applicationId}"


def clear(spark: SparkSession) -> None:
    """Delete all that this application has written for itself: call it when its results have been taken out."""
    drop_path(spark, _own(spark))


def local_path(path: str) -> str | None:
    """The POSIX path of a ``file:`` location, None for any other store."""
    if path.startswith("file:"):
        return "/" + path[5:].lstrip("/")
    return path if path.startswith("/") else None


def materialise(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write ``df`` to the shared folder and return a reader of the written rows."""
    spark = df.sparkSession
    path = workspace(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a path of the shared folder through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def input_bytes(df: DataFrame) -> int:
    """Size of a plan as the optimizer estimates it (file sizes for a scan)."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
