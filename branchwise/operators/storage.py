"""Tables written once to the folder that all machines share, so that later steps read them and not their lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: One name for everything a driver process settles, so that runs do not meet each other.
_RUN = uuid.uuid4().hex


def work_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or where the session names none (tests) a folder of this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        named = f"file://{tempfile.mkdtemp(prefix='branchwise-')}"
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def filesystem(spark: SparkSession, path: str):
    """The Hadoop path and its file system."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark._jsc.hadoopConfiguration())


def settled(df: DataFrame, name: str) -> DataFrame:
    """Write and read back; what is left when the driver ends is deleted then."""
    spark = df.sparkSession
    run = f"{work_dir(spark)}/branchwise/{_RUN}"
    at, fs = filesystem(spark, run)
    if fs.mkdirs(at):
        fs.deleteOnExit(at)
    path = f"{run}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._settled = path
    return out


def discard(df: DataFrame) -> None:
    """Delete a settled table that nothing will read again."""
    at, fs = filesystem(df.sparkSession, df._settled)
    fs.delete(at, True)


def version(spark: SparkSession, paths: list[str]) -> tuple:
    """Length and time of change of files or folders: whether something derived from them still holds."""
    out = []
    for path in paths:
        at, fs = filesystem(spark, path)
        out.append((path, fs.getContentSummary(at).getLength(), fs.getFileStatus(at).getModificationTime()))
    return tuple(out)
