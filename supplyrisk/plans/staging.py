"""Cutting lineage with tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, else the context's checkpoint folder, else a local one, on a local
    master only: executors of a cluster do not see the driver's folders."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    sc = spark.sparkContext
    at = sc._jsc.sc().getCheckpointDir()
    if at.isDefined():
        return at.get()
    if sc.master != "local" and not sc.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    local = tempfile.mkdtemp(prefix="supplyrisk-checkpoint-")
    atexit.register(shutil.rmtree, local, ignore_errors=True)
    sc.setCheckpointDir(f"file://{local}")
    return f"file://{local}"


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder on whatever file system its path names."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


class Staged:
    """A DataFrame written to the shared folder; reading it again does no work twice.

    compression: of the files. by: columns to partition the files by."""

    def __init__(self, df: DataFrame, label: str, compression: str | None = None, by: tuple[str, ...] = ()):
        self.spark, self.path = df.sparkSession, f"{shared_dir(df.sparkSession)}/staged-{label}-{uuid.uuid4().hex}"
        schema = df.schema
        writer = df.write
        if compression:
            writer = writer.option("compression", compression)
        if by:
            writer = writer.partitionBy(*by)
        writer.parquet(self.path)
        self.df = self.spark.read.schema(schema).parquet(self.path)

    def drop(self) -> None:
        """Delete the files; only once nothing lazy reads them any more."""
        delete(self.spark, self.path)


def stage(df: DataFrame, label: str) -> DataFrame:
    return Staged(df, label).df


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
