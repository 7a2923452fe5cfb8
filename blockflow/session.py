"""Session helpers that only read settings which are fixed at start."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share. Where a local session names none, as in tests, it is a temporary one; a cluster must name one."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    found = spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    made = tempfile.mkdtemp(prefix="blockflow-")
    spark.sparkContext.setCheckpointDir(made)
    return made


def removed_at_exit(spark: SparkSession, path: str) -> str:
    """The path, whose files go when the application ends."""
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def materialize(df: DataFrame, label: str, compression: str = "zstd", partition_by=None) -> DataFrame:
    """Write a frame to the shared folder and read it back, which cuts its lineage.

    The written table is removed when the application ends.
    """
    spark = df.sparkSession
    path = removed_at_exit(spark, f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    writer = df.write.option("compression", compression)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_shuffles(spark: SparkSession) -> None:
    """Let go of the shuffle files of work that is done.

    Spark removes them once the driver's garbage is collected, which a driver with little to do hardly comes to; until then
    the shuffles of all steps of a long job lie on disk together.
    """
    gc.collect()
    spark._jvm.System.gc()
