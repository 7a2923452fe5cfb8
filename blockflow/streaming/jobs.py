"""Streams over the events files; timestamps without zone are cast before watermarks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.session import removed_at_exit, shared_dir


def file_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's files as a stream: the table is one file in the folder, or a folder of files."""
    path = f"{sf_dir}/{name}.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    if hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(hadoop).isDirectory():
        return reader.parquet(path)
    return reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return file_stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there into a table in the shared folder, and read it."""
    spark = df.sparkSession
    path = removed_at_exit(spark, f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")
    removed_at_exit(spark, f"{path}-state")
    if mode == "append":
        df.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    else:
        write = lambda batch, _: batch.write.mode("overwrite").parquet(path)
        df.writeStream.outputMode("complete").foreachBatch(write).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def drained_batches(df: DataFrame, found, schema: str) -> DataFrame:
    """Run a stream whose batches go through a function of static frames, and read what came out."""
    spark = df.sparkSession
    path = removed_at_exit(spark, f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")
    removed_at_exit(spark, f"{path}-state")
    # a batch that is run again overwrites its own folder
    write = lambda batch, n: found(batch).write.mode("overwrite").parquet(f"{path}/batch={n}")
    df.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema).parquet(f"{path}/batch=*")
