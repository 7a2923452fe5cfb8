"""Documents in ascending doc_id order over bounded range partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Input bytes, as Spark estimates them, that a range partition holds at most on average.
RANGE_BYTES = 64 << 20


#: Sizes from which Spark's estimate says no more than that it has none.
UNKNOWN = 1 << 58


def estimated_bytes(df: DataFrame, text: str = "text") -> int:
    """Spark's estimate of a frame's bytes; where it has none, the bytes of its texts are summed."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return size if size < UNKNOWN else int(df.agg(F.sum(F.octet_length(text)).alias("n")).first()["n"] or 0)


def ranged(docs: DataFrame, *columns: str) -> DataFrame:
    """The columns of docs, range-partitioned by doc_id and sorted within; rows without a doc_id come first.

    Rows that share a doc_id, or have none, are ranged further by the hash of their text, so that they don't all meet in one
    task.
    """
    picked = docs.select("doc_id", *columns)
    parts = max(int(picked.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-estimated_bytes(picked) // RANGE_BYTES))
    return picked.repartitionByRange(parts, "doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id")
