"""Connected components of a link table by alternating star contractions, without collecting links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockflow.session import materialize


def _both_ways(links: DataFrame) -> DataFrame:
    return links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))


def connected_components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) links -> (node, root) of every node with a link; root is the smallest node of its component.

    A round links every larger neighbour to a node's smallest one, then every smaller neighbour likewise; rounds end when
    the set of links stays as it is. Each round is written to the shared folder, and only two sums reach the driver. Rounds
    grow with the logarithm of the longest path; where `max_rounds` don't settle the links, this fails.
    """
    now = materialize(links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
    seen, settled = None, now.isEmpty()
    for _ in range(max_rounds):
        if settled:
            break
        both = _both_ways(now)
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("m").alias("a"), "b").where("a <> b").distinct()
        under = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        low = under.groupBy("a").agg(F.min("b").alias("m"))
        small = under.join(low, "a").select(F.col("m").alias("a"), "b").union(low.select(F.col("m").alias("a"), F.col("a").alias("b")))
        now = materialize(small.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
        row = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)")).alias("s")).first()
        settled = (row["n"], row["s"]) == seen
        seen = (row["n"], row["s"])
    if not settled:
        raise RuntimeError(f"components aren't settled after {max_rounds} rounds")
    return now.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("root")).union(now.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct())
