"""Collection and cleaning: merging, integrity, exact hashes, disputed labels, analysability."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def merge_sources(frames: list[DataFrame], key: str, label: str) -> DataFrame:
    """One row for each key with the labels and sources that name it."""
    both = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), frames)
    return both.groupBy(key).agg(F.array_sort(F.collect_set(label)).alias("labels"), F.count(F.lit(1)).alias("n_records"))


def enrich(df: DataFrame, meta: DataFrame, key: str) -> DataFrame:
    return df.join(meta, key, "left")


def integrity(docs: DataFrame) -> DataFrame:
    """Add digest (recomputed SHA-256) and reason: null for intact documents."""
    reason = F.when(F.col("text").isNull() | (F.col("text") == ""), "empty").when(F.col("n_chars") != F.length("text"), "length")
    return docs.withColumn("digest", F.sha2("text", 256)).withColumn("reason", reason)


def page_integrity(pages: DataFrame) -> DataFrame:
    return pages.withColumn("reason", F.when(F.col("html").isNull() | (F.col("html") == ""), "empty").when(~F.col("html").contains("</html>"), "cut"))


def collapse_exact(df: DataFrame, key: str, order: str) -> DataFrame:
    """The earliest row of each digest and how many it stands for."""
    rest = [c for c in df.columns if c != key]
    return df.groupBy(key).agg(F.min_by(F.struct(*rest), order).alias("r"), F.count(F.lit(1)).alias("copies")).select(key, "r.*", "copies")


def label_conflicts(df: DataFrame, digest: str = "digest", label: str = "grp") -> DataFrame:
    return df.groupBy(digest).agg(F.count_distinct(label).alias("n_labels"), F.count(F.lit(1)).alias("n")).where("n_labels > 1")


def label_impurity(df: DataFrame, digest: str = "digest", label: str = "grp") -> DataFrame:
    """1 - sum p^2 of the labels of each digest, the majority label and its share; ties have no majority."""
    counts = df.groupBy(digest, label).agg(F.count(F.lit(1)).alias("n"))
    best = counts.groupBy(digest).agg(F.sum("n").alias("total"), F.sum(F.col("n") * F.col("n")).alias("squares"), F.max("n").alias("most"), F.max_by(label, F.struct("n", label)).alias("majority"), F.count(F.lit(1)).alias("n_labels"), F.collect_list("n").alias("ns"))
    tie = F.size(F.filter("ns", lambda x: x == F.col("most"))) > 1
    return best.select(digest, "total", "n_labels", F.round(1 - F.col("squares") / (F.col("total") * F.col("total")), 6).alias("impurity"), F.when(~tie, F.col("majority")).alias("majority"), F.round(F.col("most") / F.col("total"), 6).alias("p_max"))


def resolve_labels(df: DataFrame, cut: float = 0.2, digest: str = "digest", label: str = "grp") -> DataFrame:
    """Up to the cut the majority holds; beyond it, and for ties, the label becomes unknown."""
    i = label_impurity(df, digest, label)
    keep = (F.col("impurity") <= cut) & F.col("majority").isNotNull()
    action = F.when(F.col("n_labels") == 1, "none").when(keep, "majority").otherwise("unknown")
    return i.select(digest, "impurity", F.when(keep, F.col("majority")).otherwise("unknown").alias("resolved"), action.alias("action"))


def dispute_rate(resolved: DataFrame) -> DataFrame:
    n = F.count(F.lit(1))
    on = lambda a: F.sum(F.when(F.col("action") == a, 1).otherwise(0)).cast("long")
    return resolved.agg(n.alias("n"), on("majority").alias("kept"), on("unknown").alias("unknown"), F.round(F.avg(F.when(F.col("action") != "none", 1.0).otherwise(0.0)), 6).alias("rate"))


def char_entropy(text: str) -> str:
    """Entropy in bits of a text's characters, as a Spark SQL expression inside its row."""
    chars = f"filter(split({text}, ''), c -> c <> '')"
    return f"aggregate(transform(array_distinct({chars}), c -> size(filter({chars}, x -> x = c)) / length({text})), cast(0 as double), (a, p) -> a - p * log2(p))"


def packed_proxy(text: Column) -> Column:
    """Whether letters are less than half of a text."""
    return F.length(F.regexp_replace(text, r"[^\p{L}]", "")) < 0.5 * F.length(text)


def analysable(df: DataFrame, types: list[str], type_col: str, packed: Column, allow_unpacked: bool = True) -> DataFrame:
    return df.where(F.col(type_col).isin(types) & (~packed if allow_unpacked else F.lit(True)))
