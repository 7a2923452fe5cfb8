"""The baseline that the fingerprints are held against: context-triggered piecewise hashing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockflow.operators.alias import edit_ratio

ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
#: Pairs that the all-pairs comparison may list.
CAP = 2_000_000


def signature_sql(text: str, block: int = 16) -> str:
    """A character for each run of words that ends where a word's hash is 0 modulo `block`; inside the row."""
    code = lambda x, n: f"pmod(cast(conv(substring(md5({x}), 1, 8), 16, 10) as bigint), {n})"
    marked = f"transform(filter(split({text}, '\\\\s+'), t -> t <> ''), t -> if({code('t', block)} = 0, concat(t, chr(1)), t))"
    return f"array_join(transform(filter(split(array_join({marked}, ' '), chr(1)), c -> c <> ''), c -> substring('{ALPHABET}', cast({code('c', 64)} + 1 as int), 1)), '')"


def fuzzy_hash(df: DataFrame, block: int = 16) -> DataFrame:
    """id, signature of (id, text)."""
    return df.where("text is not null").select("id", F.expr(signature_sql("text", block)).alias("signature"))


def fuzzy_pairs(hashed: DataFrame, cut: float = 80.0, every: str = "ngram", cap: int = CAP) -> DataFrame:
    """(id_a, id_b, score) of distinct signatures whose edit ratio reaches the cut; equal signatures stand under their smallest id.

    `every` is ngram (only signatures with seven characters in a row in common are compared) or all (every pair, refused
    above a cap).
    """
    heads = hashed.groupBy("signature").agg(F.min("id").alias("id"))
    if every == "all":
        n = heads.count()
        if n * (n - 1) // 2 > cap:
            raise ValueError(f"{n} signatures have too many pairs to compare them all")
        pairs = heads.toDF("x", "id_a").crossJoin(heads.toDF("y", "id_b")).where("id_a < id_b")
    else:
        grams = heads.select("id", F.explode(F.expr("if(length(signature) < 7, array(), array_distinct(transform(sequence(1, length(signature) - 6), i -> substring(signature, i, 7))))")).alias("g"))
        shared = grams.toDF("id_a", "g").join(grams.toDF("id_b", "g"), "g").where("id_a < id_b").select("id_a", "id_b").distinct()
        pairs = shared.join(heads.toDF("x", "id_a"), "id_a").join(heads.toDF("y", "id_b"), "id_b")
    return pairs.where(F.least(F.length("x"), F.length("y")) * 100 >= cut * F.greatest(F.length("x"), F.length("y"))).withColumn("score", edit_ratio(F.col("x"), F.col("y"))).where(F.col("score") >= cut).select("id_a", "id_b", "score")
