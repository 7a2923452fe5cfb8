"""Diversity, profiles, agreement, audit statistics and sampling designs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def indices(df: DataFrame, column: str) -> DataFrame:
    """Groups, entropy in nats, normalised entropy (null for one group) and concentration of a column's values."""
    c = df.where(F.col(column).isNotNull()).groupBy(column).agg(F.count(F.lit(1)).alias("n"))
    c = c.agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("total"), F.sum(F.col("n") * F.ln("n")).alias("nl"), F.sum(F.col("n") * F.col("n")).alias("sq"))
    h = F.ln("total") - F.col("nl") / F.col("total")
    return c.select("k", "total", F.round(h, 6).alias("h"), F.when(F.col("k") > 1, F.round(h / F.ln("k"), 6)).alias("h_norm"), F.round(F.col("sq") / (F.col("total") * F.col("total")), 6).alias("hhi"))


def compare(named: dict[str, tuple[DataFrame, str]]) -> DataFrame:
    out = None
    for name, (df, column) in named.items():
        row = indices(df, column).select(F.lit(name).alias("corpus"), "*")
        out = row if out is None else out.union(row)
    return out


def fill_rate(df: DataFrame, columns: list[str]) -> DataFrame:
    """Share of rows with a value, for each column, in one pass."""
    row = df.agg(*[F.avg(F.col(c).isNotNull().cast("int")).alias(c) for c in columns])
    return row.select(F.explode(F.array(*[F.struct(F.lit(c).alias("field"), F.round(c, 6).alias("rate")) for c in columns])).alias("r")).select("r.*")


def coverage(df: DataFrame, reference: DataFrame, key: str) -> DataFrame:
    ref = reference.select(key).distinct()
    got = ref.join(df.select(key).distinct().withColumn("cf_in", F.lit(1)), key, "left")
    return got.agg(F.count("cf_in").alias("covered"), F.count(F.lit(1)).alias("total"), F.round(F.count("cf_in") / F.count(F.lit(1)), 6).alias("rate"))


def exact_interval(k: int, n: int, confidence: float = 0.95) -> tuple[float, float]:
    """Bounds of a binomial share by bisection on exact tails."""

    def tail(p: float, low: int, high: int) -> float:
        logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(low, high + 1)]
        return math.fsum(map(math.exp, logs))

    def solve(f, up: bool) -> float:
        a, b = 1e-12, 1 - 1e-12
        for _ in range(80):
            m = (a + b) / 2
            if (f(m) < (1 - confidence) / 2) == up:
                a = m
            else:
                b = m
        return (a + b) / 2

    low = 0.0 if k == 0 else solve(lambda p: tail(p, k, n), True)
    high = 1.0 if k == n else solve(lambda p: tail(p, 0, k), False)
    return low, high


def cohen_kappa(ratings: DataFrame) -> DataFrame:
    """Kappa for each pair of raters of (item, rater, verdict), and the pair's share of agreement."""
    a = ratings.select("item", F.col("rater").alias("ra"), F.col("verdict").alias("va"))
    b = ratings.select("item", F.col("rater").alias("rb"), F.col("verdict").alias("vb"))
    both = a.join(b, "item").where("ra < rb")
    n = both.groupBy("ra", "rb").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("va") == F.col("vb")).cast("int")).alias("same"))
    ma = both.groupBy("ra", "rb", F.col("va").alias("v")).agg(F.count(F.lit(1)).alias("na"))
    mb = both.groupBy("ra", "rb", F.col("vb").alias("v")).agg(F.count(F.lit(1)).alias("nb"))
    chance = ma.join(mb, ["ra", "rb", "v"]).groupBy("ra", "rb").agg(F.sum(F.col("na") * F.col("nb")).alias("cross"))
    joined = n.join(chance, ["ra", "rb"], "left").withColumn("pe", F.coalesce("cross", F.lit(0)) / (F.col("n") * F.col("n"))).withColumn("po", F.col("same") / F.col("n"))
    return joined.select("ra", "rb", "n", F.round("po", 6).alias("agreement"), F.round(F.try_divide(F.col("po") - F.col("pe"), 1 - F.col("pe")), 6).alias("kappa"))


def fleiss_kappa(ratings: DataFrame) -> DataFrame:
    """Kappa of many raters over items that all of them rated."""
    per = ratings.groupBy("item", "verdict").agg(F.count(F.lit(1)).alias("n"))
    item = per.groupBy("item").agg(F.sum("n").alias("raters"), F.sum(F.col("n") * F.col("n")).alias("sq"))
    agree = item.agg(F.count(F.lit(1)).alias("items"), F.avg((F.col("sq") - F.col("raters")) / (F.col("raters") * (F.col("raters") - 1))).alias("po"), F.sum("raters").alias("total"))
    share = per.groupBy("verdict").agg(F.sum("n").alias("n")).agg(F.sum(F.col("n") * F.col("n")).alias("sq"))
    row = agree.crossJoin(F.broadcast(share)).withColumn("pe", F.col("sq") / (F.col("total") * F.col("total")))
    return row.select("items", F.round("po", 6).alias("agreement"), F.round("pe", 6).alias("chance"), F.round(F.try_divide(F.col("po") - F.col("pe"), 1 - F.col("pe")), 6).alias("kappa"))


#: Sample size of a stratum of n items, as Spark and DuckDB SQL.
TIER_SQL = """cast(case when n <= 5 then n when n <= 20 then greatest(5, ceil(n * 0.5)) when n <= 100 then greatest(10, ceil(n * 0.3))
    when n <= 500 then greatest(30, ceil(n * 0.15)) else least(120, greatest(75, ceil(n * 0.08))) end as bigint)"""


def tiers(df: DataFrame, grp: str) -> DataFrame:
    return df.groupBy(grp).agg(F.count(F.lit(1)).alias("n")).withColumn("take", F.expr(TIER_SQL))


def tiered_sample(df: DataFrame, grp: str, item: str, seed: str = "0") -> DataFrame:
    """The stratum's share of items, in the order of md5(item, seed)."""
    order = Window.partitionBy(grp).orderBy(F.md5(F.concat(F.col(item).cast("string"), F.lit(seed))), item)
    sized = tiers(df, grp).select(grp, "take")
    return df.join(sized, grp).withColumn("cf_r", F.row_number().over(order)).where("cf_r <= take").drop("cf_r", "take")


def neyman(strata: DataFrame, n: int) -> DataFrame:
    """(grp, size, sd) -> take: n shared out by size times deviation, rounded by largest remainders.

    Strata are few; the windows over all of them run in one task.
    """
    every = Window.partitionBy()
    quota = F.col("size") * F.col("sd") / F.sum(F.col("size") * F.col("sd")).over(every) * n
    s = strata.withColumn("quota", F.round(quota, 9)).withColumn("base", F.floor("quota"))
    s = s.withColumn("left", F.lit(n) - F.sum("base").over(every)).withColumn("place", F.row_number().over(Window.partitionBy().orderBy(F.desc(F.round(F.col("quota") - F.col("base"), 9)), "grp")))
    return s.select("grp", "size", (F.col("base") + F.when(F.col("place") <= F.col("left"), 1).otherwise(0)).cast("long").alias("take"))


def stratified_estimate(strata: DataFrame) -> DataFrame:
    """(size, taken, right) by stratum -> weighted share and its variance."""
    p = F.col("right") / F.col("taken")
    w = F.col("size") / F.sum("size").over(Window.partitionBy())
    s = strata.withColumn("wp", w * p).withColumn("wv", w * w * (1 - F.col("taken") / F.col("size")) * p * (1 - p) / F.greatest(F.col("taken") - 1, F.lit(1)))
    return s.agg(F.round(F.sum("wp"), 6).alias("estimate"), F.round(F.sum("wv"), 9).alias("variance"))
