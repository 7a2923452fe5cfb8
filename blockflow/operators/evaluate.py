"""Truth sets by mutation, pair measures, threshold sweeps and the seventeen configurations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockflow.config import FeatureConfig
from blockflow.operators.components import connected_components

#: The paper's cuts, and two lower ones of ours.
TAUS = [0.9, 0.95, 0.99, 0.999, 0.9999, 0.99999, 0.999999]


def _cfg(representation: str, shape: str, semantic: bool, weight: bool, metric: str) -> FeatureConfig:
    return FeatureConfig(representation=representation, shape=shape, semantic=semantic, size_weight=weight, metric=metric)


#: The ablation matrix.
CONFIGS = {
    "B1": _cfg("string", "centroid", False, False, "cosine"), "B2": _cfg("string", "xy", False, False, "cosine"), "B3": _cfg("string", "xyz", False, False, "cosine"),
    "N1": _cfg("numeric", "centroid", False, False, "cosine"), "N2": _cfg("numeric", "xy", False, False, "cosine"), "N3": _cfg("numeric", "xyz", False, False, "cosine"),
    "O1": _cfg("string", "xy", True, False, "cosine"), "O2": _cfg("string", "xyz", True, False, "cosine"), "O3": _cfg("numeric", "xy", True, False, "cosine"), "O4": _cfg("numeric", "xyz", True, False, "cosine"),
    "W1": _cfg("numeric", "centroid", False, True, "cosine"), "W2": _cfg("numeric", "xy", True, True, "cosine"), "W3": _cfg("numeric", "xyz", True, True, "cosine"),
    "H1": _cfg("numeric", "xy", True, False, "hybrid"), "H2": _cfg("numeric", "xyz", True, False, "hybrid"), "H3": _cfg("numeric", "xy", True, True, "hybrid"), "H4": _cfg("numeric", "xyz", True, True, "hybrid"),
}
#: Transitions that show one component each.
COMPONENTS = {"numeric": ("B1", "N1"), "classes": ("N2", "O3"), "size": ("O3", "W2"), "hybrid": ("O3", "H1"), "depth": ("B2", "B3")}
PATH = ["B1", "N1", "O3", "W2", "H3"]


#: The published design: isolated samples, groups of two and more, and how many isolated ones are hard negatives.
ISOLATED, GROUPS, HARD = 85, 136, 40


def group_sizes(groups: int, base: int, spread: int, small: bool) -> list[int]:
    """Sizes of the duplicate groups, few of them large."""
    if small:
        return [2 + k % 5 for k in range(1, groups + 1)]
    return [base + int(spread * ((k - 1) / (groups - 1)) ** 10) - (k in (groups - 2, groups - 1)) for k in range(1, groups + 1)]


def copy_counts(isolated: int = ISOLATED, groups: int = GROUPS, small: bool = False, hard: int = HARD) -> list[int]:
    """For each base by rank how many samples are copied from it; none where a hard negative stands in its place."""
    return [0] * hard + [1] * (isolated - hard) + group_sizes(groups, 2, 67, small)


def _extra(made: DataFrame, digest: Column) -> DataFrame:
    """The helper that is appended to some copies: a function of two blocks."""
    zero = "array(1L, 0L, 0L, 0L, 0L, 0L, 0L, 0L, 0L)"
    blocks = f"array(named_struct('n', 1L, 'a', 'h', 'b', 'x', 'cls', {zero}), named_struct('n', 1L, 'a', 'i', 'b', 'y', 'cls', {zero}))"
    return made.where("last and op = 4").withColumn("func_id", F.col("func_id") + 1).withColumn("blocks", F.expr(blocks)).withColumn("func_digest", digest)


def truth_set(func: DataFrame, isolated: int = ISOLATED, groups: int = GROUPS, small: bool = False, hard: int = HARD, order: str = "md5") -> DataFrame:
    """func frame of base documents and mutated copies, with the truth group in grp; sample_id becomes base * 100 + copy.

    Bases are documents with three functions of three blocks at least, one per distinct text, by md5 (`order` md5) or by their
    number of functions first (size). Copies rename, pad a block, swap two neighbouring blocks, edit a constant or append a
    helper of two blocks, by copy number; every copy has digests of its own. A hard negative is the base of a group with one
    more real function, of an isolated document, whose place it takes; it is a group of its own, with copy number 99.
    """
    stats = func.groupBy("sample_id").agg(
        F.sum((F.size("blocks") >= 3).cast("int")).alias("big"), F.count(F.lit(1)).alias("n_func"), F.max("func_id").alias("top_func"),
        F.md5(F.concat_ws("|", F.array_sort(F.collect_list(F.concat_ws(":", F.lpad(F.col("func_id").cast("string"), 9, "0"), "func_digest"))))).alias("text"),
    )
    bases = stats.where("big >= 3").groupBy("text").agg(F.min_by(F.struct("sample_id", "n_func", "top_func"), "sample_id").alias("b")).select("b.*").withColumn("o", F.md5(F.col("sample_id").cast("string")))
    by = [F.desc("n_func"), "o"] if order == "size" else ["o"]
    # isolated + groups rows of a few numbers in the end; the order is a top-k
    top = bases.orderBy(*by).limit(isolated + groups).withColumn("rank", F.row_number().over(Window.orderBy(*by)))
    table = F.array(*[F.lit(n) for n in copy_counts(isolated, groups, small, hard)])
    copies = top.withColumn("k", F.get(table, F.col("rank") - 1)).where("k > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), F.col("k") - 1))).select("sample_id", "rank", "copy", "n_func")
    rows = func.join(F.broadcast(copies), "sample_id").withColumn("op", F.when(F.col("copy") == 0, -1).otherwise(F.col("copy") % 5))
    target = F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", "sample_id", "copy")), 1, 6), 16, 10).cast("long"), F.col("n_func"))
    place = F.row_number().over(Window.partitionBy("sample_id", "copy").orderBy("func_id")) - 1
    rows = rows.withColumn("place", place).withColumn("hit", (target == F.col("place"))).withColumn("last", F.col("place") == F.col("n_func") - 1)
    padded = F.transform("blocks", lambda x, i: F.when(i == 0, F.struct((x["n"] + 1).alias("n"), x["a"].alias("a"), x["b"].alias("b"), F.transform(x["cls"], lambda c, k: c + F.when(k == 8, 1).otherwise(0)).alias("cls"))).otherwise(x))
    swapped = F.when(F.size("blocks") >= 3, F.concat(F.slice("blocks", 2, 1), F.slice("blocks", 1, 1), F.slice("blocks", 3, F.greatest(F.size("blocks") - 2, F.lit(1))))).otherwise(F.col("blocks"))
    blocks = F.when(F.col("hit") & (F.col("op") == 1), padded).when(F.col("hit") & (F.col("op") == 2), swapped).otherwise(F.col("blocks"))
    made = rows.withColumn("blocks", blocks).withColumn("func_digest", F.md5(F.concat_ws(":", "func_digest", "copy")))
    helper = _extra(made, F.md5(F.concat_ws(":", F.lit("helper"), "sample_id", "copy")))
    keep = [(F.col("sample_id") * 100 + F.col("copy")).alias("sample_id"), "func_id", F.col("rank").cast("string").alias("grp"), "blocks", "func_digest"]
    own, donor = top.where(F.col("rank") > isolated).select((F.col("rank") - isolated).alias("rank"), "sample_id", "top_func"), top.where(F.col("rank") <= hard).select("rank", F.col("sample_id").alias("donor"))
    negatives = own.join(donor, "rank").withColumn("copy", F.lit(99))
    whole = func.join(F.broadcast(negatives), "sample_id")
    given = func.withColumnRenamed("sample_id", "donor").where(F.size("blocks") >= 3).join(F.broadcast(negatives), "donor")
    given = given.groupBy("sample_id", "rank", "copy").agg(F.min_by(F.struct("blocks", "func_digest", (F.col("top_func") + 1).alias("at")), "func_id").alias("g")).select("sample_id", "rank", "copy", F.col("g.at").alias("func_id"), "g.blocks", "g.func_digest")
    return made.select(*keep).union(helper.select(*keep)).union(whole.select(*keep)).union(given.select(*keep))


def line_calls(func: DataFrame) -> DataFrame:
    """Call edges of a truth set: each function calls the next one."""
    w = Window.partitionBy("sample_id").orderBy("func_id")
    return func.select("sample_id", F.col("func_id").alias("caller"), F.lead("func_id").over(w).alias("callee")).where("callee is not null")


def sweep(scored: DataFrame, truth: DataFrame, taus: list[float]) -> DataFrame:
    """tau, tp, fp, fn, tn, precision, recall, f1 of all cuts in one pass. scored: id_a, id_b, s. truth: id, grp."""
    n = truth.agg(F.count(F.lit(1)).alias("n"))
    positive = truth.groupBy("grp").agg(F.count(F.lit(1)).alias("k")).agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).alias("p"))
    a, b = truth.toDF("id_a", "grp_a"), truth.toDF("id_b", "grp_b")
    marked = scored.join(a, "id_a").join(b, "id_b").select("s", (F.col("grp_a") == F.col("grp_b")).alias("same"))
    counts = marked.agg(*[F.coalesce(F.sum(((F.col("s") >= t) & F.col("same")).cast("int")), F.lit(0)).cast("long").alias(f"tp{k}") for k, t in enumerate(taus)], *[F.coalesce(F.sum(((F.col("s") >= t) & ~F.col("same")).cast("int")), F.lit(0)).cast("long").alias(f"fp{k}") for k, t in enumerate(taus)])
    rows = counts.crossJoin(n).crossJoin(positive).select("n", "p", F.explode(F.array(*[F.struct(F.lit(t).alias("tau"), F.col(f"tp{k}").alias("tp"), F.col(f"fp{k}").alias("fp")) for k, t in enumerate(taus)])).alias("r")).select("n", "p", "r.*")
    fn = F.col("p") - F.col("tp")
    precision, recall = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", "p")
    f1 = F.try_divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + fn)
    return rows.select("tau", "tp", "fp", fn.alias("fn"), (F.expr("n * (n - 1) div 2") - F.col("tp") - F.col("fp") - fn).alias("tn"), F.round(precision, 6).alias("precision"), F.round(recall, 6).alias("recall"), F.round(f1, 6).alias("f1"))


def closure(pairs: DataFrame) -> DataFrame:
    """All pairs (id_a, id_b, s = 1) inside the components of pairs; for truth sets, whose components are small."""
    roots = connected_components(pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")))
    return roots.toDF("id_a", "root").join(roots.toDF("id_b", "root"), "root").where("id_a < id_b").select("id_a", "id_b", F.lit(1.0).alias("s"))


def pick_threshold(scored: DataFrame, truth: DataFrame) -> DataFrame:
    """The cut with the best F1 among those without a false merge."""
    a, b = truth.toDF("id_a", "grp_a"), truth.toDF("id_b", "grp_b")
    marked = scored.join(a, "id_a").join(b, "id_b").select("s", (F.col("grp_a") == F.col("grp_b")).alias("same"))
    worst = marked.agg(F.coalesce(F.max(F.when(~F.col("same"), F.col("s"))), F.lit(-1.0)).alias("bad"))
    return marked.crossJoin(worst).where("same and s > bad").agg(F.min("s").alias("tau"), F.count(F.lit(1)).alias("tp"))
