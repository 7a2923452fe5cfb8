"""Clusters of reused functions over groups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockflow.config import FUNCTION_TAU, FeatureConfig
from blockflow.operators import features, flowvec, similarity
from blockflow.session import materialize

#: Function numbers of a sample stay below this in a function's id.
SPREAD = 10_000_000


def function_id():
    return F.col("sample_id") * SPREAD + F.col("func_id")


def function_frame(func: DataFrame, cfg: FeatureConfig = FeatureConfig(), min_blocks: int = 3, unique_ids: bool = False) -> DataFrame:
    """Vectors of the non-trivial functions with id; unique_ids takes func_id itself."""
    return as_functions(flowvec.build(func, min_blocks=min_blocks), cfg, unique_ids)


def as_functions(flows: DataFrame, cfg: FeatureConfig = FeatureConfig(), unique_ids: bool = False) -> DataFrame:
    """Function vectors with id of flow vectors."""
    return features.function_vectors(flows, cfg).withColumn("id", F.col("func_id").cast("long") if unique_ids else function_id())


def cluster_functions(vectors: DataFrame, tau: float = FUNCTION_TAU, gamma: float = 5.0) -> DataFrame:
    """(id, root) over a function frame, by search-and-prune on the lossless grid."""
    return similarity.search_and_prune(vectors.select("id", "shape", "cls", "vec_digest"), tau, gamma)


def placed(vectors: DataFrame, roots: DataFrame) -> DataFrame:
    return vectors.select("id", "sample_id", "grp").join(roots, "id")


def clusters(members: DataFrame, scope: str = "groups") -> DataFrame:
    """cluster_id, size, n_samples, n_groups of clusters over groups, over samples, or of any two functions."""
    c = members.groupBy(F.col("root").alias("cluster_id")).agg(F.count(F.lit(1)).alias("size"), F.count_distinct("sample_id").alias("n_samples"), F.count_distinct("grp").alias("n_groups"))
    return c.where({"groups": "n_groups >= 2", "samples": "n_samples >= 2", "any": "size >= 2"}[scope])


def distribution(members: DataFrame) -> DataFrame:
    """Each cluster's share of groups: a map, the preferred group, impurity and entropy."""
    n = members.groupBy("root", "grp").agg(F.count(F.lit(1)).alias("n"))
    c = n.groupBy(F.col("root").alias("cluster_id")).agg(F.sum("n").alias("size"), F.count(F.lit(1)).alias("n_groups"), F.array_sort(F.collect_list(F.struct("grp", "n"))).alias("g"), F.max_by("grp", F.struct("n", "grp")).alias("top_group"), F.sum(F.col("n") * F.col("n")).alias("sq"), F.sum(F.col("n") * F.ln("n")).alias("nl"))
    return c.select("cluster_id", "size", "n_groups", F.map_from_entries("g").alias("by_group"), "top_group", F.round(1 - F.col("sq") / (F.col("size") * F.col("size")), 6).alias("impurity"), F.round(F.ln("size") - F.col("nl") / F.col("size"), 6).alias("entropy"))


def representative(members: DataFrame, func: DataFrame) -> DataFrame:
    """Of each cluster the function with the smallest id: its address, digest, flow graph as an edge list, and a summary.

    func: id, sample_id, func_id, grp, blocks, func_digest.
    """
    first = members.groupBy(F.col("root").alias("cluster_id")).agg(F.min("id").alias("id"))
    picked = func.join(first, "id")
    flows = flowvec.build(picked.withColumn("grp", F.struct("grp", "cluster_id", "id", "func_digest", flowvec.edge_list().alias("flow"))))
    kept = flows.select("grp.cluster_id", "grp.id", "sample_id", F.col("grp.grp").alias("grp"), F.concat_ws(":", "sample_id", "func_id").alias("address"), "grp.func_digest", "n_blocks", "n_edges", "grp.flow", "omega")
    return kept.withColumn("summary", F.format_string("%d blocks, %d edges, %d edge mass", "n_blocks", "n_edges", "omega")).drop("omega")


def size_histogram(members: DataFrame) -> DataFrame:
    return clusters(members, "any").groupBy("size").agg(F.count(F.lit(1)).alias("n_clusters"))


def inter_intra(members: DataFrame) -> DataFrame:
    """Clusters and functions within one group and across groups."""
    kind = F.when(F.col("n_groups") >= 2, "inter").otherwise("intra")
    return clusters(members, "any").groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n_clusters"), F.sum("size").alias("n_functions"))


def group_network(members: DataFrame) -> DataFrame:
    """Pairs of groups with the clusters they share and the Jaccard similarity of their cluster sets."""
    g = members.select("root", "grp").distinct()
    size = g.groupBy("grp").agg(F.count(F.lit(1)).alias("n"))
    shared = g.alias("a").join(g.alias("b"), "root").where("a.grp < b.grp").groupBy(F.col("a.grp").alias("grp_a"), F.col("b.grp").alias("grp_b")).agg(F.count(F.lit(1)).alias("shared"))
    sized = shared.join(F.broadcast(size.select(F.col("grp").alias("grp_a"), F.col("n").alias("na"))), "grp_a").join(F.broadcast(size.select(F.col("grp").alias("grp_b"), F.col("n").alias("nb"))), "grp_b")
    return sized.select("grp_a", "grp_b", "shared", F.round(F.col("shared") / (F.col("na") + F.col("nb") - F.col("shared")), 6).alias("jaccard"))


def lineage(members: DataFrame, times: DataFrame) -> DataFrame:
    """The group that shows a cluster first, and how many days after it each adopter follows. times: id, first_seen."""
    seen = members.join(times, "id").groupBy("root", "grp").agg(F.min("first_seen").alias("seen"))
    w = Window.partitionBy("root").orderBy("seen", "grp")
    made = seen.withColumn("first_grp", F.first("grp").over(w)).withColumn("first_seen", F.first("seen").over(w)).withColumn("place", F.row_number().over(w)).withColumn("after_previous", F.datediff("seen", F.lag("seen").over(w)))
    return made.select(F.col("root").alias("cluster_id"), "grp", "first_grp", F.datediff("seen", "first_seen").alias("lag_days"), "after_previous", "place")


def lookup(new: DataFrame, library: DataFrame, tau: float = FUNCTION_TAU, gamma: float = 5.0) -> DataFrame:
    """Matches of new functions against a library of distinct vectors: (id, lib_id, s). Both: id, shape, cls.

    Ids of both sides may clash, so a match is told by its side: new functions meet the library's cells and not each other.
    """
    heads = new.select((-F.col("id") - 1).alias("id"), "shape", "cls")
    found = similarity.grid_between(heads, library.select("id", "shape", "cls"), tau, gamma)
    return found.select((-F.col("id_a") - 1).alias("id"), F.col("id_b").alias("lib_id"), "s")
