"""Sample deduplication end to end, its report, prefilter and incremental mode."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockflow.config import SAMPLE_TAU, FeatureConfig
from blockflow.operators import features, flowvec, similarity
from blockflow.operators.components import connected_components
from blockflow.session import materialize


def sample_frame(func: DataFrame, calls: DataFrame, cfg: FeatureConfig = FeatureConfig()) -> DataFrame:
    """id, shape, cls, vec_digest of every sample that has functions."""
    return sample_frame_of(flowvec.build(func), calls, cfg)


def sample_frame_of(flows: DataFrame, calls: DataFrame, cfg: FeatureConfig = FeatureConfig()) -> DataFrame:
    """The same of flow vectors, which should be written ones, as each hop reads them again."""
    return features.sample_vectors(flows, calls, cfg).withColumnRenamed("sample_id", "id")


def pairs_of(vectors: DataFrame, cfg: FeatureConfig = FeatureConfig(), tau: float = SAMPLE_TAU) -> tuple[DataFrame, DataFrame]:
    """Accepted pairs between distinct vectors, and (id, head) of all."""
    heads, members = similarity.collapse(vectors.select("id", "shape", "cls", "vec_digest"))
    heads, members = materialize(heads, "heads"), materialize(members, "members")
    return materialize(similarity.grid_pairs(heads, tau, cfg.gamma, cfg.metric, wide=True), "pairs"), members


def roots_of(pairs: DataFrame, members: DataFrame) -> DataFrame:
    roots = connected_components(pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")))
    return members.join(roots, members["head"] == roots["node"], "left").select("id", F.coalesce("root", "head").alias("root"))


def within_groups(pairs: DataFrame, members: DataFrame, grp: DataFrame) -> DataFrame:
    """(id, root) of merging inside groups only: a pair counts where both sides occur in a group, and links its members there.

    members: id, head; grp: id, grp. A vector's members in a group stand for it by the smallest id.
    """
    g = members.join(grp, "id")
    reps = g.groupBy("grp", "head").agg(F.min("id").alias("rep"))
    a, b = reps.toDF("grp", "id_a", "a"), reps.toDF("grp", "id_b", "b")
    links = pairs.select("id_a", "id_b").join(a, "id_a").join(b, ["grp", "id_b"]).select("a", "b")
    roots = connected_components(links)
    placed = g.join(reps, ["grp", "head"])
    return placed.join(roots, placed["rep"] == roots["node"], "left").select("id", F.coalesce("root", "rep").alias("root"))


def keep_representatives(roots: DataFrame, order: DataFrame) -> DataFrame:
    """id, root and kept: of each cluster the one with the smallest (first_seen, digest, id). order: id, first_seen, digest."""
    best = roots.join(order, "id").groupBy("root").agg(F.min_by("id", F.struct("first_seen", "digest", "id")).alias("keeper"))
    return roots.join(best, "root").select("id", "root", (F.col("id") == F.col("keeper")).alias("kept"))


def report(kept: DataFrame, samples: DataFrame) -> DataFrame:
    """Samples, kept, removed and their share, groups before and after. samples: id, grp."""
    j = samples.join(kept, "id", "left").withColumn("stays", F.coalesce("kept", F.lit(True)))
    n = F.count(F.lit(1))
    gone = F.sum((~F.col("stays")).cast("int")).cast("long")
    return j.agg(n.alias("n"), (n - gone).alias("n_kept"), gone.alias("n_removed"), F.round(gone / F.count("kept"), 6).alias("share_analysable"), F.round(gone / n, 6).alias("share_corpus"), F.count_distinct("grp").alias("groups_before"), F.count_distinct(F.when(F.col("stays"), F.col("grp"))).alias("groups_after"))


def prefilter(pairs: DataFrame, tau: float, verify: Column) -> DataFrame:
    """Pairs that pass the cut and then a costlier test given as an expression over the pair."""
    return pairs.where(F.col("s") >= tau).where(verify)


def increment(new: DataFrame, index: DataFrame, roots: DataFrame, cfg: FeatureConfig, tau: float = SAMPLE_TAU, axes: list | None = None) -> tuple[DataFrame, DataFrame]:
    """(index, roots) after a batch: only new vectors are compared, with each other and with the index.

    new: id, shape, cls, vec_digest; index: the same columns of the distinct vectors so far; roots: (id, root) so far.
    The grid's axes may be given, so that batches needn't look for them.
    """
    batch = new.groupBy("vec_digest").agg(F.min_by(F.struct("id", "shape", "cls"), "id").alias("v")).select("v.*", "vec_digest")
    fresh = materialize(batch.join(index.select("vec_digest"), "vec_digest", "left_anti").select("id", "shape", "cls", "vec_digest"), "fresh")
    every = index.unionByName(fresh)
    same = new.select("id", "vec_digest").join(every.select("vec_digest", F.col("id").alias("head")), "vec_digest").where("id <> head").select(F.col("head").alias("a"), F.col("id").alias("b"))
    found = similarity.grid_between(fresh, every, tau, cfg.gamma, cfg.metric, wide=True, axes=axes).where("id_a < id_b").select(F.col("id_a").alias("a"), F.col("id_b").alias("b"))
    # old components take part by their roots alone
    links = same.union(found).join(roots.toDF("a", "ra"), "a", "left").join(roots.toDF("b", "rb"), "b", "left").select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b"))
    merged = connected_components(links).toDF("node", "next")
    known = roots.union(new.select("id", F.col("id").alias("root")))
    return every, materialize(known.join(merged, known["root"] == merged["node"], "left").select("id", F.coalesce("next", "root").alias("root")), "roots")
