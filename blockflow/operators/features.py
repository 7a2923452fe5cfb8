"""Representations, propagation over call edges and sample vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockflow.config import FeatureConfig
from blockflow.operators import flowvec
from blockflow.operators.vec import l2

#: Digits that propagated values keep, so that sums don't depend on their order.
DIGITS = 9


def shape_of(cfg: FeatureConfig) -> list[str]:
    return {"xy": ["x", "y"], "xyz": ["x", "y", "z"], "centroid": ["x", "y", "z", "w"]}[cfg.shape]


def initial(vectors: DataFrame, cfg: FeatureConfig) -> DataFrame:
    """Node features of hop 0: sample_id, func_id, hop, shape, cls."""
    v = vectors.withColumn("w", F.col("omega").cast("double"))
    if cfg.size_weight:
        v = flowvec.size_weighted(v)
    shape = F.array(*[F.round(k, DIGITS) for k in shape_of(cfg)])
    cls = F.transform("cls", lambda x: x.cast("double")) if cfg.semantic else F.expr("cast(array() as array<double>)")
    return v.select("sample_id", "func_id", F.lit(0).alias("hop"), shape.alias("shape"), cls.alias("cls"))


def _summed(column: str, size: int, how: str):
    total = [F.sum(F.get(column, F.lit(k)).cast("decimal(28,9)")).cast("double") for k in range(size)]
    return F.array(*[F.round(t / F.count(F.lit(1)), DIGITS) if how == "mean" else t for t in total]) if size else F.expr("cast(array() as array<double>)")


def propagate(nodes: DataFrame, calls: DataFrame, cfg: FeatureConfig) -> DataFrame:
    """Add hops 1..rounds: what a node's neighbours had one hop before, summed (or averaged); zeros without neighbours."""
    n_shape, n_cls = len(shape_of(cfg)), 9 if cfg.semantic else 0
    ends = calls.select("sample_id", "caller", "callee")
    if cfg.neighbours in ("in", "both"):
        turned = ends.select("sample_id", F.col("callee").alias("caller"), F.col("caller").alias("callee"))
        ends = turned if cfg.neighbours == "in" else ends.union(turned).distinct()
    out, now = nodes, nodes
    for hop in range(1, cfg.rounds + 1):
        said = now.select("sample_id", F.col("func_id").alias("callee"), "shape", "cls")
        got = ends.join(said, ["sample_id", "callee"]).groupBy("sample_id", F.col("caller").alias("func_id")).agg(_summed("shape", n_shape, cfg.hop_agg).alias("shape"), _summed("cls", n_cls, cfg.hop_agg).alias("cls"))
        zero = lambda n: F.array_repeat(F.lit(0.0), n)
        now = nodes.select("sample_id", "func_id").join(got, ["sample_id", "func_id"], "left").select("sample_id", "func_id", F.lit(hop).alias("hop"), F.coalesce("shape", zero(n_shape)).alias("shape"), F.coalesce("cls", zero(n_cls)).alias("cls"))
        out = out.union(now)
    return out


def hashed(nodes: DataFrame, buckets: int = 1024, digits: int = 4) -> DataFrame:
    """String representation: each printed value with its place is a token; cf_t has the tokens' buckets."""
    scale = F.lit(float(10**digits))
    code = lambda t: F.pmod(F.conv(F.substring(F.md5(t), 1, 8), 16, 10).cast("long"), F.lit(buckets))
    tokens = lambda c, tag: F.transform(c, lambda x, i: code(F.concat_ws(":", F.lit(tag), F.col("hop").cast("string"), i.cast("string"), F.floor(x * scale + 0.5).cast("long").cast("string"))))
    return nodes.withColumn("cf_t", F.concat(tokens("shape", "s"), tokens("cls", "c")))


def hashed_samples(nodes: DataFrame, buckets: int = 1024, digits: int = 4) -> DataFrame:
    """A count vector over buckets for each sample."""
    items = hashed(nodes, buckets, digits).select("sample_id", "func_id", F.explode("cf_t").alias("b"))
    n = nodes.groupBy("sample_id").agg(F.count_distinct("func_id").alias("n_nodes"))
    counts = items.groupBy("sample_id", "b").agg(F.count(F.lit(1)).cast("double").alias("n"))
    maps = counts.groupBy("sample_id").agg(F.map_from_entries(F.collect_list(F.struct("b", "n"))).alias("m"))
    vec = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(buckets - 1).cast("long")), lambda k: F.coalesce(F.try_element_at("m", k), F.lit(0.0)))
    return maps.join(n, "sample_id").select("sample_id", "n_nodes", F.expr("cast(array() as array<double>)").alias("shape"), vec.alias("cls"))


def concatenated(nodes: DataFrame, order: str = "func_id") -> DataFrame:
    """Sample vectors: shape and class parts of all hops of all nodes.

    Nodes come in function order, or in the order of their content, which outlives a reordering of functions. A sample's
    nodes meet in one row here, which the layout asks for; `pooled` doesn't.
    """
    if order == "content":
        first = F.min(F.when(F.col("hop") == 0, F.struct("cls", "shape"))).over(Window.partitionBy("sample_id", "func_id"))
        nodes = nodes.withColumn("cf_by", F.struct(first.alias("content"), "func_id"))
    else:
        nodes = nodes.withColumn("cf_by", F.col("func_id"))
    ordered = F.array_sort(F.collect_list(F.struct("cf_by", "hop", "shape", "cls")))
    made = nodes.groupBy("sample_id").agg(ordered.alias("cf_n"), F.count_distinct("func_id").alias("n_nodes"))
    return made.select("sample_id", "n_nodes", F.flatten(F.col("cf_n.shape")).alias("shape"), F.flatten(F.col("cf_n.cls")).alias("cls"))


def pooled(nodes: DataFrame, cfg: FeatureConfig) -> DataFrame:
    """Sample vectors of a fixed length: node features summed by hop."""
    n_shape, n_cls = len(shape_of(cfg)), 9 if cfg.semantic else 0
    by_hop = nodes.groupBy("sample_id", "hop").agg(_summed("shape", n_shape, "sum").alias("shape"), _summed("cls", n_cls, "sum").alias("cls"), F.count(F.lit(1)).alias("n"))
    made = by_hop.groupBy("sample_id").agg(F.array_sort(F.collect_list(F.struct("hop", "shape", "cls"))).alias("cf_n"), F.max("n").alias("n_nodes"))
    return made.select("sample_id", "n_nodes", F.flatten(F.col("cf_n.shape")).alias("shape"), F.flatten(F.col("cf_n.cls")).alias("cls"))


def sample_vectors(vectors: DataFrame, calls: DataFrame, cfg: FeatureConfig) -> DataFrame:
    """sample_id, n_nodes, shape (unit length for the hybrid metric), cls, vec_digest."""
    nodes = propagate(initial(vectors, cfg), calls, cfg)
    if cfg.representation == "string":
        made = hashed_samples(nodes)
    else:
        made = pooled(nodes, cfg) if cfg.layout == "pooled" else concatenated(nodes, cfg.node_order)
    if cfg.metric in ("hybrid", "gauss"):
        made = made.withColumn("shape", l2("shape"))
    return made.withColumn("vec_digest", F.md5(F.to_json(F.struct(F.transform("shape", lambda x: F.round(x, 10)), F.transform("cls", lambda x: F.round(x, 6))))))


def function_vectors(vectors: DataFrame, cfg: FeatureConfig) -> DataFrame:
    """Function mode: raw shape, class part of unit length; id is (sample_id, func_id)."""
    v = flowvec.size_weighted(vectors) if cfg.size_weight else vectors
    shape = F.array(*[F.round(k, DIGITS) for k in shape_of(cfg)])
    made = v.withColumn("shape", shape).withColumn("cls", l2(F.transform("cls", lambda x: x.cast("double"))))
    return made.select("sample_id", "func_id", "grp", "n_blocks", "shape", "cls", F.md5(F.to_json(F.struct("shape", F.transform("cls", lambda x: F.round(x, 10))))).alias("vec_digest"))
