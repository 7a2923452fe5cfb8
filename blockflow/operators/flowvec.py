"""Flow vectors: shape and activity of a function's blocks along its flow edges, all inside the row.

Flow edges: to the next block; to the next block with the same forward key; to the previous block with the same back key;
each once. An edge counts both of its ends, so every sum over edges is a sum over blocks weighted by the ends that lie in
it. Loop depth of a block is the number of back edges around it. A function without edges has zeros. The work grows with the
blocks of a function, times the logarithm that sorting takes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Places of the blocks with the same key before and after each block, -1 where there is none, in block order. Sorting by
#: (key, place) brings equal keys together, so this is n log n whatever the length of a function.
_NEAR = """transform(sort_array(transform({sorted}, (x, k) -> named_struct('i', x.i,
    'before', if(k > 0 and get({sorted}, k - 1).key <=> x.key, get({sorted}, k - 1).i, -1),
    'after', if(get({sorted}, k + 1) is not null and get({sorted}, k + 1).key <=> x.key, get({sorted}, k + 1).i, -1)))), x -> struct(x.before, x.after))"""

#: A block's out-degree and edge ends follow from its neighbours: the next block, the one ahead with its forward key unless
#: that is the next block, the one behind with its back key, and the same seen from their ends.
_OUT = "if(i + 1 < size(blocks), 1, 0) + if(cf_a[i].after > i + 1, 1, 0) + if(cf_b[i].before >= 0, 1, 0)"
_IN = "if(i > 0, 1, 0) + if(cf_a[i].before >= 0 and cf_a[i].before < i - 1, 1, 0) + if(cf_b[i].after >= 0, 1, 0)"

#: One pass over the blocks. Depth of a block is the number of back edges that began at or before it and haven't ended.
_START = "named_struct('omega', 0L, 'xn', 0L, 'yn', 0L, 'zn', 0L, 'outs', 0L, 'open', 0L, 'cls', array_repeat(0L, 9))"
_STEP = """named_struct('omega', s.omega + v.ends * v.n, 'xn', s.xn + v.ends * v.n * v.i, 'yn', s.yn + v.ends * v.n * v.outs,
    'zn', s.zn + v.ends * v.n * (s.open + v.opens), 'outs', s.outs + v.outs, 'open', s.open + v.opens - v.closes,
    'cls', zip_with(s.cls, v.cls, (p, q) -> p + v.ends * q))"""


def edge_list() -> Column:
    """The flow edges of `blocks` as text, src-dst with commas, in order; for single functions to be shown."""
    ahead = "transform(blocks, (y, j) -> if(j > i and y.a <=> x.a, j, null))"
    behind = "transform(blocks, (y, j) -> if(j < i and y.b <=> x.b, j, null))"
    ends = f"array_sort(array_distinct(array_compact(array(if(i + 1 < size(blocks), i + 1, null), array_min({ahead}), array_max({behind})))))"
    return F.array_join(F.expr(f"flatten(transform(blocks, (x, i) -> transform({ends}, e -> concat(i, '-', e))))"), ",")


def with_flow(func: DataFrame) -> DataFrame:
    """Replace each block by n, cls, i, outs (out-degree), ends (incident edge ends), opens and closes (back edges)."""
    ordered = lambda key: F.expr(f"sort_array(transform(blocks, (x, i) -> named_struct('key', x.{key}, 'i', i)))")
    placed = func.withColumns({"cf_sa": ordered("a"), "cf_sb": ordered("b")})
    placed = placed.withColumns({"cf_a": F.expr(_NEAR.format(sorted="cf_sa")), "cf_b": F.expr(_NEAR.format(sorted="cf_sb"))})
    full = f"""transform(blocks, (x, i) -> named_struct('n', x.n, 'cls', x.cls, 'i', i, 'outs', {_OUT}, 'ends', {_OUT} + {_IN},
        'opens', if(cf_b[i].after >= 0, 1, 0), 'closes', if(cf_b[i].before >= 0, 1, 0)))"""
    return placed.withColumn("blocks", F.expr(full)).drop("cf_a", "cf_b", "cf_sa", "cf_sb")


def build(func: DataFrame, min_blocks: int = 1, x_offset: float = 0.0, ignore_weight: float = 1.0) -> DataFrame:
    """sample_id, func_id, grp, n_blocks, n_edges, omega, xn, yn, zn, cls, x, y, z; trivial functions go first."""
    kept = with_flow(func.where(F.size("blocks") >= min_blocks))
    summed = kept.select("sample_id", "func_id", "grp", F.size("blocks").alias("n_blocks"), F.expr(f"aggregate(blocks, {_START}, (s, v) -> {_STEP})").alias("cf_s"))
    out = summed.select("sample_id", "func_id", "grp", "n_blocks", F.col("cf_s.outs").cast("int").alias("n_edges"), *[f"cf_s.{k}" for k in ("omega", "xn", "yn", "zn", "cls")])
    if ignore_weight != 1.0:
        out = out.withColumn("cls", F.transform("cls", lambda v, k: F.when(k == 8, v * ignore_weight).otherwise(v).cast("double")))
    part = lambda c: F.coalesce(F.try_divide(F.col(c).cast("double"), F.col("omega").cast("double")), F.lit(0.0))
    return out.withColumns({"x": F.when(F.col("omega") > 0, part("xn") + x_offset).otherwise(0.0), "y": part("yn"), "z": part("zn")})


def centroid(vectors: DataFrame) -> DataFrame:
    """The four numbers (x, y, z, omega) without classes."""
    return vectors.withColumn("centroid", F.array("x", "y", "z", F.col("omega").cast("double")))


def size_weighted(vectors: DataFrame) -> DataFrame:
    """Shape numbers times the number of blocks."""
    return vectors.withColumns({k: F.col(k) * F.col("n_blocks") for k in ("x", "y", "z")})


def drop_trivial(func: DataFrame, min_blocks: int = 3) -> DataFrame:
    return func.where(F.size("blocks") >= min_blocks)


def extraction_report(samples: DataFrame, vectors: DataFrame) -> DataFrame:
    """How many samples gave vectors, and how many none."""
    got = vectors.select("sample_id").distinct().withColumn("cf_ok", F.lit(1))
    return samples.select("sample_id").distinct().join(got, "sample_id", "left").agg(F.count("cf_ok").alias("n_ok"), F.sum(F.when(F.col("cf_ok").isNull(), 1).otherwise(0)).cast("long").alias("n_failed"))
