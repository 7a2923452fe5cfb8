"""Candidates, exact scores, decisions and clusters over vector frames.

A vector frame has id, shape and cls. The hybrid score is cosine(cls) times exp(-gamma * squared shape distance); both
factors are at most 1, so a score of tau bounds the shape distance by sqrt(-ln(tau) / gamma) and the distance of the class
parts at unit length by sqrt(2 (1 - tau)). Cells with these sides on a few coordinates therefore hold every pair in
neighbouring cells, and no pair is lost. The same holds for each part alone and for the cosine of whole vectors.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockflow.operators.components import connected_components
from blockflow.operators.vec import dot, gauss, norm, ratio, squared_distance
from blockflow.session import materialize


def radius(tau: float, gamma: float) -> float:
    return math.sqrt(-math.log(tau) / gamma)


def collapse(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct vectors under their smallest id, and (id, head) of all; equal vectors have similarity 1."""
    heads = vectors.groupBy("vec_digest").agg(F.min_by(F.struct("id", "shape", "cls"), "id").alias("v"))
    members = vectors.select("id", "vec_digest").join(heads.select("vec_digest", F.col("v.id").alias("head")), "vec_digest").select("id", "head")
    return heads.select("v.*"), members


#: What a vector frame has once its norms are known.
READY = ["id", "shape", "cls", "norm_shape", "norm_cls"]


def with_norms(vectors: DataFrame) -> DataFrame:
    """Norms once for each vector, not once for each pair."""
    return vectors.select("id", "shape", "cls", norm(F.col("shape")).alias("norm_shape"), norm(F.col("cls")).alias("norm_cls"))


def _scored(pairs: DataFrame, metric: str, gamma: float) -> DataFrame:
    """id_a, id_b, s_cls, s_shape, s, rounded to 10 digits."""
    staged = pairs.withColumn("p_cls", dot("cls_a", "cls_b"))
    s_cls = F.round(ratio(F.col("p_cls"), F.col("norm_cls_a"), F.col("norm_cls_b")), 10)
    if metric == "cosine":
        joined = lambda x: F.sqrt(F.col(f"norm_shape_{x}") * F.col(f"norm_shape_{x}") + F.col(f"norm_cls_{x}") * F.col(f"norm_cls_{x}"))
        staged = staged.withColumn("p_shape", dot("shape_a", "shape_b"))
        s_shape = F.round(ratio(F.col("p_shape"), F.col("norm_shape_a"), F.col("norm_shape_b")), 10)
        final = F.round(ratio(F.col("p_shape") + F.col("p_cls"), joined("a"), joined("b")), 10)
    else:
        s_shape = F.round(gauss("shape_a", "shape_b", gamma), 10)
        final = {"hybrid": F.round(F.col("s_cls") * F.col("s_shape"), 10), "gauss": F.col("s_shape"), "cls": F.col("s_cls")}[metric]
    staged = staged.withColumn("s_cls", s_cls).withColumn("s_shape", s_shape)
    return staged.withColumn("s", final).select("id_a", "id_b", "s_cls", "s_shape", "s")


#: Vectors of a block of brute force, blocks at least where there are enough vectors, and vectors scored at a time.
BLOCK, LEAST_BLOCKS, AT_ONCE = 4096, 12, 256


def _dense(column: pa.ListArray, width: int) -> np.ndarray:
    at = np.asarray(column.offsets) - column.offsets[0].as_py()
    out = np.zeros((len(at) - 1, width))
    n = np.diff(at)
    out[np.repeat(np.arange(len(n)), n), np.arange(at[-1]) - np.repeat(at[:-1], n)] = np.asarray(column.flatten())
    return out


def _cosines(product: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """As vec.ratio: 0 where one norm is zero, 1 where both are, never above 1; rounded to 10 digits."""
    norms = x[:, None] * y[None, :]
    out = np.minimum(1.0, np.divide(product, norms, out=np.zeros_like(product), where=norms > 0))
    return np.round(np.where((x[:, None] == 0) & (y[None, :] == 0), 1.0, out), 10)


def _apart(x: np.ndarray, y: np.ndarray, gamma: float) -> np.ndarray:
    return np.round(np.exp(-gamma * ((x - y) ** 2).sum(axis=-1)), 10)


def _parts(x: pa.StructArray, y: pa.StructArray, part: str) -> tuple[np.ndarray, np.ndarray]:
    p, q = x.field(part), y.field(part)
    width = max([1, *np.diff(np.asarray(p.offsets)).tolist(), *np.diff(np.asarray(q.offsets)).tolist()])
    return _dense(p, width), _dense(q, width)


def _scored_blocks(x: pa.StructArray, y: pa.StructArray, metric: str, gamma: float, least: float) -> Iterator[pa.RecordBatch]:
    a, b = np.asarray(x.field("id")), np.asarray(y.field("id"))
    same = len(a) == len(b) and (a == b).all()
    (xs, ys), (xc, yc) = _parts(x, y, "shape"), _parts(x, y, "cls")
    norm = lambda m: np.sqrt((m * m).sum(axis=1))
    nxs, nys, nxc, nyc = norm(xs), norm(ys), norm(xc), norm(yc)
    for k in range(0, len(a), AT_ONCE):
        at = slice(k, k + AT_ONCE)
        dot_cls = xc[at] @ yc.T
        s_cls, s_shape = _cosines(dot_cls, nxc[at], nyc), None
        if metric == "cosine":
            dot_shape = xs[at] @ ys.T
            s_shape = _cosines(dot_shape, nxs[at], nys)
            s = _cosines(dot_shape + dot_cls, np.hypot(nxs[at], nxc[at]), np.hypot(nys, nyc))
        elif metric == "cls":
            s = s_cls
        else:
            s_shape = np.stack([_apart(row, ys, gamma) for row in xs[at]])
            s = np.round(s_cls * s_shape, 10) if metric == "hybrid" else s_shape
        i, j = np.nonzero((s >= least) & ((a[at, None] < b[None, :]) if same else True))
        for m in range(0, len(i), 1 << 18):
            p, q = i[m : m + (1 << 18)], j[m : m + (1 << 18)]
            shape = _apart(xs[at][p], ys[q], gamma) if s_shape is None else s_shape[p, q]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a[at][p], b[q])), pa.array(np.maximum(a[at][p], b[q])), pa.array(s_cls[p, q]), pa.array(shape), pa.array(s[p, q])], names=["id_a", "id_b", "s_cls", "s_shape", "s"])


def _block_scores(metric: str, gamma: float, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # rows come ordered by pair of blocks, the first block's row before the second's
        first, held = None, None
        for batch in batches:
            for a, b, second, values in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("second").to_pylist(), batch.column("held"), strict=True):
                if not second:
                    first, held = (a, b), values.values
                if second and first == (a, b) or a == b:
                    yield from _scored_blocks(held, values.values, metric, gamma, least)

    return run


def brute(vectors: DataFrame, metric: str = "hybrid", gamma: float = 5.0, least: float = -1.0) -> DataFrame:
    """Scores of all pairs, or of those from `least` on.

    Blocks of vectors meet each other, and matrix products score them; only the pairs leave a block. A vector travels once
    for each block, which is what all pairs cost; no number of vectors is refused.
    """
    n = vectors.count()
    blocks = max(1, -(-n // BLOCK), min(LEAST_BLOCKS, -(-n // AT_ONCE)))
    held = vectors.groupBy(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("block")).agg(F.array_sort(F.collect_list(F.struct("id", "shape", "cls"))).alias("held"))
    held = materialize(held, "blocks")
    # a hash may leave a block empty, whose pairs have one side only then and no scores
    dealt = held.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    dealt = dealt.select(F.least("block", "other").alias("a"), F.greatest("block", "other").alias("b"), (F.col("block") > F.col("other")).alias("second"), "held")
    ordered = dealt.repartition("a", "b").sortWithinPartitions("a", "b", "second")
    return ordered.mapInArrow(_block_scores(metric, gamma, least), "id_a long, id_b long, s_cls double, s_shape double, s double")


#: Coordinates of each part among which the grid's axes are chosen, and those of the first, cheap distance test.
LEADING = 12
#: Axes of the grid at most.
AXES = 3


def _coordinate(part: str, k: int, joint: bool, side: str = ""):
    """A coordinate that the score bounds: of the shape as it is, of the class part at unit length; of both at joint length for the cosine."""
    value = F.coalesce(F.get(f"{part}{side}", F.lit(k)), F.lit(0.0))
    n_shape, n_cls = F.col(f"norm_shape{side}"), F.col(f"norm_cls{side}")
    if joint:
        return F.coalesce(F.try_divide(value, F.sqrt(n_shape * n_shape + n_cls * n_cls)), F.lit(0.0))
    return F.coalesce(F.try_divide(value, n_cls), F.lit(0.0)) if part == "cls" else value


def _sides(metric: str, tau: float, gamma: float) -> dict[str, float]:
    """For each part that the metric bounds, how far two vectors of score tau can lie apart; with a margin for rounding."""
    angle, shape = math.sqrt(2 * (1 - tau) + 1e-9), radius(tau, gamma) if tau < 1 else 0.0
    found = {"hybrid": {"shape": shape, "cls": angle}, "gauss": {"shape": shape}, "cls": {"cls": angle}, "cosine": {"shape": angle, "cls": angle}}[metric]
    return {k: x * (1 + 1e-6) + 1e-9 for k, x in found.items()}


def _axes(vectors: DataFrame, sides: dict[str, float], joint: bool) -> list[tuple[str, int]]:
    """The coordinates that spread most against their side, over all vectors; only those that tell vectors apart, one at least."""
    every = [(part, k) for part in sides for k in range(LEADING)]
    row = vectors.agg(*[F.coalesce(F.variance(_coordinate(part, k, joint)), F.lit(0.0)).alias(f"{part}{k}") for part, k in every]).first()
    spread = {(part, k): row[f"{part}{k}"] / sides[part] ** 2 for part, k in every}
    best = sorted(every, key=lambda x: (-spread[x], x))[:AXES]
    return [x for n, x in enumerate(best) if n == 0 or spread[x] > 0.25]


def axes_of(vectors: DataFrame, tau: float, gamma: float = 5.0, metric: str = "hybrid") -> list[tuple[str, int]]:
    """Axes for a grid over these vectors, to be used for others like them too."""
    return _axes(with_norms(vectors), _sides(metric, tau, gamma), metric == "cosine")


def _celled(vectors: DataFrame, axes: list[tuple[str, int]], sides: dict[str, float], joint: bool) -> DataFrame:
    return vectors.withColumns({f"cell{n}": F.floor(_coordinate(part, k, joint) / sides[part]) for n, (part, k) in enumerate(axes)})


def _shifted(placed: DataFrame, axes: int, half: bool) -> DataFrame:
    """Rows in all neighbouring cells; half of them, and the own cell, where both sides are the same vectors."""
    zero = (0,) * axes
    steps = [o for o in itertools.product((-1, 0, 1), repeat=axes) if not half or o >= zero]
    made = F.array(*[F.struct(*[(F.col(f"cell{n}") + x).alias(f"cell{n}") for n, x in enumerate(o)], F.lit(o == zero).alias("cf_own")) for o in steps])
    return placed.withColumn("cf_to", F.explode(made)).withColumns({f"cell{n}": F.col(f"cf_to.cell{n}") for n in range(axes)}).withColumn("cf_own", F.col("cf_to.cf_own")).drop("cf_to")


def grid(vectors: DataFrame, tau: float, gamma: float = 5.0, metric: str = "hybrid", wide: bool = False, against: DataFrame | None = None, axes: list | None = None) -> DataFrame:
    """Candidate pairs with vectors and norms (sides _a and _b), among the vectors, or between them and others.

    Each cell meets half of its neighbours by an equi-join. `wide` vectors don't travel with the cells: ids and leading
    coordinates do, and the vectors join the pairs that are left.
    """
    sides, joint = _sides(metric, tau, gamma), metric == "cosine"
    first = with_norms(vectors)
    second = first if against is None else with_norms(against)
    axes = axes or _axes(second, sides, joint)
    cells = [f"cell{n}" for n in range(len(axes))]
    held = ["id", "near"] if wide else READY
    near = F.array(*[_coordinate("shape", k, joint) for k in range(LEADING)])
    ready = lambda v: _celled(v, axes, sides, joint).withColumn("near", near).select(*cells, *held)
    left = ready(second).select(*cells, *[F.col(c).alias(f"{c}_a") for c in held])
    right = _shifted(ready(first), len(axes), against is None).select(*cells, "cf_own", *[F.col(c).alias(f"{c}_b") for c in held])
    pairs = left.join(right, cells)
    if against is None:
        pairs = pairs.where(~F.col("cf_own") | (F.col("id_a") < F.col("id_b")))
    pairs = pairs.drop(*cells, "cf_own")
    if "shape" in sides and not joint:
        # a sum over leading coordinates bounds the whole distance from below
        if wide:
            apart = sum((F.pow(F.get("near_a", F.lit(k)) - F.get("near_b", F.lit(k)), F.lit(2)) for k in range(LEADING)), F.lit(0.0))
        else:
            apart = squared_distance("shape_a", "shape_b")
        pairs = pairs.where(apart <= sides["shape"] ** 2)
    if wide:
        of = lambda v, x: v.select(*[F.col(c).alias(f"{c}_{x}") for c in READY])
        pairs = pairs.select("id_a", "id_b").join(of(second, "a"), "id_a").join(of(first, "b"), "id_b")
    return pairs


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b"), "s_cls", "s_shape", "s")


def grid_pairs(vectors: DataFrame, tau: float, gamma: float = 5.0, metric: str = "hybrid", wide: bool = False, axes: list | None = None) -> DataFrame:
    """Pairs with a score of at least tau, id_a below id_b; nothing is lost for any metric."""
    return _ordered(_scored(grid(vectors, tau, gamma, metric, wide, axes=axes), metric, gamma).where(F.col("s") >= tau))


def grid_between(new: DataFrame, index: DataFrame, tau: float, gamma: float = 5.0, metric: str = "hybrid", wide: bool = False, axes: list | None = None) -> DataFrame:
    """Pairs of a new vector and one of the index with a score of at least tau, id_a below id_b."""
    return _ordered(_scored(grid(new, tau, gamma, metric, wide, against=index, axes=axes), metric, gamma).where(F.col("s") >= tau))


def sign_lsh(vectors: DataFrame, width: int = 12, tables: int = 16, dims: int = 64) -> DataFrame:
    """(table, bucket, id): signs of pseudo-random projections of the class part, tables times width of them."""
    plane = lambda t, w: F.aggregate(F.transform("cls", lambda x, i: x * (F.pmod(F.xxhash64(i, F.lit(t), F.lit(w)), F.lit(2001)) - 1000)), F.lit(0.0), lambda s, v: s + v)
    bucket = lambda t: F.concat(*[F.when(plane(t, w) > 0, "1").otherwise("0") for w in range(width)])
    return vectors.select("id", F.posexplode(F.array(*[bucket(t) for t in range(tables)])).alias("table", "bucket"))


def ann_candidates(vectors: DataFrame, width: int = 12, tables: int = 16) -> DataFrame:
    """Distinct id pairs that share a bucket in some table."""
    b = sign_lsh(vectors, width, tables)
    return b.alias("l").join(b.alias("r"), ["table", "bucket"]).where("l.id < r.id").select(F.col("l.id").alias("id_a"), F.col("r.id").alias("id_b")).distinct()


def ann_pairs(vectors: DataFrame, tau: float, metric: str = "cls", gamma: float = 5.0, width: int = 12, tables: int = 16) -> DataFrame:
    c = ann_candidates(vectors, width, tables)
    v = with_norms(vectors)
    a, b = v.select(*[F.col(k).alias(f"{k}_a") for k in READY]), v.select(*[F.col(k).alias(f"{k}_b") for k in READY])
    return _scored(c.join(a, "id_a").join(b, "id_b"), metric, gamma).where(F.col("s") >= tau)


#: Pivots of the inverted lists, in how many lists a vector stands, and how many a query visits.
LISTS, HOMES, PROBES = 32, 4, 16
#: Vectors and queries of a block of the search.
SOUGHT, ASKED = 1024, 4096


def _best(score: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the k best of each row, equal scores by their ids."""
    if score.shape[1] > k:
        least = -np.partition(-score, k - 1, axis=1)[:, k - 1]
        row, at = np.nonzero(score >= least[:, None])
    else:
        row, at = (x.ravel() for x in np.indices(score.shape))
    order = np.lexsort((ids[at], -score[row, at], row))
    row, at = row[order], at[order]
    keep = np.arange(len(row)) - np.searchsorted(row, row, "left") < k
    return row[keep], at[keep]


def _visited(pivots: list, n: int):
    """(list, id, cls) of each vector's n nearest pivots."""
    heads = pa.array([{"id": r["id"], "cls": r["cls"]} for r in pivots], pa.struct([("id", pa.int64()), ("cls", pa.list_(pa.float64()))]))
    names = np.array([r["id"] for r in pivots], np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = _parts(pa.StructArray.from_arrays([batch.column("id"), batch.column("cls")], ["id", "cls"]), heads, "cls")
            row, at = _best(_cosines(x @ y.T, np.sqrt((x * x).sum(axis=1)), np.sqrt((y * y).sum(axis=1))), names, n)
            yield pa.RecordBatch.from_arrays([pa.array(names[at]), batch.column("id").take(pa.array(row)), batch.column("cls").take(pa.array(row))], names=["list", "id", "cls"])

    return run


def _searched(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for asked, held in zip(batch.column("asked"), batch.column("held"), strict=True):
                x, y = asked.values, held.values
                q, ids = np.asarray(x.field("id")), np.asarray(y.field("id"))
                xs, ys = _parts(x, y, "cls")
                nx, ny = np.sqrt((xs * xs).sum(axis=1)), np.sqrt((ys * ys).sum(axis=1))
                for m in range(0, len(q), AT_ONCE):
                    at = slice(m, m + AT_ONCE)
                    score = _cosines(xs[at] @ ys.T, nx[at], ny)
                    # a query isn't its own neighbour
                    score[q[at, None] == ids[None, :]] = -np.inf
                    i, j = _best(score, ids, k)
                    keep = score[i, j] > -np.inf
                    i, j = i[keep], j[keep]
                    yield pa.RecordBatch.from_arrays([pa.array(q[at][i]), pa.array(ids[j]), pa.array(score[i, j])], names=["query", "id", "s"])

    return run


def _in_blocks(rows: DataFrame, size: int, block: str, held: str) -> DataFrame:
    """Blocks of (list, id, cls) within each list, and `{block}s`, their number; lists are a constant number."""
    number = rows.groupBy("list").agg(F.ceil(F.count(F.lit(1)) / size).cast("int").alias(f"{block}s"))
    placed = rows.join(F.broadcast(number), "list").withColumn(block, F.pmod(F.xxhash64("id"), F.col(f"{block}s")).cast("int"))
    return placed.groupBy("list", block, f"{block}s").agg(F.collect_list(F.struct("id", "cls")).alias(held))


def nearest(vectors: DataFrame, queries: DataFrame, k: int, lists: int = LISTS, probes: int | None = PROBES) -> DataFrame:
    """(query, id, s, place) of the k most similar class parts to each query, by inverted lists; exact where probes is None.

    A fixed number of pivots, the vectors with the smallest md5 of their ids, parts the vectors: each stands in the lists of
    its HOMES nearest pivots, and a query meets those of its `probes` nearest. Every vector is in some list; the exact
    search has one list of all. Blocks of a list's queries and vectors meet, and only the k best of each query in a block
    leave it, so what is shuffled doesn't grow with the pairs that are scored.
    """
    v, q = vectors.select("id", "cls"), queries.select("id", "cls")
    if probes is None:
        home, seen = (x.select(F.lit(0).cast("long").alias("list"), "id", "cls") for x in (v, q))
    else:
        pivots = v.orderBy(F.md5(F.col("id").cast("string"))).limit(lists).collect()
        home, seen = (x.mapInArrow(_visited(pivots, n), "list long, id long, cls array<double>") for x, n in ((v, HOMES), (q, probes)))
    held = materialize(_in_blocks(home, SOUGHT, "block", "held"), "sought")
    asked = materialize(_in_blocks(seen, ASKED, "part", "asked"), "asked")
    # each side learns the other's number of blocks
    left = asked.join(F.broadcast(held.select("list", "blocks").distinct()), "list").withColumn("block", F.explode(F.expr("sequence(0, blocks - 1)")))
    right = held.join(F.broadcast(asked.select("list", "parts").distinct()), "list").withColumn("part", F.explode(F.expr("sequence(0, parts - 1)")))
    dealt = left.select("list", "block", "part", "asked").join(right.select("list", "block", "part", "held"), ["list", "block", "part"])
    scored = dealt.select("asked", "held").mapInArrow(_searched(k), "query long, id long, s double").dropDuplicates(["query", "id"])
    place = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("s"), "id"))
    return scored.withColumn("place", place).where(F.col("place") <= k)


#: Pair generators by name: (vectors, tau, gamma, metric) -> scored pairs of at least tau.
BACKENDS = {
    "grid": lambda v, tau, gamma, metric: grid_pairs(v, tau, gamma, metric),
    "grid_wide": lambda v, tau, gamma, metric: grid_pairs(v, tau, gamma, metric, wide=True),
    "brute": lambda v, tau, gamma, metric: brute(v, metric, gamma, least=tau),
    "ann": lambda v, tau, gamma, metric: ann_pairs(v, tau, metric, gamma),
}


#: Backends that find all pairs.
LOSSLESS = ("grid", "grid_wide", "brute")


def clusters(vectors: DataFrame, pairs: DataFrame, members: DataFrame) -> DataFrame:
    """(id, root) of every vector, with the members of collapsed ones expanded."""
    roots = connected_components(pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")))
    return members.join(roots, members["head"] == roots["node"], "left").select("id", F.coalesce("root", "head").alias("root"))


def search_and_prune(vectors: DataFrame, tau: float, gamma: float = 5.0, metric: str = "hybrid", backend: str = "grid", max_rounds: int = 10) -> DataFrame:
    """Retrieve, score, merge, drop absorbed vectors, and again until nothing merges: (id, root)."""
    active, members = collapse(vectors)
    active, found = materialize(active, "active"), materialize(members, "members")
    for _ in range(max_rounds):
        pairs = materialize(BACKENDS[backend](active, tau, gamma, metric), "pairs")
        if pairs.isEmpty():
            break
        roots = materialize(connected_components(pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b"))), "roots")
        found = materialize(found.join(roots, found["head"] == roots["node"], "left").select("id", F.coalesce("root", "head").alias("head")), "members")
        if backend in LOSSLESS:
            break  # all links are known, so what is left has none
        active = materialize(active.join(roots.where("node <> root"), active["id"] == F.col("node"), "left_anti"), "active")
    else:
        raise RuntimeError(f"vectors still merge after {max_rounds} rounds")
    return found.select("id", F.col("head").alias("root"))
