"""Near-duplicate documents: fast similarity sketches, banding, exact verification, connected components.

A document's set holds its distinct five-word shingles as 64-bit hashes. Its sketch has `size` coordinates. In round i < size
every element is placed into a random coordinate with value (i, hash); in round size + j every element is placed into
coordinate j, which guarantees that all fill. A coordinate keeps the smallest value it gets, so rounds stop once all are
filled, and the share of equal coordinates of two sketches is concentrated around the Jaccard similarity of the sets.
Bands of `rows` coordinates make the candidates: at 48 bands of 6, a pair at similarity 0.85 shares no band with a chance of
1e-10, and one at 0.80, where the pipeline's stage links, with a chance of 5e-7; one at 0.3 shares a band with a chance of
0.03, so that texts with some boilerplate in common seldom meet.

Sets that are equal become one node first. In a bucket each node is compared with the bucket's smallest node, the hub, unless
their sizes alone rule a link out; so a bucket of m nodes gives m - 1 pairs, and links merge components. A hub's partners are
dealt into chunks of bounded size, and its text goes to each chunk once.

Where all nodes of a hub are one component then, nothing is left to find. The other hubs' nodes get signatures, a byte for
each coordinate of their sketches, and a hub's nodes of equal or neighbouring size classes are compared by signatures in
blocks of bounded size: the share of equal bytes of a linked pair lies more than 0.2 below the least similarity with a chance
of 1e-13. Nodes of different components that such likeness connects are a family. A family is laid out by size class,
component and hash in blocks of bounded size, and blocks of equal or neighbouring size classes are compared with each other,
unless both lie in the same component. Only the links that full sets confirm leave a block. So no task sees a whole bucket
or family, and all links come from comparisons of the full sets of the whole texts.

Defined cases: null and empty texts, and texts without words, have empty sets and are linked with nothing; equal texts are
linked; a row without doc_id is its own class with a null id; an empty table gives an empty result; a doc_id stands for one
text, and where it repeats, a link of any of its texts counts for it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockflow.llm import kernels as K
from blockflow.operators.components import connected_components
from blockflow.session import drop_shuffles, materialize

U64 = np.uint64


@dataclass(frozen=True)
class NearDupConfig:
    width: int = 5
    bands: int = 48
    rows: int = 6
    #: A link: share_of * intersection >= share * union.
    share: int = 85
    share_of: int = 100
    #: Shingles of a block or chunk.
    block: int = 40_000
    #: Nodes of a block of signatures.
    signed: int = 1024
    #: How far below the least similarity the likeness of a linked pair's signatures may lie.
    margin: float = 0.2

    @property
    def size(self) -> int:
        return self.bands * self.rows


#: Rounds in which elements go where their hashes say, at these steps; later rounds take the coordinates in turn.
STEPS = (0, 1, 2, 4, 8, 16, 32, 64)
_OPEN = ~U64(0)


def sketch(values: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """One row of `size` coordinates for each text with elements; zeros for one without.

    A coordinate's value is (round, hash) in one number, and the smallest stays; so what comes in later rounds never
    replaces anything, and rounds are worked off several at a time over the texts that still have open coordinates.
    """
    n = len(at) - 1
    out = np.full(n * size, _OPEN)
    owner, elements = np.repeat(np.arange(n), np.diff(at)), values
    for begin, end in zip(STEPS, STEPS[1:], strict=False):
        rounds = np.arange(begin, end, dtype=U64)
        h = K.mix((elements[None, :] + ((rounds + U64(1)) * U64(0xA0761D6478BD642F))[:, None]).ravel())
        flat = np.tile(owner * size, len(rounds)) + (((h >> U64(32)) * U64(size)) >> U64(32)).astype(np.int64)
        np.minimum.at(out, flat, np.repeat(rounds << U64(57), len(elements)) | (K.mix(h) >> U64(7)))
        stay = (out.reshape(n, size) == _OPEN).any(axis=1)[owner]
        elements, owner = elements[stay], owner[stay]
        if not len(elements):
            break
    rows = out.reshape(n, size)
    turns = (np.arange(STEPS[-1], STEPS[-1] + size, dtype=U64) + U64(1)) * U64(0xA0761D6478BD642F)
    for i in range(0, len(elements), 4096):
        part, mine = elements[i : i + 4096], owner[i : i + 4096]
        keys = U64(STEPS[-1] << 57) | (K.mix(K.mix(part[:, None] + turns[None, :])) >> U64(7))
        heads = np.flatnonzero(np.append(True, mine[1:] != mine[:-1]))
        rows[mine[heads]] = np.minimum(rows[mine[heads]], np.minimum.reduceat(keys, heads, axis=0))
    rows[np.diff(at) == 0] = 0
    return rows


def band_keys(sketches: np.ndarray, bands: int) -> np.ndarray:
    """A 64-bit key for each band, which differs between bands."""
    n, size = sketches.shape
    parts = sketches.reshape(n, bands, size // bands)
    key = np.tile(K.mix(np.arange(1, bands + 1, dtype=U64)), (n, 1))
    for k in range(parts.shape[2]):
        key = K.mix(key * U64(0x9FB21C651E98DF25) + parts[:, :, k])
    return key


def _sketched(config: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            ids = batch.column("doc_id")
            for i, j in K.slices(offsets):
                values, at = K.distinct_sorted(*K.shingles(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], config.width))
                keys = band_keys(sketch(values, at, config.size), config.bands)
                sums = np.append(U64(0), np.cumsum(K.mix(values ^ U64(0x5851F42D4C957F2D)), dtype=U64))
                twice = np.append(U64(0), np.cumsum(K.mix(values * U64(0xDA942042E4DD58B5) + U64(1)), dtype=U64))
                flat = pa.array(keys.view(np.int64).ravel())
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, config.bands, dtype=np.int32)), flat)
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(i, j - i), pa.array(np.diff(at)), pa.array((sums[at[1:]] - sums[at[:-1]]).view(np.int64)), pa.array((twice[at[1:]] - twice[at[:-1]]).view(np.int64)), lists],
                    names=["doc_id", "n_shingles", "d1", "d2", "bands"],
                )

    return run


def sketch_documents(docs: DataFrame, config: NearDupConfig) -> DataFrame:
    """doc_id, set size, two digests of the set, band keys."""
    return docs.select("doc_id", "text").mapInArrow(_sketched(config), "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>")


def _sets(config: NearDupConfig, texts) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first text, shingles, offsets) of a column's texts, a slice at a time."""
    data, offsets = K.column_bytes(texts)
    for i, j in K.slices(offsets):
        yield i, *K.distinct_sorted(*K.shingles(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], config.width))


def _similar(config: NearDupConfig, both, x, y):
    return (both > 0) & (config.share_of * both >= config.share * (x + y - both))


def _common(x: np.ndarray, y: np.ndarray) -> int:
    """The size of the intersection of two sorted sets."""
    if len(x) > len(y):
        x, y = y, x
    at = np.searchsorted(y, x)
    return int((y[np.minimum(at, len(y) - 1)] == x).sum()) if len(x) else 0


def _verified(config: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # rows come ordered by chunk, its hub first; the hub's set stays for the chunk, which batches may cut
        hub, whole = None, np.zeros(0, U64)
        for batch in batches:
            heads, node, is_node = (batch.column(k).to_pylist() for k in ("hub", "node", "is_node"))
            a, b = [], []
            for i, values, at in _sets(config, batch.column("text")):
                for k in range(len(at) - 1):
                    mine = values[at[k] : at[k + 1]]
                    if not is_node[i + k]:
                        hub, whole = heads[i + k], mine
                    elif heads[i + k] == hub and _similar(config, _common(whole, mine), len(whole), len(mine)):
                        a.append(hub)
                        b.append(node[i + k])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return run


def _sizes_allow(config: NearDupConfig, x: str, y: str) -> Column:
    return F.expr(f"{config.share_of} * least({x}, {y}) >= {config.share} * greatest({x}, {y})")


def verify(pairs: DataFrame, texts: DataFrame, config: NearDupConfig) -> DataFrame:
    """Those pairs (hub, node, ways) whose full shingle sets are similar enough, as (a, b).

    ways says into how many chunks the hub's partners are dealt. texts has doc_id and text.
    """
    dealt = pairs.select("hub", "ways", F.pmod(F.xxhash64("node"), "ways").alias("chunk"), "node", F.lit(True).alias("is_node"))
    heads = dealt.select("hub", "ways", "chunk").distinct().select("hub", "ways", "chunk", F.col("hub").alias("node"), F.lit(False).alias("is_node"))
    full = dealt.union(heads).join(texts.select(F.col("doc_id").alias("node"), "text"), "node").select("hub", "ways", "chunk", "is_node", "node", "text")
    return full.repartition("hub", "ways", "chunk").sortWithinPartitions("hub", "ways", "chunk", "is_node").mapInArrow(_verified(config), "a long, b long")


def _overlaps(x: tuple[np.ndarray, np.ndarray], y: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of each set of x with each of y, by the shingles they share."""
    (xv, xa), (yv, ya) = x, y
    nx, ny = len(xa) - 1, len(ya) - 1
    out = np.zeros((nx, ny), np.int64)
    owner = np.repeat(np.arange(ny), np.diff(ya))
    order = np.argsort(yv, kind="stable")
    yv, owner = yv[order], owner[order]
    step = max(1, (1 << 21) // max(1, ny * int(np.diff(xa).max(initial=1))))
    for i in range(0, nx, step):
        j = min(nx, i + step)
        part = xv[xa[i] : xa[j]]
        low, high = np.searchsorted(yv, part, "left"), np.searchsorted(yv, part, "right")
        n = high - low
        where = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(n.sum())
        row = np.repeat(np.repeat(np.arange(j - i), np.diff(xa[i : j + 1])), n)
        out[i:j] = np.bincount(row * ny + owner[where], minlength=(j - i) * ny).reshape(j - i, ny)
    return out


def _compared(config: NearDupConfig):
    def sets(texts) -> tuple[np.ndarray, np.ndarray]:
        return K.distinct_sorted(*K.shingles(*K.column_bytes(texts), config.width))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for left, right in zip(batch.column("left"), batch.column("right"), strict=True):
                x, y = left.values, right.values
                xs, ys = sets(x.field("text")), sets(y.field("text"))
                both = _overlaps(xs, ys)
                like = _similar(config, both, np.diff(xs[1])[:, None], np.diff(ys[1])[None, :])
                a, b = np.asarray(x.field("node")), np.asarray(y.field("node"))
                open_ = np.asarray(x.field("root"))[:, None] != np.asarray(y.field("root"))[None, :]
                i, j = np.nonzero(like & open_)
                yield pa.RecordBatch.from_arrays([pa.array(a[i]), pa.array(b[j])], names=["a", "b"])

    return run


def _signed(config: NearDupConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            node = batch.column("node")
            for i, values, at in _sets(config, batch.column("text")):
                signs = np.ascontiguousarray(K.mix(sketch(values, at, config.size)) >> U64(56)).astype(np.uint8)
                flat = pa.FixedSizeBinaryArray.from_buffers(pa.binary(config.size), len(signs), [None, pa.py_buffer(signs.tobytes())])
                yield pa.RecordBatch.from_arrays([node.slice(i, len(signs)), flat.cast(pa.binary())], names=["node", "sign"])

    return run


def _like(config: NearDupConfig):
    least = (config.share / config.share_of - config.margin) * config.size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = [], []
            for left, right in zip(batch.column("left"), batch.column("right"), strict=True):
                x, y = left.values, right.values
                sx, sy = (np.frombuffer(b"".join(z.field("sign").to_pylist()), np.uint8).reshape(-1, config.size) for z in (x, y))
                (i, nx, rx), (j, ny, ry) = ([np.asarray(z.field(k)) for k in ("node", "n", "root")] for z in (x, y))
                low, high = np.minimum(nx[:, None], ny[None, :]), np.maximum(nx[:, None], ny[None, :])
                meet = (config.share_of * low >= config.share * high) & (rx[:, None] != ry[None, :])
                for k in np.flatnonzero(meet.any(axis=1)):
                    at = np.flatnonzero(meet[k])
                    meet[k, at] = np.count_nonzero(sy[at] == sx[k], axis=1) >= least
                # of each group that likeness connects in these blocks only a star leaves them
                keep, other = np.flatnonzero(meet.any(axis=1)), np.flatnonzero(meet.any(axis=0))
                meet, to_i, to_j = meet[np.ix_(keep, other)], i[keep].copy(), j[other].copy()
                same, seen = len(i) == len(j) and (i == j).all(), None
                while len(keep) and seen != (to_i.sum(), to_j.sum()):
                    seen = (to_i.sum(), to_j.sum())
                    to_i = np.minimum(to_i, np.where(meet, to_j[None, :], _LAST).min(axis=1))
                    to_j = np.minimum(to_j, np.where(meet, to_i[:, None], _LAST).min(axis=0))
                    if same:
                        to_i = to_j = np.minimum(to_i, to_j)
                for nodes, to in ((i[keep], to_i), (j[other], to_j)):
                    a.append(to[to < nodes])
                    b.append(nodes[to < nodes])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(z) if z else [], pa.int64()) for z in (a, b)], names=["a", "b"])

    return run


#: Above all nodes.
_LAST = np.iinfo(np.int64).max


def _classed(nodes: DataFrame, config: NearDupConfig) -> DataFrame:
    """With cls, the size class; sets that can be similar enough lie in equal or neighbouring ones."""
    width = np.log(config.share_of / config.share) * (1 + 1e-9)
    return nodes.withColumn("cls", F.floor(F.ln("n") / F.lit(float(width))))


def _meeting(blocks: DataFrame, group: str) -> DataFrame:
    """(left, right): the held nodes of a group's blocks in equal or neighbouring size classes, unless both blocks are of one component."""
    thin = blocks.select(group, "cls", "block", "lo", "hi")
    ahead = thin.select(group, F.explode(F.array("cls", F.col("cls") - 1)).alias("cls"), F.col("cls").alias("other_cls"), F.col("block").alias("other"), F.col("lo").alias("other_lo"), F.col("hi").alias("other_hi"))
    wanted = thin.join(ahead, [group, "cls"]).where("(other_cls > cls or block <= other) and not (lo = hi and other_lo = other_hi and lo = other_lo)")
    wanted = wanted.select(group, "cls", "block", "other_cls", "other")
    left = blocks.select(group, "cls", "block", F.col("held").alias("left"))
    right = blocks.select(group, F.col("cls").alias("other_cls"), F.col("block").alias("other"), F.col("held").alias("right"))
    return wanted.join(left, [group, "cls", "block"]).join(right, [group, "other_cls", "other"]).select("left", "right")


def _families(open_: DataFrame, texts: DataFrame, config: NearDupConfig) -> DataFrame:
    """(node, family) of the nodes whose signatures connect different components. open_: hub, node, root, n."""
    full = open_.select("node").distinct().join(texts.select(F.col("doc_id").alias("node"), "text"), "node")
    signs = materialize(full.mapInArrow(_signed(config), "node long, sign binary"), "signatures")
    placed = materialize(_classed(open_, config), "placed")
    ways = placed.groupBy("hub", "cls").agg(F.ceil(F.count(F.lit(1)) / config.signed).alias("k"), F.min("root").alias("lo"), F.max("root").alias("hi"))
    held = placed.join(ways, ["hub", "cls"]).withColumn("block", F.pmod(F.xxhash64("node"), "k")).join(signs, "node")
    blocks = held.groupBy("hub", "cls", "block").agg(F.collect_list(F.struct("node", "root", "n", "sign")).alias("held"), F.min("root").alias("lo"), F.max("root").alias("hi"))
    blocks = materialize(blocks, "signed")
    drop_shuffles(texts.sparkSession)
    likely = materialize(_meeting(blocks, "hub").mapInArrow(_like(config), "a long, b long"), "likely")
    drop_shuffles(texts.sparkSession)
    return connected_components(likely).withColumnRenamed("root", "family")


def _family_links(open_: DataFrame, texts: DataFrame, config: NearDupConfig) -> DataFrame:
    """Links across components between the nodes of a family, from comparing its blocks. open_: hub, node, root, n."""
    families = _families(open_, texts, config)
    placed = materialize(_classed(open_.select("node", "root", "n").distinct().join(families, "node"), config), "families")
    weight = placed.groupBy("family", "cls", "root").agg(F.sum("n").alias("w"))
    small = weight.where(F.col("w") < config.block).groupBy("family", "cls").agg(F.ceil(F.sum("w") / config.block).alias("k"))
    # a large component has blocks of its own, small ones share blocks
    shape = weight.join(small, ["family", "cls"], "left").select(
        "family", "cls", "root", (F.col("w") >= config.block).alias("big"), F.when(F.col("w") >= config.block, F.ceil(F.col("w") / config.block)).otherwise(F.col("k")).alias("k")
    )
    at = F.when(F.col("big"), F.pmod(F.xxhash64("node"), "k")).otherwise(F.pmod(F.xxhash64("root"), "k"))
    block = F.struct("big", F.when(F.col("big"), F.col("root")).otherwise(F.lit(0)).alias("owner"), at.alias("at"))
    blocked = placed.join(shape, ["family", "cls", "root"]).select("family", "cls", block.alias("block"), "node", "root")
    full = blocked.join(texts.select(F.col("doc_id").alias("node"), "text"), "node")
    blocks = materialize(full.groupBy("family", "cls", "block").agg(F.collect_list(F.struct("node", "root", "text")).alias("held"), F.min("root").alias("lo"), F.max("root").alias("hi")), "blocks")
    drop_shuffles(texts.sparkSession)
    return _meeting(blocks, "family").mapInArrow(_compared(config), "a long, b long")


#: Ways that the rows of a class of equal sets are dealt to, so that no task gets all copies of one text.
COPIES = 16


def near_duplicates(docs: DataFrame, config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id (smallest doc_id that links reach), kept."""
    sketched = materialize(sketch_documents(docs, config), "sketches")
    member = sketched.where("n_shingles > 0").select("doc_id", "n_shingles", "d1", "d2")
    classes = materialize(member.groupBy("d1", "d2", "n_shingles").agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("copies")).where("node is not null"), "classes")
    bands = (
        sketched.join(classes.select(F.col("node").alias("doc_id")), "doc_id", "left_semi")
        .where("n_shingles > 0")
        .select(F.col("doc_id").alias("node"), F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    )
    shared = bands.groupBy("key").agg(F.min(F.struct("node", "n")).alias("hub"), F.max("node").alias("last"), F.sum("n").alias("w")).where("hub.node < last")
    # written, so that a bucket with a large share of all nodes can be split where it is joined
    shared = materialize(shared.select("key", F.col("hub.node").alias("hub"), F.col("hub.n").alias("hub_n"), F.ceil(F.col("w") / config.block).alias("ways")), "keys")
    drop_shuffles(docs.sparkSession)
    # only buckets with two nodes or more matter from here on
    rows = materialize(bands.join(shared, "key").groupBy("hub", "hub_n", "node", "n").agg(F.max("ways").alias("ways")), "buckets")
    in_play = rows.select(F.col("node").alias("doc_id")).distinct()
    texts = materialize(docs.select("doc_id", "text").join(in_play, "doc_id", "left_semi"), "texts")
    drop_shuffles(docs.sparkSession)
    pairs = rows.where("hub < node").where(_sizes_allow(config, "n", "hub_n")).select("hub", "node", "ways")
    links = materialize(verify(pairs, texts, config), "verified")
    drop_shuffles(docs.sparkSession)
    roots = materialize(connected_components(links), "roots")
    # hubs whose nodes aren't all in one component leave pairs to look at
    rooted = rows.select("hub", "node", "n").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    split = materialize(rooted.groupBy("hub").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("hub"), "split-hubs")
    open_ = materialize(rooted.join(split, "hub", "left_semi").select("hub", "node", "root", "n"), "open")
    drop_shuffles(docs.sparkSession)
    if not open_.isEmpty():
        links = links.union(materialize(_family_links(open_, texts, config), "family-links"))
        roots = materialize(connected_components(links), "roots")
        drop_shuffles(docs.sparkSession)
    # rows find their class by its digests and one of several ways; only classes with copies need this
    doubled = classes.where("copies > 1").join(roots, "node", "left").select("d1", "d2", "n_shingles", F.coalesce("root", "node").alias("class_root"), F.explode(F.sequence(F.lit(0), F.lit(COPIES - 1))).alias("way"))
    known = sketched.select("doc_id", "n_shingles", "d1", "d2", F.pmod(F.xxhash64("doc_id"), F.lit(COPIES)).cast("int").alias("way"))
    placed = known.join(roots.select(F.col("node").alias("doc_id"), "root"), "doc_id", "left").join(doubled, ["d1", "d2", "n_shingles", "way"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("class_root", "root", "doc_id"))
    return placed.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_representatives(docs: DataFrame, config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """The rows of docs whose document stays; of rows that repeat a kept doc_id all stay."""
    verdict = near_duplicates(docs, config).where(~F.col("kept")).select("doc_id").distinct()
    return docs.join(verdict, "doc_id", "left_anti").select(*docs.columns)
