"""Toxicity by a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Texts are folded to lower case and their n-grams hashed into buckets, present or absent. From labelled texts, each bucket has
a log-count ratio r; the buckets whose ratio is most certain (by r over its standard error) are the features, r their
scale, and a logistic regression with ridge penalty gives the weights.

The classifier is fitted on at most `sample` labelled rows, those with the smallest hashes of their doc_id; the model has
at most `features` weights. Scoring reads every whole text.

Defined cases: null and empty texts have no n-grams and score the intercept alone; labels other than 0 and 1 are left out, and
a document with several labels counts as toxic if any is 1; without labels of both kinds the score is the share of label 1
(0 where there are none); rows are scored one by one, whatever repeats; an empty table gives an empty result; a column named
toxicity or tox_text is replaced or left out.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockflow.llm import kernels as K
from blockflow.session import materialize

U64 = np.uint64


@dataclass(frozen=True)
class ToxicityConfig:
    orders: tuple[int, ...] = (3, 4, 5)
    #: Hash buckets, as a power of two.
    bits: int = 18
    features: int = 3000
    sample: int = 24_000
    smoothing: float = 0.5
    ridge: float = 2e-4
    steps: int = 400
    rate: float = 0.05


@dataclass(frozen=True)
class ToxicityModel:
    config: ToxicityConfig
    intercept: float
    #: For each bucket its weight, 0 for what isn't a feature.
    weights: np.ndarray


#: Lower case of the characters below 0x500, where it is one character; white space becomes a space.
_FOLD = np.array([ord(x) if len(x := chr(c).lower()) == 1 else c for c in range(0x500)], np.uint32)
_FOLD[[9, 10, 11, 12, 13, 0xA0]] = 32


def code_points(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Folded code points of the texts in a row, and where each text's begin."""
    points = np.frombuffer(data.tobytes().decode("utf-8", "replace").encode("utf-32-le", "surrogatepass"), np.uint32)
    leads = np.append(0, np.cumsum((data & 0xC0) != 0x80))
    at = leads[offsets]
    low = points < len(_FOLD)
    out = points.copy()
    out[low] = _FOLD[points[low]]
    return out, at


def grams(data: np.ndarray, offsets: np.ndarray, config: ToxicityConfig) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text number, bucket) of all n-grams, an order at a time."""
    points, at = code_points(data, offsets)
    prefix = np.zeros(len(points) + 1, U64)
    np.cumsum((points.astype(U64) + U64(1)) * K.powers(max(1, len(points)))[0][: len(points)], dtype=U64, out=prefix[1:])
    inverse = K.powers(len(points) + 1)[1]
    for n in config.orders:
        count = len(points) - n + 1
        if count <= 0:
            continue
        h = ((prefix[n:] - prefix[:-n]) * inverse[:count] + U64(n)) * U64(0x9FB21C651E98DF25)
        h ^= h >> U64(32)
        bucket = ((h * U64(0xD6E8FEB86659FD93)) >> U64(64 - config.bits)).astype(np.int64)
        ok = np.ones(count, bool)
        for edge in range(1, n):
            cut = at[1:-1] - edge
            ok[cut[(cut >= 0) & (cut < count)]] = False
        yield ok, bucket


def _text_of(at: np.ndarray, places: np.ndarray) -> np.ndarray:
    return np.searchsorted(at, places, "right") - 1


def present(data: np.ndarray, offsets: np.ndarray, config: ToxicityConfig, wanted: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (text number, bucket) pairs; wanted, by bucket, restricts them."""
    at = np.append(0, np.cumsum((data & 0xC0) != 0x80))[offsets]
    keys = []
    for ok, bucket in grams(data, offsets, config):
        places = np.flatnonzero(ok if wanted is None else ok & wanted[bucket])
        keys.append((_text_of(at, places) << config.bits) | bucket[places])
    found = np.unique(np.concatenate(keys)) if keys else np.zeros(0, np.int64)
    return found >> config.bits, found & ((1 << config.bits) - 1)


def _counted(config: ToxicityConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, 1 << config.bits), np.int64)
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            toxic = np.asarray(batch.column("toxic")).astype(np.int64)
            # all n-grams of a slice are held at once here, so slices are small
            for i, j in K.slices(offsets, 1 << 19):
                text, bucket = present(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], config)
                label = toxic[i:j][text]
                for c in (0, 1):
                    total[c] += np.bincount(bucket[label == c], minlength=total.shape[1])
        used = np.flatnonzero(total.sum(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(total[0][used]), pa.array(total[1][used])], names=["bucket", "clean", "toxic"])

    return run


def _featured(config: ToxicityConfig, buckets: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = np.full(1 << config.bits, -1, np.int32)
        index[buckets] = np.arange(len(buckets))
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            for i, j in K.slices(offsets):
                text, bucket = present(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], config, index >= 0)
                edges = np.searchsorted(text, np.arange(j - i + 1))
                columns = index[bucket].astype("<i4")
                yield pa.RecordBatch.from_arrays([batch.column("toxic").slice(i, j - i), pa.array([columns[a:b].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)], pa.binary())], names=["toxic", "columns"])

    return run


def _regression(columns: np.ndarray, at: np.ndarray, y: np.ndarray, scale: np.ndarray, config: ToxicityConfig) -> tuple[np.ndarray, float]:
    """Weights on the scaled features and the intercept, by Adam over all rows."""
    owner = np.repeat(np.arange(len(y)), np.diff(at))
    x = scale[columns]
    w = np.zeros(len(scale) + 1)
    share = np.clip(y.mean(), 1e-6, 1 - 1e-6)
    w[-1] = np.log(share / (1 - share))
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, config.steps + 1):
        z = np.bincount(owner, w[columns] * x, minlength=len(y)) + w[-1]
        error = (1 / (1 + np.exp(-np.clip(z, -60, 60))) - y) / len(y)
        slope = np.append(np.bincount(columns, error[owner] * x, minlength=len(scale)) + config.ridge * w[:-1], error.sum())
        first = 0.9 * first + 0.1 * slope
        second = 0.999 * second + 0.001 * slope**2
        w -= config.rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-10)
    return w[:-1], float(w[-1])


def fit(docs: DataFrame, labels: DataFrame, config: ToxicityConfig = ToxicityConfig()) -> ToxicityModel:
    """The classifier of docs (doc_id, text) with labels (doc_id, toxic); labels hold only rows to learn from."""
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    # at most config.sample rows of two numbers, so this may be broadcast
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(config.sample)
    rows = materialize(docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("toxic", "text"), "labelled")
    totals = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    negative, positive = totals.get(0, 0), totals.get(1, 0)
    weights = np.zeros(1 << config.bits)
    if not (negative and positive):
        share = positive / max(1, positive + negative)
        return ToxicityModel(config, float(np.log(share / (1 - share))) if 0 < share < 1 else (-60.0 if share == 0 else 60.0), weights)
    a = config.smoothing
    counts = rows.mapInArrow(_counted(config), "bucket long, clean long, toxic long").groupBy("bucket").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    ratio = F.log((F.col("toxic") + a) / (positive + 2 * a)) - F.log((F.col("clean") + a) / (negative + 2 * a))
    certain = F.abs(ratio) / F.sqrt(1 / (F.col("toxic") + a) + 1 / (F.col("clean") + a))
    best = counts.select("bucket", ratio.alias("r"), F.round(certain, 6).alias("z")).orderBy(F.desc("z"), "bucket").limit(config.features).collect()
    buckets, scale = np.array([r["bucket"] for r in best]), np.array([r["r"] for r in best])
    held = rows.mapInArrow(_featured(config, buckets), "toxic int, columns binary").toArrow()
    raw, at = K.column_bytes(held.column("columns"))
    columns = np.frombuffer(raw.tobytes(), "<i4").astype(np.int64)
    w, intercept = _regression(columns, at // 4, np.asarray(held.column("toxic")).astype(float), scale, config)
    weights[buckets] = w * scale
    return ToxicityModel(config, intercept, weights)


def _scored(model: ToxicityModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = model.weights != 0
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            score = np.zeros(len(offsets) - 1)
            for i, j in K.slices(offsets):
                text, bucket = present(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], model.config, wanted)
                score[i:j] = np.bincount(text, model.weights[bucket], minlength=j - i)
            score = 1 / (1 + np.exp(-np.clip(score + model.intercept, -60, 60)))
            rest = [n for n in batch.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([batch.column(n) for n in rest] + [pa.array(score)], names=[*rest, "toxicity"])

    return run


def score(docs: DataFrame, model: ToxicityModel, keep_text: bool = False) -> DataFrame:
    """All columns of docs but `text` (unless kept) with `toxicity`, from 0 to 1."""
    docs = docs.drop("toxicity")
    source = docs.drop("tox_text").withColumn("tox_text", F.col("text")) if keep_text else docs
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name != "text"]
    out = source.mapInArrow(_scored(model), ", ".join([*kinds, "toxicity double"]))
    return out.withColumnRenamed("tox_text", "text").select(*[c for c in docs.columns if c != "tox_text"], "toxicity") if keep_text else out


def held_out(doc_id: Column) -> Column:
    """The rows that no model learns from: crc32 of the id as text is divisible by 5."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))
