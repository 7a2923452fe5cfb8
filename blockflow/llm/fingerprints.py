"""Document fingerprints of statistically improbable byte windows in chained Bloom filters.

A text of 256 bytes or more has windows of 64 bytes, one under 2048 bytes has windows of 16 bytes as well or instead; the
two scales are kept apart. Each window has an entropy, scaled to 0..1000. How often each value occurs in the corpus gives its
rarity, and a window's rank is the place of its entropy in order of rarity, rarest first; windows of very low entropy are
left out. Among each run of neighbouring windows, as many as a window has bytes, the best-ranked (leftmost of equals) gains
a point, and windows with points of a quarter of a run, or an eighth at the small scale, are the features. A feature sets 5 bits of a Bloom filter of 2048 bits; after 160 features the next filter
of the chain begins. Two fingerprints are compared filter by filter: the overlap of set bits beyond what chance gives, as a
share of the most possible; the mean over the shorter chain's best matches is the likeness at a scale, and the best of the
scales that both texts have is the likeness.

Defined cases: null is the empty text; an empty text has an empty fingerprint, which is like another empty one (1) and unlike
all else (0); a text shorter than a window of its scale is one feature; where no window has enough points, the one with most is the
feature; equal texts have equal fingerprints, of likeness 1; repeated rows stand next to each other in doc_id order; rows
without doc_id come first; the next document of the last is the first, so a lone document is its own next.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockflow.llm import kernels as K
from blockflow.llm.ordered import RANGE_BYTES, estimated_bytes

U64 = np.uint64
#: Bytes of a window (and windows of a run), and points that make a feature: for long and for short texts.
SCALES = ((64, 16), (16, 2))
#: Bytes from which, and below which, a text has a scale.
REACH = ((256, 1 << 62), (0, 2048))
LEVELS = 1001
#: Windows below this scaled entropy are never features.
LEAST = 100
BITS, HASHES, MOST = 2048, 5, 160
CHANCE = 0.3
NO_ID = -(1 << 63)

_counts = np.arange(SCALES[0][0] + 1)
_terms = np.round(_counts * np.log2(np.maximum(_counts, 1)) * (1 << 20)).astype(np.int64)
#: What one more of c equal bytes adds to the sum of c * log2(c), in 2**-20.
_GAIN = np.append(np.diff(_terms), 0)


def entropies(data: np.ndarray, offsets: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """Scaled entropy of the window beginning at each byte, and where a window fits into its text."""
    n = len(data)
    start = np.repeat(offsets[:-1], np.diff(offsets))
    depth = np.minimum(np.arange(n) - start, 255).astype(np.uint8)
    before, after = np.zeros(n, np.uint8), np.zeros(n, np.uint8)
    for lag in range(1, min(span, n)):
        same = (data[lag:] == data[:-lag]) & (depth[lag:] >= lag)
        before[lag:] += same
        after[:-lag] += same
    gained = np.append(0, np.cumsum(_GAIN[before]))
    lost = np.append(0, np.cumsum(_GAIN[after]))
    fits = np.zeros(n, bool)
    whole = np.repeat(offsets[1:], np.diff(offsets)) - span >= np.arange(n)
    fits[whole] = True
    at = np.flatnonzero(fits)
    total = gained[at + span] - gained[start[at]] - (lost[at] - lost[start[at]])
    scaled = np.zeros(n, np.int64)
    full = int(_terms[span])
    scaled[at] = np.clip((full - total) * 1000 // full, 0, 1000)
    return scaled, fits


def _of_scale(data: np.ndarray, offsets: np.ndarray, scale: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers, bytes and offsets of the texts that have a scale."""
    lengths = np.diff(offsets)
    mine = (lengths >= REACH[scale][0]) & (lengths < REACH[scale][1])
    return np.flatnonzero(mine), data[np.repeat(mine, lengths)], np.append(0, np.cumsum(lengths[mine]))


def _selected(data: np.ndarray, offsets: np.ndarray, order: np.ndarray, span: int, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the features in place order, and where each text's begin."""
    n, texts = len(data), len(offsets) - 1
    if not n:
        return np.zeros(0, U64), np.zeros(texts + 1, np.int64)
    scaled, fits = entropies(data, offsets, span)
    low = max(24, n.bit_length())
    mask = U64((1 << low) - 1)
    rank = np.where(fits & (scaled >= LEAST), order[scaled], LEVELS + 1).astype(U64)
    keys = np.full(-(-n // span) * span + span, ~U64(0))
    keys[:n] = (rank << U64(low)) | np.arange(n, dtype=U64)
    blocks = keys.reshape(-1, span)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    # all runs of windows that lie in one text; where a text has too few windows, the run of them all
    lengths = np.diff(offsets)
    windows = np.maximum(lengths - span + 1, 0)
    runs = np.where(windows > 0, np.maximum(windows - span + 1, 1), 0)
    owner = np.repeat(np.arange(texts), runs)
    begin = offsets[:-1][owner] + np.arange(runs.sum()) - (np.cumsum(runs) - runs)[owner]
    best = np.minimum(behind[begin], ahead[begin + span - 1])
    for k in np.flatnonzero(windows[owner] < span):
        best[k] = keys[begin[k] : begin[k] + windows[owner[k]]].min()
    place = (best & mask).astype(np.int64)[(best >> U64(low)) <= LEVELS]
    points = np.bincount(place, minlength=n)
    starts = np.flatnonzero(points >= least)
    ends = starts + span
    none = np.flatnonzero((np.searchsorted(starts, offsets[1:]) == np.searchsorted(starts, offsets[:-1])) & (lengths > 0))
    a, b = offsets[none], offsets[none + 1]
    most = np.array([x if y - x < span else x + int(points[x : y - span + 1].argmax()) for x, y in zip(a.tolist(), b.tolist(), strict=True)], np.int64)
    starts, ends = np.append(starts, most), np.append(ends, np.minimum(most + span, b))
    by_place = np.argsort(starts, kind="stable")
    starts, ends = starts[by_place], ends[by_place]
    return K.span_hash(K.prefix_hash(data), starts, ends), np.searchsorted(starts, offsets, "left")


Chains = tuple[np.ndarray, ...]


def features(data: np.ndarray, offsets: np.ndarray, orders: np.ndarray) -> list[list[np.ndarray]]:
    """Each text's 64-bit feature hashes by scale; orders has the rank by scaled entropy for each scale."""
    out: list = [[np.zeros(0, U64)] * len(SCALES) for _ in range(len(offsets) - 1)]
    for scale, (span, least) in enumerate(SCALES):
        texts, part, at = _of_scale(data, offsets, scale)
        hashes, edges = _selected(part, at, orders[scale], span, least)
        for k, t in enumerate(texts.tolist()):
            out[t][scale] = hashes[edges[k] : edges[k + 1]]
    return out


def filters(hashes: np.ndarray) -> np.ndarray:
    """The chain of Bloom filters, one row of bits each. A feature that repeats is set once."""
    _, first = np.unique(hashes, return_index=True)
    hashes = hashes[np.sort(first)]
    out = np.zeros((-(-len(hashes) // MOST), BITS), bool)
    row = np.arange(len(hashes)) // MOST
    for k in range(HASHES):
        out[row, (K.mix(hashes + U64(k + 1)) >> U64(53)).astype(np.int64)] = True
    return out


def to_text(chains: Chains) -> str:
    """Number of filters by scale, and the bits in base 64, parted by colons."""
    return ":".join([*(str(len(c)) for c in chains), base64.b64encode(np.packbits(np.concatenate(chains)).tobytes()).decode()])


def from_text(digest: str) -> Chains:
    *sizes, body = digest.split(":")
    bits = np.unpackbits(np.frombuffer(base64.b64decode(body), np.uint8)).astype(bool).reshape(-1, BITS)
    return tuple(np.split(bits, np.cumsum([int(n) for n in sizes])[:-1]))


def likeness(x: Chains, y: Chains) -> float:
    """From 0 to 1; see the module's text."""
    if not any(map(len, x)) or not any(map(len, y)):
        return float(any(map(len, x)) == any(map(len, y)))
    return max((_alike(a, b) for a, b in zip(x, y, strict=True) if len(a) and len(b)), default=0.0)


def _alike(x: np.ndarray, y: np.ndarray) -> float:
    if x.shape == y.shape and np.array_equal(x, y):
        return 1.0
    if len(x) > len(y):
        x, y = y, x
    a, b = x.sum(axis=1)[:, None].astype(float), y.sum(axis=1)[None, :].astype(float)
    both = x.astype(np.float32) @ y.T.astype(np.float32)
    most, chance = np.minimum(a, b), a * b / BITS
    floor = CHANCE * (most - chance) + chance
    share = np.where(most > floor, (both - floor) / np.maximum(most - floor, 1e-9), 0.0)
    return float(np.clip(share, 0, 1).max(axis=1).mean())


def _tallied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros((len(SCALES), LEVELS), np.int64)
    for batch in batches:
        data, offsets = K.column_bytes(batch.column("text"))
        for i, j in K.slices(offsets, 1 << 18):
            for scale, (span, _) in enumerate(SCALES):
                _, part, at = _of_scale(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], scale)
                scaled, fits = entropies(part, at, span)
                total[scale] += np.bincount(scaled[fits], minlength=LEVELS)
    used = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(total.ravel()[used])], names=["level", "n"])


def rarity_orders(docs: DataFrame) -> np.ndarray:
    """For each scale the place of each scaled entropy in order of rarity over all windows; what never occurs comes last."""
    total = np.zeros((len(SCALES), LEVELS), np.int64)
    for row in docs.select("text").mapInArrow(_tallied, "level long, n long").groupBy("level").agg(F.sum("n").alias("n")).collect():
        total.ravel()[row["level"]] = row["n"]
    rank = np.full(total.shape, LEVELS, np.int64)
    for scale, counts in enumerate(total):
        order = np.lexsort((np.arange(LEVELS), counts))
        order = order[counts[order] > 0]
        rank[scale][order] = np.arange(len(order))
    return rank


def _dealt(bounds: np.ndarray):
    """Each row to its range; the first of a range also to the end of the range before, the very first to the last range."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = np.asarray(batch.column("doc_id").fill_null(NO_ID))
            part = np.searchsorted(bounds, ids, "right") - 1
            edge = np.flatnonzero(bounds[part] == ids)
            rows = np.append(np.arange(len(ids)), edge)
            to = np.append(part, (part[edge] - 1) % len(bounds)).astype(np.int32)
            tail = np.append(np.zeros(len(ids), bool), np.ones(len(edge), bool))
            picked = pa.array(rows)
            yield pa.RecordBatch.from_arrays([pa.array(to), pa.array(tail), batch.column("doc_id").take(picked), batch.column("text").take(picked)], names=["part", "tail", "doc_id", "text"])

    return run


def with_next(docs: DataFrame) -> DataFrame:
    """Rows (part, tail, doc_id, text) such that, in the order of the first three, each row that is no tail precedes the next document's."""
    ids = docs.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"))
    spark = docs.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-estimated_bytes(docs.select("text")) // RANGE_BYTES))
    shares = [k / parts for k in range(1, parts)] or [0.5]
    row = ids.agg(F.min("doc_id").alias("low"), F.percentile_approx("doc_id", shares, max(10_000, 10 * parts)).alias("cuts")).first()
    bounds = np.unique(np.array([NO_ID if row["low"] is None else row["low"], *(row["cuts"] or [])], np.int64))
    dealt = docs.select("doc_id", "text").mapInArrow(_dealt(bounds), "part int, tail boolean, doc_id long, text string")
    return dealt.repartition(parts, "part").sortWithinPartitions("part", "tail", "doc_id")


def _half(text: str, after: str) -> str:
    cut = len(text) // 2
    return text[: len(text) - cut] + after[:cut]


def _digested(orders: np.ndarray):
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]

    def chains(texts: list[str]) -> list[Chains]:
        data, offsets = K.column_bytes(pa.array(texts, pa.string()))
        out: list[Chains] = []
        for i, j in K.slices(offsets, 1 << 18):
            out += [tuple(map(filters, h)) for h in features(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], orders)]
        return out

    def compared(rows: list[tuple]) -> pa.RecordBatch:
        """rows: (doc_id, text, next text), where the next text is the next row's own but at the end of a part."""
        edited = [_half(t, after) for _, t, after in rows]
        own, other = chains([t for _, t, _ in rows]), chains(edited)
        alone = [k for k, (_, _, after) in enumerate(rows) if k + 1 == len(rows) or rows[k + 1][1] is not after]
        follow = dict(zip(alone, chains([rows[k][2] for k in alone]), strict=True))
        near = [likeness(own[k], follow[k] if k in follow else own[k + 1]) for k in range(len(rows))]
        columns = [
            [r[0] for r in rows], [len(r[1]) for r in rows], [hashlib.sha256(e.encode()).hexdigest() for e in edited],
            [to_text(c) for c in own], [to_text(c) for c in other], [likeness(a, b) for a, b in zip(own, other, strict=True)], near,
        ]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, last = [], 0, None
        for batch in batches:
            for part, tail, doc, text in zip(*[batch.column(k) for k in ("part", "tail", "doc_id", "text")], strict=True):
                part, tail, text = part.as_py(), tail.as_py(), text.as_py() or ""
                if last is not None and last[0] == part:
                    held.append((last[1], last[2], text))
                    size += len(text)
                    if size > 1 << 20:
                        yield compared(held)
                        held, size = [], 0
                    last = None if tail else (part, doc.as_py(), text)
                elif not tail:
                    last = (part, doc.as_py(), text)
        if held:
            yield compared(held)

    return run


def fingerprint_pairs(docs: DataFrame) -> DataFrame:
    """Each document's fingerprint, that of its edited text, and how alike they and the next document's are."""
    orders = rarity_orders(docs)
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return with_next(docs).mapInArrow(_digested(orders), schema)
