"""Packing documents into sequences of a fixed window by non-negative least squares over length combinations.

Each range partition of documents is packed on its own. Whole windows are cut off long documents first and stand alone. The
rest of every document has a length below the window, counted in a histogram of units. All combinations of up to `depth`
units that fill a window are enumerated, and non-negative least squares finds how often each should be used to use up the
histogram. Rounded down, these repeats take documents from the histogram; the residual documents go, longest first, where
they leave the least room. What room is left is filled by cutting up the emptiest sequences, unless a gap is smaller than
`least_gap`.

Defined cases: a null or empty text gives its end id alone; rows that repeat a doc_id are packed one by one; an empty table
gives no pieces; a document of any length is cut into windows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from blockflow.llm import kernels as K
from blockflow.llm.ordered import ranged
from blockflow.llm.tokens import encoder

WINDOW = 2048
#: Units of a window in the histogram, and lengths in a combination.
UNITS, DEPTH = 64, 3
LEAST_GAP = 12


def combinations(units: int = UNITS, depth: int = DEPTH) -> list[tuple[int, ...]]:
    """All non-increasing tuples of up to `depth` lengths that add up to `units`."""

    def parts(left: int, most: int, places: int) -> Iterator[tuple[int, ...]]:
        if left == 0:
            yield ()
        elif places:
            for x in range(min(left, most), 0, -1):
                if x * places < left:
                    break
                for tail in parts(left - x, x, places - 1):
                    yield (x, *tail)

    return list(parts(units, units, depth))


def nonnegative_least_squares(a: np.ndarray, b: np.ndarray, rounds: int = 400) -> np.ndarray:
    """x >= 0 with the least |a x - b|, by an active set of columns."""
    x = np.zeros(a.shape[1])
    active = np.zeros(a.shape[1], bool)
    scale = max(1.0, float(np.abs(b).max(initial=0)))
    for _ in range(rounds):
        slope = a.T @ (b - a @ x)
        slope[active] = -np.inf
        if slope.max() <= 1e-9 * scale:
            break
        active[int(slope.argmax())] = True
        for _ in range(a.shape[1]):
            cols = np.flatnonzero(active)
            z = np.linalg.lstsq(a[:, cols], b, rcond=None)[0]
            if z.min(initial=1) > 1e-12:
                break
            down = z <= 1e-12
            step = (x[cols][down] / np.maximum(x[cols][down] - z[down], 1e-300)).min()
            moved = x[cols] + min(1.0, max(0.0, float(step))) * (z - x[cols])
            moved[moved <= 1e-12] = 0
            x[:] = 0
            x[cols] = moved
            active[cols[moved == 0]] = False
        x[:] = 0
        x[cols] = np.maximum(z, 0)
    return x


def pack(lengths: np.ndarray, window: int = WINDOW, units: int = UNITS, depth: int = DEPTH, least_gap: int = LEAST_GAP) -> list[list[tuple[int, int, int]]]:
    """Sequences of (document, start, length) that hold every id of every document once."""
    sequences: list[list[tuple[int, int, int]]] = []
    rest: list[tuple[int, int]] = []
    for d, n in enumerate(lengths.tolist()):
        whole = n // window
        sequences += [[(d, k * window, window)] for k in range(whole)]
        if n % window:
            rest.append((n % window, d))
    alone = len(sequences)
    unit = window // units
    bins: list[list[tuple[int, int]]] = [[] for _ in range(units + 1)]
    for n, d in sorted(rest):
        bins[-(-n // unit)].append((n, d))
    ways = combinations(units, depth)
    a = np.zeros((units, len(ways)))
    for k, way in enumerate(ways):
        for u in way:
            a[u - 1, k] += 1
    times = np.floor(nonnegative_least_squares(a, np.array([len(x) for x in bins[1:]], float)) + 1e-9).astype(int)
    room: list[int] = []
    open_: list[list[tuple[int, int, int]]] = []

    def put(k: int, n: int, d: int, start: int) -> None:
        open_[k].append((d, start, n))
        room[k] -= n

    begin = lambda n, d: int(lengths[d]) - n
    for way, n_times in zip(ways, times.tolist(), strict=True):
        for _ in range(n_times):
            if any(len(bins[u]) < way.count(u) for u in set(way)):
                break
            open_.append([])
            room.append(window)
            for u in way:
                n, d = bins[u].pop()
                put(len(open_) - 1, n, d, begin(n, d))
    by_room: list[list[int]] = [[] for _ in range(window + 1)]
    for k, r in enumerate(room):
        by_room[r].append(k)
    filled = np.array([bool(x) for x in by_room])
    for n, d in sorted((x for held in bins for x in held), reverse=True):
        ahead = filled[n:]
        at = int(ahead.argmax()) if len(ahead) else 0
        if len(ahead) and ahead[at]:
            k = by_room[n + at].pop()
            filled[n + at] = bool(by_room[n + at])
        else:
            k = len(open_)
            open_.append([])
            room.append(window)
        put(k, n, d, begin(n, d))
        by_room[room[k]].append(k)
        filled[room[k]] = True
    # cut up the emptiest sequences to fill the room of the others
    order = sorted(range(len(open_)), key=lambda k: room[k])
    gaps = [k for k in order if room[k] >= least_gap]
    spare = sum(room[k] for k in gaps)
    i = 0
    while i < len(gaps) - 1:
        last = gaps[-1]
        used = window - room[last]
        if spare - room[last] < used:
            break
        gaps.pop()
        spare -= room[last]
        pieces, open_[last] = open_[last], []
        for d, start, n in pieces:
            while n:
                k = gaps[i]
                if room[k] == 0:
                    i += 1
                    continue
                cut = min(n, room[k])
                put(k, cut, d, start)
                spare -= cut
                start, n = start + cut, n - cut
    return sequences[:alone] + [s for s in open_ if s]


def _packed(tokenizer: str, end_id: int, window: int):
    from pyspark import TaskContext

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part = encoder(tokenizer), TaskContext.get().partitionId()
        names, lengths, kept = [], [], []
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            names.append(batch.column("doc_id"))
            for i, j in K.slices(offsets):
                ids, at = enc.encode(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                kept.append(np.insert(ids, at[1:], ids.dtype.type(end_id)))
                lengths.append(np.diff(at) + 1)
        if not lengths:
            return
        count, ids = np.concatenate(lengths), np.concatenate(kept)
        first = np.cumsum(count) - count
        rows = [(d, start, n, s, at) for s, held in enumerate(pack(count, window)) for (d, start, n), at in zip(held, np.cumsum([0] + [x[2] for x in held]).tolist(), strict=False)]
        d, start, n, s, at = (np.array(x, np.int64) for x in zip(*rows, strict=True))
        crc = [zlib.crc32(ids[a : a + m].astype("<u4").tobytes()) for a, m in zip((first[d] + start).tolist(), n.tolist(), strict=True)]
        owners = pa.chunked_array(names).combine_chunks().take(pa.array(d))
        yield pa.RecordBatch.from_arrays(
            [owners, pa.array(start), pa.array(n), pa.array(crc, pa.int64()), pa.array(count[d].astype(np.int64)), pa.array(s + (part << 32)), pa.array(at)],
            names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"],
        )

    return run


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int, window: int = WINDOW) -> DataFrame:
    """One row for each piece; a sequence_id holds the partition above 32 bits and the place below."""
    return ranged(docs, "text").mapInArrow(_packed(tokenizer, end_id, window), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
