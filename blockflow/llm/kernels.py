"""Vectorised kernels over the raw UTF-8 bytes of many texts at once.

All work on a byte buffer in which texts lie one after another, with the offsets where they begin and end, as Arrow
stores them; no text is ever turned into a Python string here. Temporary arrays are as long as the buffer, so callers
hand over bounded slices (see slices()).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
#: Odd base of the rolling hashes, which work modulo 2**64, and its inverse.
BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(BASE, -1, 1 << 64)
#: Bytes of a slice, unless one text alone is longer; its temporary arrays stay near the caches.
SLICE = 1 << 19

_powers: list[np.ndarray] = [np.ones(1, U64), np.ones(1, U64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and BASE**-i for i < n, modulo 2**64."""
    if len(_powers[0]) < n:
        size = 1 << max(16, (n - 1).bit_length())
        for k, base in enumerate((BASE, _INVERSE)):
            steps = np.full(size, base, U64)
            steps[0] = 1
            _powers[k] = np.cumprod(steps, dtype=U64)
    return _powers[0][:n], _powers[1][:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def column_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes and offsets of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def slices(offsets: np.ndarray, size: int = SLICE) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about `size` bytes together."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1
        j = min(n, max(j, i + 1))
        yield i, j
        i = j


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """Sums of (byte + 1) * BASE**i, with a leading 0; one more element than data."""
    out = np.zeros(len(data) + 1, U64)
    if len(data):
        np.cumsum((data.astype(U64) + U64(1)) * powers(len(data))[0], dtype=U64, out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of data[start:end], the same for the same bytes wherever they lie."""
    return mix((prefix[end] - prefix[start]) * powers(len(prefix))[1][start] + (end - start).astype(U64) * U64(0xD6E8FEB86659FD93))


def _class_table(chars: bytes, inside: bool) -> np.ndarray:
    table = np.full(256, not inside)
    table[list(chars)] = inside
    return table


WHITE = _class_table(b" \t\n\x0b\x0c\r", True)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def word_spans(data: np.ndarray, offsets: np.ndarray, white: np.ndarray = WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of every word, and for each text the number of words before it (one more element)."""
    word = np.append(~white[data], False)
    cut = np.zeros(len(data) + 1, bool)
    cut[offsets] = True
    before = np.append(False, word[:-1])
    starts = np.flatnonzero(word & (~before | cut))
    ends = np.flatnonzero(before & (~word | cut))
    return starts, ends, np.searchsorted(starts, offsets, "left")


#: Odd factors of the words of a shingle by place.
_PLACES = mix(np.arange(1, 65, dtype=U64)) | U64(1)


def shingles(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of `width` lower-cased words of each text, and the offsets of each text's run.

    A text with fewer words gives one for its whole sequence; one without words none.
    """
    low = LOWER[data]
    starts, ends, first = word_spans(low, offsets)
    words = span_hash(prefix_hash(low), starts, ends)
    count = np.diff(first)
    full = np.maximum(count - width + 1, (count > 0).astype(np.int64))
    at = np.append(0, np.cumsum(full))
    owner = np.repeat(np.arange(len(count)), full)
    place = first[:-1][owner] + np.arange(at[-1]) - at[:-1][owner]
    out = np.zeros(len(place), U64)
    padded = np.append(words, np.zeros(width, U64))
    left = np.minimum(count[owner], width)
    for k in range(width):
        out += np.where(k < left, padded[place + k] * _PLACES[k], U64(0))
    return mix(out + left.astype(U64)), at


def distinct_sorted(values: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's values sorted, without repeats."""
    values, edges = values.copy(), at.tolist()
    for a, b in zip(edges, edges[1:], strict=False):
        if b - a > 1:
            values[a:b].sort()
    keep = np.ones(len(values), bool)
    keep[1:] = values[1:] != values[:-1]
    keep[at[:-1][at[:-1] < len(values)]] = True
    return values[keep], np.append(0, np.cumsum(keep))[at]
