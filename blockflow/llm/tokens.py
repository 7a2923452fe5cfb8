"""Token ids of whole texts by a tokenizer file of the tokenizers library.

A text is cut where the tokenizer cuts it in any case, the distinct pieces of a slice of texts are encoded by the library
once, and the ids are put together in order. A worker keeps what it has encoded up to a bound, beyond which pieces that came
once are forgotten; so frequent pieces are encoded once per worker. Pieces of one kind of plain characters go to the library
many at a time, with a separator that it cuts at in any case; where the cuts in its answer don't fit the pieces, each is
encoded alone. Where a piece holds anything but plain letters, digits and signs, it stays in one with its
neighbours between white space and the library decides on it as a whole; so the ids are those of the whole text.

Two kinds of tokenizer files can be cut: byte-level ones whose words take one space in front, and word-end ones that drop
white space. Any other file is refused.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np

from blockflow.llm import kernels as K

U64 = np.uint64
#: Encoded pieces that a worker keeps, at about 60 bytes each.
KEEP = 1_000_000
#: Pieces that the library gets as one text.
JOINED = 200

_OTHER, _LETTER, _DIGIT, _SIGN, _WHITE, _LEAD = range(6)
_CLASS = np.zeros(256, np.uint8)
_CLASS[33:127] = _SIGN
_CLASS[48:58] = _DIGIT
_CLASS[65:91] = _CLASS[97:123] = _LETTER
_CLASS[K.WHITE] = _WHITE
_CLASS[ord("'")] = _OTHER
_CLASS[ord("<")] = _OTHER
#: Lead byte of the Latin letters from U+00C0 to U+00FF.
_LATIN = 0xC3
#: Second bytes of the two signs among those.
_NOT_LETTERS = (0x97, 0xB7)
#: Lead bytes of characters of which some are white space.
_WIDE_WHITE = np.zeros(256, bool)
_WIDE_WHITE[[0xC2, 0xE1, 0xE2, 0xE3]] = True


def _classes(data: np.ndarray) -> np.ndarray:
    kind = _CLASS[data]
    lead = np.flatnonzero(data[:-1] == _LATIN)
    if not len(lead):
        return kind
    tail = data[lead + 1]
    fine = lead[(tail >= 0x80) & (tail < 0xC0) & (tail != _NOT_LETTERS[0]) & (tail != _NOT_LETTERS[1])]
    kind[fine] = kind[fine + 1] = _LETTER
    return kind


class PieceTable:
    """Open addressing from 64-bit hashes to places, for whole arrays at once."""

    def __init__(self, size: int):
        self.bits = max(10, (2 * size - 1).bit_length())
        self.keys = np.zeros(1 << self.bits, U64)
        self.places = np.zeros(1 << self.bits, np.int32)

    def _slots(self, hashes: np.ndarray) -> np.ndarray:
        return (hashes >> U64(64 - self.bits)).astype(np.int64)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The place of each hash, -1 where it is unknown; 0 is no hash."""
        slot = self._slots(hashes)
        held = self.keys[slot]
        out = np.where(held == hashes, self.places[slot], np.int32(-1))
        left = np.flatnonzero((held != hashes) & (held != 0))
        mask = len(self.keys) - 1
        slot = slot[left]
        while len(left):
            slot = (slot + 1) & mask
            held = self.keys[slot]
            hit = held == hashes[left]
            out[left[hit]] = self.places[slot[hit]]
            on = ~hit & (held != 0)
            left, slot = left[on], slot[on]
        return out

    def put(self, hashes: np.ndarray, places: np.ndarray) -> None:
        """Add distinct hashes that aren't in the table."""
        slot, mask = self._slots(hashes), len(self.keys) - 1
        while len(hashes):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = hashes[free]
            won = free & (self.keys[slot] == hashes)
            self.places[slot[won]] = places[won]
            hashes, places, slot = hashes[~won], places[~won], (slot[~won] + 1) & mask


class PieceEncoder:
    """Encodes texts; one per worker and tokenizer file."""

    def __init__(self, path: str, keep: int = KEEP):
        # one thread a worker: the tasks of an executor share its cores
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        config = json.load(open(path))
        model = config["model"]
        self.word_end = model.get("end_of_word_suffix") == "</w>" and config["pre_tokenizer"]["type"] == "Sequence"
        spaced = config["pre_tokenizer"]["type"] == "ByteLevel" and not config["normalizer"] and not config["pre_tokenizer"]["add_prefix_space"]
        if not (self.word_end or spaced) or config["post_processor"] and not spaced:
            raise ValueError("texts for this tokenizer file can't be cut into pieces")
        self.size = self.tokenizer.get_vocab_size()
        self.dtype = np.dtype(np.uint16 if self.size <= 1 << 16 else np.uint32)
        self.keep = keep
        #: Ids that end a piece of joined ones: those with the word end, or that of the line feed between pieces.
        self.stops = np.zeros(self.size, bool)
        if self.word_end:
            self.stops[[i for x, i in self.tokenizer.get_vocab().items() if x.endswith("</w>")]] = True
        else:
            self.stops[self.tokenizer.encode("\n", add_special_tokens=False).ids] = True
        self._start(np.zeros(0, U64), np.zeros(0, np.int64), np.zeros(0, self.dtype))

    def _start(self, hashes: np.ndarray, lengths: np.ndarray, flat: np.ndarray) -> None:
        self.table = PieceTable(self.keep)
        self.hashes, self.again = np.zeros(self.keep, U64), np.zeros(self.keep, bool)
        self.starts, self.lengths = np.zeros(self.keep, np.int32), np.zeros(self.keep, np.int32)
        self.flat = np.zeros(4 * self.keep, self.dtype)
        self.held = self.used = 0
        self._add(hashes, lengths, flat)

    def _add(self, hashes: np.ndarray, lengths: np.ndarray, flat: np.ndarray) -> np.ndarray:
        """The places of new pieces."""
        i, j, k = self.held, self.held + len(hashes), self.used + len(flat)
        if k > len(self.flat):
            self.flat = np.append(self.flat[: self.used], np.zeros(k, self.dtype))
        self.flat[self.used : k] = flat
        self.hashes[i:j], self.lengths[i:j] = hashes, lengths
        self.starts[i:j] = self.used + np.cumsum(lengths) - lengths
        places = np.arange(i, j, dtype=np.int32)
        self.table.put(hashes, places)
        self.held, self.used = j, k
        return places

    def _forget(self) -> None:
        """Keep the pieces that came again, unless these alone nearly fill the table."""
        stay = np.flatnonzero(self.again[: self.held])
        if 2 * len(stay) > self.keep:
            stay = stay[:0]
        lengths = self.lengths[stay].astype(np.int64)
        total = np.cumsum(lengths) - lengths
        where = np.repeat(self.starts[stay] - total, lengths) + np.arange(int(lengths.sum()))
        self._start(self.hashes[stay], lengths, self.flat[where])

    def _alone(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        got = [e.ids for e in self.tokenizer.encode_batch_fast(pieces, add_special_tokens=False)]
        counts = np.fromiter(map(len, got), np.int64, len(got))
        return np.array([x for ids in got for x in ids], self.dtype), counts

    def _library(self, pieces: list[str], plain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces in a row, and how many each has."""
        order = np.argsort(~plain, kind="stable")
        n = int(plain.sum())
        runs = [order[i : min(n, i + JOINED)] for i in range(0, n, JOINED)]
        between = " " if self.word_end else "\n"
        flats, counts, done = [], [], []
        for run, e in zip(runs, self.tokenizer.encode_batch_fast([between.join([pieces[k] for k in run.tolist()]) for run in runs], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, self.dtype)
            stop = np.flatnonzero(self.stops[ids])
            if self.word_end:
                size = np.diff(np.append(-1, stop))
                fits = len(stop) == len(run) and int(stop[-1]) == len(ids) - 1
            else:
                size = np.diff(np.concatenate([[-1], stop, [len(ids)]])) - 1
                ids = ids[~self.stops[ids]]
                fits = len(size) == len(run) and int(size.min()) > 0
            if not fits:
                ids, size = self._alone([pieces[k] for k in run.tolist()])
            flats.append(ids)
            counts.append(size)
            done.append(run)
        if n < len(pieces):
            rest = order[n:]
            ids, size = self._alone([pieces[k] for k in rest.tolist()])
            flats.append(ids)
            counts.append(size)
            done.append(rest)
        flat, size, place = np.concatenate(flats), np.concatenate(counts), np.concatenate(done)
        begin = np.zeros(len(pieces), np.int64)
        length = np.zeros(len(pieces), np.int64)
        begin[place], length[place] = np.cumsum(size) - size, size
        total = np.cumsum(length) - length
        return flat[np.repeat(begin - total, length) + np.arange(len(flat))], length

    def _cuts(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Begin and end of each piece; the bytes to hash (folded, where case is dropped); which bytes are of plain pieces."""
        n = len(data)
        kind = _classes(data)
        white = kind == _WHITE
        after = np.append(True, white[:-1])
        first = np.zeros(n + 1, bool)
        first[offsets] = True
        first = first[:n]
        # a chunk begins where white space follows anything else, unless that may be white space of another kind
        chunk = white & ~after
        lead = np.flatnonzero(_WIDE_WHITE[data])
        if len(lead):
            wide = np.zeros(n + 3, bool)
            for back in (2, 3):
                wide[lead + back] |= np.append(data, np.zeros(3, np.uint8))[lead + back - 1] >= 0x80
            chunk &= ~wide[:n]
        chunk |= first
        heads = np.flatnonzero(chunk)
        owner = np.cumsum(chunk) - 1
        # chunks of plain characters with at most one white character in front are cut further
        odd = kind == _OTHER
        odd[1:] |= white[1:] & white[:-1] & ~first[1:]
        odd_chunk = np.zeros(len(heads), bool)
        odd_chunk[owner[odd]] = True
        # a trailing white character of a text has nothing to stand in front of
        last = np.flatnonzero(white & np.append(chunk[1:], True))
        odd_chunk[owner[last]] = True
        plain = ~odd_chunk[owner] if n else np.zeros(0, bool)
        change = np.zeros(n, bool)
        if n > 1:
            change[1:] = kind[1:] != kind[:-1]
            if self.word_end:
                change[1:] |= (kind[1:] == _DIGIT)
            else:
                change[1:] &= ~((kind[:-1] == _WHITE) & (data[:-1] == 32))
        begin = chunk | (change & plain)
        starts = np.flatnonzero(begin)
        ends = np.append(starts[1:], n)
        if self.word_end:
            # white space gives nothing; a plain piece without its white space is the same anywhere
            drop = white[starts] & plain[starts]
            starts, ends = starts[~drop], ends[~drop]
            low = K.LOWER[data]
            lead = np.flatnonzero((data[:-1] == _LATIN) & (kind[:-1] == _LETTER)) + 1 if n > 1 else np.zeros(0, int)
            upper = lead[(low[lead] >= 0x80) & (low[lead] < 0x9F)]
            low[upper] += 0x20
            return starts, ends, np.where(plain, low, data), plain
        return starts, ends, data, plain

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the texts in a row, and where each text's begin (one more element)."""
        starts, ends, basis, plain = self._cuts(data, offsets)
        if not len(starts):
            return np.zeros(0, self.dtype), np.zeros(len(offsets), np.int64)
        hashes = K.span_hash(K.prefix_hash(basis), starts, ends)
        hashes[hashes == 0] = 1
        piece = self.table.find(hashes)
        self.again[piece[piece >= 0]] = True
        new = np.flatnonzero(piece < 0)
        if len(new):
            distinct, head, inverse = np.unique(hashes[new], return_index=True, return_inverse=True)
            if self.held + len(distinct) > self.keep:
                if len(distinct) > self.keep // 2:
                    self.keep = 4 * len(distinct)
                self._forget()
                return self.encode(data, offsets)
            raw, at = basis.tobytes(), new[head]
            pieces = [raw[s:e].decode() for s, e in zip(starts[at].tolist(), ends[at].tolist(), strict=True)]
            flat, length = self._library(pieces, plain[starts[at]])
            piece[new] = self._add(distinct, length, flat)[inverse]
        counts = self.lengths[piece]
        total = np.append(0, np.cumsum(counts))
        where = np.repeat(self.starts[piece] - total[:-1], counts) + np.arange(total[-1])
        return self.flat[where], total[np.searchsorted(starts, offsets, "left")]


@lru_cache(maxsize=4)
def encoder(path: str) -> PieceEncoder:
    return PieceEncoder(path)
