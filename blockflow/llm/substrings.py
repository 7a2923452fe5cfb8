"""Removal of repeated byte strings by prefix-free parsing of the corpus.

Parsing. A rolling hash over k bytes triggers where it is the smallest of the hashes of all k-byte strings of a window of
`size` bytes, so every string of `size` bytes holds a trigger, and equal strings hold it at the same place. The window
starts between two changes of the trigger form a phrase: the bytes from its first window start to the end of its last
window. Neighbouring phrases overlap, no phrase's windows can occur in phrases of another trigger, and a window occurs at
the same distance before the trigger wherever it occurs.

Dictionary and parse. The parse of the corpus is its list of (trigger, phrase, text, start). Partitioned by trigger, it
gives the dictionary of distinct phrases with their first occurrence; every later occurrence repeats in full. Only phrases
that share their trigger with other phrases still need the order of their suffixes.

Suffix array. For those, the phrases' bytes are fetched once for the dictionary entry, and the dictionary's suffixes, cut to
`size` bytes, are put in order letter by letter, by doubling. Equal windows share a rank, and the first occurrences of the
parse put the windows of a rank into corpus order. The parse itself needs no suffix array: phrases overlap by a window less
a byte, so every window lies within one phrase, and what follows a phrase never decides.

Phrases count as equal where their 64-bit hashes agree, windows where their bytes do. Matches never cross documents.

Memory. A task holds one partition of the parse at 36 bytes an entry; each map task keeps one entry of a phrase, so a
phrase that a third of all documents repeat gives as many entries as there are map batches.

Defined cases: null text is empty; shorter texts than `size` lose nothing; rows without doc_id give no matches and stay as
they are; rows that repeat a doc_id with the same text share its first occurrence, so none of them counts as a repeat of
another; other texts under the same doc_id (told apart by CRC-32) are documents of their own, in the order of their CRC-32; an empty table gives an
empty result; columns named like an output are replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockflow.llm import kernels as K
from blockflow.llm.ordered import estimated_bytes
from blockflow.session import drop_shuffles, materialize

U64 = np.uint64
#: Length of a repeated string, and of the trigger strings.
SIZE, GRAM = 100, 24
#: Input bytes (as Spark estimates them) for each partition of the parse.
PART_BYTES = 12 << 20
#: Bytes of the dictionary whose suffixes are put in order at once; a trigger with more is taken whole.
SORTED = 2 << 20
#: A parse entry; n counts window starts, and (doc, tag) stands for a text.
ENTRY = np.dtype([("trigger", "<u8"), ("phrase", "<u8"), ("doc", "<i8"), ("tag", "<u4"), ("start", "<i4"), ("n", "<i2"), ("before", "<i2")])
#: A span of window starts of a document.
SPAN = np.dtype([("start", "<i4"), ("n", "<i4")])
#: A dictionary entry whose bytes are wanted.
WANT = np.dtype([("trigger", "<u8"), ("start", "<i4"), ("n", "<i2")])


def phrases(data: np.ndarray, offsets: np.ndarray, size: int = SIZE, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """text number, start in the buffer, count of window starts, trigger place less start, trigger and phrase hash."""
    n = len(data)
    windows = n - size + 1
    if windows <= 0:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, U64, U64))
    prefix = K.prefix_hash(data)
    grams = n - gram + 1
    at = np.arange(grams)
    hashes = K.span_hash(prefix, at, at + gram)
    low = max(24, n.bit_length())
    mask = U64((1 << low) - 1)
    keys = (hashes & ~mask) | at.astype(U64)
    width = size - gram + 1
    rows = -(-grams // width) + 1
    padded = np.full(rows * width, ~U64(0))
    padded[:grams] = keys
    blocks = padded.reshape(rows, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    trigger = (np.minimum(behind[:windows], ahead[width - 1 : width - 1 + windows]) & mask).astype(np.int64)
    whole = np.zeros(n + 1, np.int32)
    lengths = np.diff(offsets)
    long_ = lengths >= size
    np.add.at(whole, offsets[:-1][long_], 1)
    np.add.at(whole, offsets[1:][long_] - size + 1, -1)
    valid = np.cumsum(whole)[:windows] > 0
    begin = np.zeros(windows + 1, bool)
    begin[0] = True
    begin[1:windows] = trigger[1:] != trigger[:-1]
    begin[np.minimum(offsets[:-1], windows)] = True
    change = np.flatnonzero(valid & begin[:windows])
    stops = begin.copy()
    stops[windows] = True
    stops[1:windows] |= valid[:-1] & ~valid[1:]
    ends = np.flatnonzero(stops)
    end = ends[np.searchsorted(ends, change, "right")]
    place = trigger[change]
    return np.searchsorted(offsets, change, "right") - 1, change, end - change, place - change, hashes[place], K.span_hash(prefix, change, end + size - 1)


def _same_place(entries: np.ndarray, lead: np.ndarray) -> np.ndarray:
    return (entries["doc"] == entries["doc"][lead]) & (entries["tag"] == entries["tag"][lead]) & (entries["start"] == entries["start"][lead])


def _first_of(entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entries by (phrase, doc, tag, start), and which of them are the first of their phrase or tie with it."""
    entries = entries[np.lexsort((entries["start"], entries["tag"], entries["doc"], entries["phrase"]))]
    new = np.ones(len(entries), bool)
    new[1:] = (entries["trigger"][1:] != entries["trigger"][:-1]) | (entries["phrase"][1:] != entries["phrase"][:-1])
    heads = np.flatnonzero(new)
    lead = heads[np.cumsum(new) - 1] if len(entries) else heads
    return entries, _same_place(entries, lead)


def _spans(entries: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
    """Merged spans of window starts for each text: (doc, tag, spans)."""
    if not len(entries):
        return
    entries = entries[np.lexsort((entries["start"], entries["tag"], entries["doc"]))]
    docs, tags, starts = entries["doc"], entries["tag"], entries["start"].astype(np.int64)
    ends = starts + entries["n"]
    other = (docs[1:] != docs[:-1]) | (tags[1:] != tags[:-1])
    cut = np.ones(len(docs), bool)
    cut[1:] = other | (starts[1:] > ends[:-1])
    heads = np.flatnonzero(cut)
    spans = np.zeros(len(heads), SPAN)
    spans["start"] = starts[heads]
    spans["n"] = np.maximum.reduceat(ends, heads) - starts[heads]
    edges = np.append(np.searchsorted(heads, np.flatnonzero(np.append(True, other))), len(heads))
    for i, j in zip(edges[:-1], edges[1:], strict=True):
        yield int(docs[heads[i]]), int(tags[heads[i]]), spans[i:j].tobytes()


_PARSED = "part int, doc_id long, tag long, payload binary"


def _batch(schema: dict, columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, schema.values(), strict=True)], names=list(schema))


def _parse(parts: int, size: int, gram: int):
    schema = {"part": pa.int32(), "doc_id": pa.int64(), "tag": pa.int64(), "payload": pa.binary()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            ids, tags = np.asarray(batch.column("doc_id")), np.asarray(batch.column("tag"))
            found = []
            for i, j in K.slices(offsets):
                text, start, n, before, trigger, phrase = phrases(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], size, gram)
                e = np.zeros(len(start), ENTRY)
                e["trigger"], e["phrase"], e["doc"], e["n"], e["before"] = trigger, phrase, ids[i:j][text], n, before
                e["tag"] = tags[i:j][text]
                e["start"] = start - (offsets[i : j + 1] - offsets[i])[text]
                found.append(e)
            if not found:
                continue
            entries, first = _first_of(np.concatenate(found))
            if local := list(_spans(entries[~first])):
                yield _batch(schema, [[-1] * len(local), *zip(*local, strict=True)])
            kept = entries[first]
            part = (kept["trigger"] % U64(parts)).astype(np.int64)
            # triggers together compress better
            order = np.lexsort((kept["trigger"], part))
            kept, part = kept[order], part[order]
            edges = np.searchsorted(part, np.arange(parts + 1))
            full = np.flatnonzero(np.diff(edges))
            yield _batch(schema, [full, [None] * len(full), [None] * len(full), [kept[edges[p] : edges[p + 1]].tobytes() for p in full]])

    return run


def _by_part(batches: Iterator[pa.RecordBatch], dtype: np.dtype) -> Iterator[tuple[int, np.ndarray]]:
    """The payloads of each part together; a task gets one part."""
    now, held = None, []
    for batch in batches:
        for part, payload in zip(batch.column("part").to_pylist(), batch.column("payload"), strict=True):
            if part != now and held:
                yield now, np.frombuffer(b"".join(held), dtype)
                held = []
            now = part
            held.append(payload.as_py())
    if held:
        yield now, np.frombuffer(b"".join(held), dtype)


#: kind 0: spans of repeated window starts; kind 1: dictionary entries whose bytes are wanted.
_RESOLVED = "kind int, doc_id long, tag long, payload binary"


def _resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = {"kind": pa.int32(), "doc_id": pa.int64(), "tag": pa.int64(), "payload": pa.binary()}
    for _, entries in _by_part(batches, ENTRY):
        entries, first = _first_of(entries)
        rows = [(0, *span) for span in _spans(entries[~first])]
        entries = entries[first]
        # ties of a first occurrence are one dictionary entry
        keep = np.ones(len(entries), bool)
        keep[1:] = (entries["phrase"][1:] != entries["phrase"][:-1]) | (entries["trigger"][1:] != entries["trigger"][:-1])
        entries = entries[keep]
        _, owner, members = np.unique(entries["trigger"], return_inverse=True, return_counts=True)
        entries = entries[members[owner] > 1]
        entries = entries[np.lexsort((entries["tag"], entries["doc"]))]
        other = (entries["doc"][1:] != entries["doc"][:-1]) | (entries["tag"][1:] != entries["tag"][:-1])
        edges = np.append(np.flatnonzero(np.append(len(entries) > 0, other)), len(entries))
        for i, j in zip(edges[:-1], edges[1:], strict=True):
            want = np.zeros(j - i, WANT)
            for k in WANT.names:
                want[k] = entries[k][i:j]
            rows.append((1, int(entries["doc"][i]), int(entries["tag"][i]), want.tobytes()))
        if rows:
            yield _batch(schema, list(zip(*rows, strict=True)))


#: A fetched dictionary entry, followed by its bytes.
HEAD = np.dtype([("trigger", "<u8"), ("doc", "<i8"), ("tag", "<u4"), ("start", "<i4"), ("n", "<i2")])
#: A window of an entry.
WINDOW = np.dtype([("doc", "<i8"), ("tag", "<u4"), ("start", "<i4"), ("n", "<i2")])


def _fetch(parts: int, size: int):
    schema = {"part": pa.int32(), "heads": pa.binary(), "body": pa.binary()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            heads, bodies = [], []
            for doc, tag, raw, wants in zip(batch.column("doc_id").to_pylist(), batch.column("tag").to_pylist(), batch.column("text"), batch.column("wants").to_pylist(), strict=True):
                text = np.frombuffer((raw.as_py() or "").encode(), np.uint8)
                want = np.frombuffer(b"".join(wants), WANT)
                want = want[want["start"].astype(np.int64) + want["n"] + size - 1 <= len(text)]
                head = np.zeros(len(want), HEAD)
                for k in WANT.names:
                    head[k] = want[k]
                head["doc"], head["tag"] = doc, tag
                heads.append(head)
                lengths = want["n"].astype(np.int64) + size - 1
                where = np.repeat(want["start"].astype(np.int64) - np.append(0, np.cumsum(lengths)[:-1]), lengths) + np.arange(lengths.sum())
                bodies.append(text[where])
            if not heads:
                continue
            head, body = np.concatenate(heads), np.concatenate(bodies)
            lengths = head["n"].astype(np.int64) + size - 1
            at = np.append(0, np.cumsum(lengths))
            part = (head["trigger"] // U64(parts) % U64(parts)).astype(np.int64)
            rows = []
            order = np.argsort(part, kind="stable")
            edges = np.searchsorted(part[order], np.arange(parts + 1))
            for p in np.flatnonzero(np.diff(edges)):
                pick = order[edges[p] : edges[p + 1]]
                sizes = lengths[pick]
                where = np.repeat(at[pick] - np.append(0, np.cumsum(sizes)[:-1]), sizes) + np.arange(sizes.sum())
                rows.append((int(p), head[pick].tobytes(), body[where].tobytes()))
            if rows:
                yield _batch(schema, list(zip(*rows, strict=True)))

    return run


def _dense(keys: np.ndarray) -> np.ndarray:
    """The rank of each key among the distinct ones."""
    order = np.argsort(keys)
    held = keys[order]
    ranks = np.zeros(len(keys), U64)
    ranks[order] = np.cumsum(np.append(False, held[1:] != held[:-1]), dtype=U64) if len(keys) else ranks
    return ranks


def suffix_ranks(data: np.ndarray, size: int) -> np.ndarray:
    """For each place its rank in the order of the suffixes cut to `size` bytes, by doubling; equal ones share a rank.

    Suffixes that end earlier are filled up with zeros.
    """
    n = len(data)
    words = np.append(data, np.zeros(8, np.uint8)).astype(U64)
    for step in (1, 2, 4):
        words = (words[:-step] << U64(8 * step)) | words[step:]
    have = min(8, size)
    ranks = _dense(words[:n] >> U64(8 * (8 - have)))
    while have < size:
        step = min(have, size - have)
        # place n + k of the filling ranks lowest: 0, as all others are raised by 1
        ahead = np.append(ranks[step:] + U64(1), np.zeros(min(step, n), U64))
        ranks = _dense((ranks << U64(32)) | ahead)
        have += step
    return ranks


def _rank(size: int):
    schema = {"kind": pa.int32(), "doc_id": pa.int64(), "tag": pa.int64(), "payload": pa.binary()}

    def repeats(heads: np.ndarray, body: np.ndarray) -> Iterator[tuple[int, int, bytes]]:
        """Spans of the windows that equal one at an earlier place."""
        counts = heads["n"].astype(np.int64)
        owner = np.repeat(np.arange(len(heads)), counts)
        step = np.arange(len(owner)) - np.repeat(np.append(0, np.cumsum(counts)[:-1]), counts)
        ranks = suffix_ranks(body, size)[np.append(0, np.cumsum(counts + size - 1)[:-1])[owner] + step].astype(np.int64)
        # windows that no other equals need no place in the corpus
        shared = np.flatnonzero(np.bincount(ranks)[ranks] > 1)
        owner, step, ranks = owner[shared], step[shared], ranks[shared]
        found = np.zeros(len(owner), WINDOW)
        found["doc"], found["tag"], found["n"] = heads["doc"][owner], heads["tag"][owner], 1
        found["start"] = heads["start"][owner] + step
        order = np.lexsort((found["start"], found["tag"], found["doc"], ranks))
        found, ranks = found[order], ranks[order]
        new = np.append(True, ranks[1:] != ranks[:-1])[: len(found)]
        lead = np.flatnonzero(new)[np.cumsum(new) - 1]
        return _spans(found[~_same_place(found, lead)])

    def rank(held: list) -> Iterator[pa.RecordBatch]:
        """Equal windows share their trigger, so whole triggers of about SORTED bytes are taken at a time."""
        heads = np.concatenate([np.frombuffer(h, HEAD) for h, _ in held])
        body = np.frombuffer(b"".join(b for _, b in held), np.uint8)
        lengths = heads["n"].astype(np.int64) + size - 1
        at = np.append(0, np.cumsum(lengths)[:-1])
        order = np.argsort(heads["trigger"], kind="stable")
        heads, lengths, at = heads[order], lengths[order], at[order]
        triggers = np.flatnonzero(np.append(True, heads["trigger"][1:] != heads["trigger"][:-1]))
        bytes_before = np.append(0, np.cumsum(lengths))
        edges = np.append(triggers, len(heads))
        for i, j in K.slices(bytes_before[edges], SORTED):
            a, b = edges[i], edges[j]
            where = np.repeat(at[a:b] - bytes_before[a:b] + bytes_before[a], lengths[a:b]) + np.arange(bytes_before[b] - bytes_before[a])
            rows = [(0, *span) for span in repeats(heads[a:b], body[where])]
            if rows:
                yield _batch(schema, list(zip(*rows, strict=True)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for batch in batches:
            for part, heads, body in zip(batch.column("part").to_pylist(), batch.column("heads"), batch.column("body"), strict=True):
                if part != now and held:
                    yield from rank(held)
                    held = []
                now = part
                held.append((heads.as_py(), body.as_py()))
        if held:
            yield from rank(held)

    return run


def _cut(size: int, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text, spans = batch.column("text"), batch.column("spans").to_pylist()
            columns: list[list] = [[] for _ in range(5)]
            for raw, held in zip(text, spans, strict=True):
                data = np.frombuffer((raw.as_py() or "").encode(), np.uint8)
                gone = np.zeros(len(data) + 1, np.int32)
                if held:
                    span = np.frombuffer(b"".join(held), SPAN)
                    start = np.minimum(span["start"], len(data))
                    np.add.at(gone, start, 1)
                    np.add.at(gone, np.minimum(span["start"].astype(np.int64) + span["n"] + size - 1, len(data)), -1)
                out = np.cumsum(gone)[:-1] > 0
                rest = data[~out].tobytes()
                columns[0].append(len(data))
                columns[1].append(int(out.sum()))
                columns[2].append(int((out & ~np.append(False, out[:-1])).sum()))
                columns[3].append(hashlib.sha256(rest).hexdigest())
                if with_text:
                    columns[4].append(rest.decode("utf-8", "ignore") if raw.is_valid else None)
            made = [pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.string())]
            names = ["n_bytes", "n_removed", "n_spans", "kept_sha256"]
            if with_text:
                made.append(pa.array(columns[4], pa.string()))
                names.append("kept_text")
            rest_names = [n for n in batch.schema.names if n not in ("spans", *(() if with_text else ("text",)))]
            yield pa.RecordBatch.from_arrays([batch.column(n) for n in rest_names if n != "text"] + made, names=[n for n in rest_names if n != "text"] + names)

    return run


def _tag(text: Column) -> Column:
    """Tells texts of one doc_id apart."""
    return F.crc32(F.coalesce(text, F.lit("")).cast("binary"))


def repeated_spans(docs: DataFrame, size: int = SIZE, gram: int = GRAM, parts: int | None = None) -> DataFrame:
    """(doc_id, tag, spans): for each text with repeats, blobs of SPAN over its window starts that occurred earlier."""
    known = docs.select("doc_id", _tag(F.col("text")).alias("tag"), "text").where(F.col("doc_id").isNotNull())
    if parts is None:
        parts = max(8, -(-estimated_bytes(known) // PART_BYTES))
    parsed = materialize(known.mapInArrow(_parse(parts, size, gram), _PARSED), "parse")
    entries = parsed.where("part >= 0").select("part", "payload")
    resolved = materialize(entries.repartitionById(parts, "part").mapInArrow(_resolve, _RESOLVED), "dictionary")
    drop_shuffles(docs.sparkSession)
    wanted = resolved.where("kind = 1").groupBy("doc_id", "tag").agg(F.collect_list("payload").alias("wants"))
    fetched = known.join(wanted.hint("shuffle_hash"), ["doc_id", "tag"]).select("doc_id", "tag", "text", "wants").mapInArrow(_fetch(parts, size), "part int, heads binary, body binary")
    ranked = fetched.repartitionById(parts, "part").mapInArrow(_rank(size), _RESOLVED)
    columns = ["doc_id", "tag", "payload"]
    spans = resolved.where("kind = 0").select(columns).union(parsed.where("part < 0").select(columns)).union(ranked.select(columns))
    return spans.groupBy("doc_id", "tag").agg(F.collect_list("payload").alias("spans"))


def remove_repeats(docs: DataFrame, size: int = SIZE, gram: int = GRAM, with_text: bool = False, parts: int | None = None) -> DataFrame:
    """All columns of docs but text, with n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, kept_text.

    A removed span may cut a character in two; kept_text leaves out what remains of such characters, the digest doesn't.
    """
    docs = docs.drop("spans", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text")
    spans = materialize(repeated_spans(docs, size, gram, parts), "spans")
    drop_shuffles(docs.sparkSession)
    spans = spans.select(F.col("doc_id").alias("rep_doc"), F.col("tag").alias("rep_tag"), "spans")
    joined = docs.join(spans.hint("shuffle_hash"), (docs["doc_id"] == spans["rep_doc"]) & (_tag(docs["text"]) == spans["rep_tag"]), "left").select(*[docs[f"`{c}`"] for c in docs.columns], spans["spans"])
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name != "text"]
    kinds += ["n_bytes long", "n_removed long", "n_spans long", "kept_sha256 string", *(["kept_text string"] if with_text else [])]
    return joined.mapInArrow(_cut(size, with_text), ", ".join(kinds))
