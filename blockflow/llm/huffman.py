"""Token ids in shards of canonical length-limited Huffman code.

Each shard is one self-contained file image, kept as a row of a written table so that any store Spark writes to can hold
it. Its layout, little-endian throughout:

    magic "BFH1", u32 documents, u64 ids, u64 ids of its part before the shard, u32 ids a block, u32 blocks
    i64 doc_id of each document (the smallest value stands for none), u32 ids of each document
    u64 bit offset of each block
    the code bits, most significant first, and 8 bytes of zeros

The code comes from the counts of all ids of the corpus: no code is longer than `limit` bits (package-merge finds the best
such lengths), and codes of one length are numbered in ascending id order, so the lengths alone are the code book. Every
block begins at its checkpoint and is decoded without the others, by one table lookup an id. A part is a run of documents
that one task wrote; the manifest, a table beside the shards, says how many ids come before each part in the corpus.

Defined cases: a null text is empty and gives the end id alone; rows that repeat a doc_id each stand for a document; an
empty table gives no shards.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockflow.llm import kernels as K
from blockflow.llm.ordered import ranged
from blockflow.llm.tokens import encoder
from blockflow.session import materialize

MAGIC = b"BFH1"
_HEAD = struct.Struct("<4sIQQII")
BLOCK = 1024
#: Longest code in bits; more where the vocabulary needs it.
LIMIT = 18
#: Ids of a shard at least, unless its partition ends.
SHARD = 1 << 20
NO_ID = -(1 << 63)


def code_lengths(counts: np.ndarray, limit: int = LIMIT) -> np.ndarray:
    """The best code lengths of at most `limit` bits for ids with these counts; 0 for ids that don't occur."""
    used = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.uint8)
    if len(used) < 2:
        out[used] = 1
        return out
    limit = max(limit, int(len(used) - 1).bit_length())
    order = used[np.argsort(counts[used], kind="stable")]
    leaves = counts[order].astype(np.float64)
    levels, packed = [], np.zeros(0)
    for _ in range(limit):
        both = np.concatenate([leaves, packed])
        rank = np.argsort(both, kind="stable")
        levels.append(rank < len(leaves))
        merged = both[rank]
        merged = merged[: len(merged) // 2 * 2]
        packed = merged[0::2] + merged[1::2]
    take = 2 * len(leaves) - 2
    for is_leaf in reversed(levels):
        n = int(is_leaf[:take].sum())
        out[order[:n]] += 1
        take = 2 * (take - n)
    return out


def canonical_codes(lengths: np.ndarray) -> np.ndarray:
    """The code of each id, by (length, id)."""
    codes = np.zeros(len(lengths), np.uint32)
    code, last = 0, 0
    for size in range(1, int(lengths.max(initial=0)) + 1):
        ids = np.flatnonzero(lengths == size)
        code <<= size - last
        codes[ids] = code + np.arange(len(ids))
        code, last = code + len(ids), size
    return codes


def decode_table(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """id and length by the next `width` bits."""
    width = int(lengths.max(initial=1))
    ids, sizes = np.zeros(1 << width, np.uint32), np.zeros(1 << width, np.int64)
    order = np.lexsort((np.arange(len(lengths)), lengths))
    order = order[lengths[order] > 0]
    spread = np.int64(1) << (width - lengths[order].astype(np.int64))
    filled = int(spread.sum())
    ids[:filled] = np.repeat(order, spread)
    sizes[:filled] = np.repeat(lengths[order], spread)
    return ids, sizes, width


def encode_shard(ids: np.ndarray, doc_ids: np.ndarray, counts: np.ndarray, first: int, lengths: np.ndarray, codes: np.ndarray, block: int = BLOCK) -> bytes:
    size = lengths[ids].astype(np.int64)
    end = np.cumsum(size)
    at = end - size
    bits = int(end[-1]) if len(ids) else 0
    words = np.zeros(bits // 32 + 3, np.uint64)
    # a code lies in one 32-bit word or two; words add up, as codes don't overlap
    value = codes[ids].astype(np.uint64) << (64 - size - (at & 31)).astype(np.uint64)
    np.add.at(words, at >> 5, value >> np.uint64(32))
    np.add.at(words, (at >> 5) + 1, value & np.uint64(0xFFFFFFFF))
    body = words.astype(">u4").tobytes()[: (bits + 7) // 8] + bytes(8)
    starts = at[::block].astype("<u8")
    head = _HEAD.pack(MAGIC, len(doc_ids), len(ids), first, block, len(starts))
    return b"".join([head, doc_ids.astype("<i8").tobytes(), counts.astype("<u4").tobytes(), starts.tobytes(), body])


def shard_header(image: bytes) -> dict:
    magic, docs, ids, first, block, blocks = _HEAD.unpack_from(image)
    if magic != MAGIC:
        raise ValueError("not a shard of token ids")
    at = _HEAD.size
    out = {"ids": ids, "first": first, "block": block, "doc_ids": np.frombuffer(image, "<i8", docs, at)}
    out["counts"] = np.frombuffer(image, "<u4", docs, at := at + 8 * docs)
    out["starts"] = np.frombuffer(image, "<u8", blocks, at := at + 4 * docs)
    return out | {"body": at + 8 * blocks}


def decode_blocks(image: bytes, table: tuple[np.ndarray, np.ndarray, int], header: dict | None = None, blocks: np.ndarray | None = None) -> np.ndarray:
    """The ids of the shard, or of some of its blocks one after another; all blocks advance together."""
    h = header or shard_header(image)
    symbol, size, width = table
    which = np.arange(len(h["starts"])) if blocks is None else np.asarray(blocks)
    raw = np.frombuffer(image, np.uint8, offset=h["body"])
    raw = np.append(raw, np.zeros(8, np.uint8)).astype(np.uint64)
    window = (raw[:-4] << np.uint64(32)) | (raw[1:-3] << np.uint64(24)) | (raw[2:-2] << np.uint64(16)) | (raw[3:-1] << np.uint64(8)) | raw[4:]
    at = h["starts"][which].astype(np.int64)
    counts = np.minimum(h["block"], h["ids"] - which * h["block"])
    out = np.zeros((h["block"], len(which)), np.uint32)
    shift, mask = np.uint64(40 - width), np.uint64((1 << width) - 1)
    for step in range(int(counts.max(initial=0))):
        if step == counts.min():
            # only the shard's last block is shorter; it drops out
            live = counts > step
            at = np.where(live, at, 0)
        bits = ((window[at >> 3] >> (shift - (at & 7).astype(np.uint64))) & mask).astype(np.int64)
        out[step] = symbol[bits]
        at = at + size[bits]
        if step >= counts.min():
            at = np.where(counts > step + 1, at, 0)
    flat = out.T.ravel()
    if len(which) and counts.min() < h["block"]:
        flat = flat[(np.arange(h["block"]) < counts[:, None]).ravel()]
    return flat


_BLOB = "part int, seq int, doc_ids binary, counts binary, ids binary, n long, first long"


def _tokenized(path: str, end_id: int):
    from pyspark import TaskContext

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, seq, first = encoder(path), TaskContext.get().partitionId(), 0, 0
        held: list[tuple] = []

        def out() -> pa.RecordBatch:
            nonlocal first
            docs, counts, ids = (np.concatenate(x) for x in zip(*held, strict=True))
            row = [[part], [seq], [docs.tobytes()], [counts.tobytes()], [ids.tobytes()], [len(ids)], [first]]
            first += len(ids)
            kinds = [pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(row, kinds, strict=True)], names=["part", "seq", "doc_ids", "counts", "ids", "n", "first"])

        for batch in batches:
            data, offsets = K.column_bytes(batch.column("text"))
            names = np.asarray(batch.column("doc_id").fill_null(NO_ID))
            for i, j in K.slices(offsets):
                ids, at = enc.encode(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                held.append((names[i:j].astype("<i8"), (np.diff(at) + 1).astype("<u4"), with_end(ids, at, end_id).astype("<u4" if enc.dtype.itemsize > 2 else "<u2")))
                if sum(len(x[2]) for x in held) >= SHARD:
                    yield out()
                    held, seq = [], seq + 1
        if held:
            yield out()

    return run


def with_end(ids: np.ndarray, at: np.ndarray, end_id: int) -> np.ndarray:
    """The ids with the end id after each text."""
    return np.insert(ids, at[1:], ids.dtype.type(end_id))


def token_table(docs: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    """Ids of all documents in ascending doc_id order, in rows of about a million; written once."""
    return materialize(ranged(docs, "text").mapInArrow(_tokenized(tokenizer, end_id), _BLOB), "tokens")


def _id_type(wide: bool) -> str:
    return "<u4" if wide else "<u2"


def _counted(vocabulary: int, wide: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(vocabulary, np.int64)
        for batch in batches:
            for raw in batch.column("ids"):
                total += np.bincount(np.frombuffer(raw.as_py(), _id_type(wide)), minlength=vocabulary)
        ids = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(total[ids])], names=["id", "n"])

    return run


def _written(lengths: np.ndarray, wide: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = canonical_codes(lengths)
        for batch in batches:
            for part, seq, docs, counts, ids, first in zip(*[batch.column(k) for k in ("part", "seq", "doc_ids", "counts", "ids", "first")], strict=True):
                image = encode_shard(np.frombuffer(ids.as_py(), _id_type(wide)), np.frombuffer(docs.as_py(), "<i8"), np.frombuffer(counts.as_py(), "<u4"), first.as_py(), lengths, codes)
                yield pa.RecordBatch.from_arrays([pa.array([part.as_py()], pa.int32()), pa.array([seq.as_py()], pa.int32()), pa.array([image], pa.binary())], names=["part", "seq", "image"])

    return run


def _read(lengths: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = decode_table(lengths)
        for batch in batches:
            for part, image in zip(batch.column("part"), batch.column("image"), strict=True):
                raw = image.as_py()
                h = shard_header(raw)
                ids = decode_blocks(raw, table, h).astype("<u4")
                ends = np.cumsum(h["counts"], dtype=np.int64)
                begins = ends - h["counts"]
                view = memoryview(ids.tobytes())
                crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
                none = h["doc_ids"] == NO_ID
                yield pa.RecordBatch.from_arrays(
                    [pa.repeat(part, len(begins)), pa.array(h["doc_ids"], mask=none), pa.array(begins + h["first"]), pa.array(h["counts"].astype(np.int64)), pa.array(crc, pa.int64())],
                    names=["part", "doc_id", "inside", "n_tokens", "ids_crc32"],
                )

    return run


def write_shards(docs: DataFrame, tokenizer: str, end_id: int) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """(part, seq, image) of every shard, written; the manifest (part, base); and the code lengths that read the shards.

    What the driver receives is one count for each id of the vocabulary.
    """
    enc = encoder(tokenizer)
    vocabulary, wide = max(enc.size, end_id + 1), enc.dtype.itemsize > 2
    tokens = token_table(docs, tokenizer, end_id)
    counts = np.zeros(vocabulary, np.int64)
    for row in tokens.select("ids").mapInArrow(_counted(vocabulary, wide), "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).collect():
        counts[row["id"]] = row["n"]
    lengths = code_lengths(counts)
    # one row for each part, some sixty-four million bytes of text
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    manifest = tokens.groupBy("part").agg(F.sum("n").alias("total")).select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"))
    shards = tokens.select("part", "seq", "doc_ids", "counts", "ids", "first").mapInArrow(_written(lengths, wide), "part int, seq int, image binary")
    return materialize(shards, "shards", "uncompressed"), materialize(manifest, "manifest"), lengths


def read_shards(shards: DataFrame, manifest: DataFrame, lengths: np.ndarray) -> DataFrame:
    """Per document, from the shards: doc_id, start, n_tokens, ids_crc32. Only these rows meet the manifest."""
    read = shards.select("part", "image").mapInArrow(_read(lengths), "part int, doc_id long, inside long, n_tokens long, ids_crc32 long")
    return read.join(manifest, "part").select("doc_id", (F.col("base") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")
