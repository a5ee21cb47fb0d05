"""Token ids as patched frame-of-reference blocks.

A segment's bytes: the magic ``PFR1``; the numbers of ids and of blocks; the index of block
starts; then the blocks. A block of 256 ids holds its minimum, the bit width that a percentile
of its differences needs, the number of exceptions, the packed low bits and the exceptions as
(place, high bits). Packing runs in eight lanes of 32 values, so that each of its 32 steps is
one vector operation over all blocks of a width; the last block is filled up with its minimum.
Any block can be decoded alone from the index.

A file's bytes hold two segments: the documents' lengths and their ids, the first behind its own size.

``write`` sorts documents by range of doc_id and the first characters of the text, so that rows of one id need not
lie in one task, and stores files in the shared folder as rows of a Parquet table, whose commit protocol
leaves whole files only when tasks are retried. Documents and their bounds are read from these bytes.

Defined cases: a null or empty text is the end id alone; equal doc_ids, repeated rows too, stand in order of
their texts; null doc_ids come first; a very long text may fill a file alone; an empty table gives an
empty file set; further columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import tokens
from .common import SharedTable, batched, prepare, rows_of
from .decontaminate import _arrow

BLOCK, LANES = 256, 8
STEPS = BLOCK // LANES
PERCENTILE = 90
MAGIC = b"PFR1"
SEGMENT_IDS = 1 << 19
TOKENIZER, END_ID = "word_bpe_49k.json", 2


def _pack_bits(values: np.ndarray, width: int) -> np.ndarray:
    """(blocks, 256) values below 2**width to (blocks, width * 8) words of 32 bits."""
    lanes = values.reshape(-1, STEPS, LANES).astype(np.uint64)
    out = np.zeros((len(values), width + 1, LANES), np.uint64)
    for k in range(STEPS):
        word, shift = divmod(k * width, 32)
        moved = lanes[:, k] << np.uint64(shift)
        out[:, word] |= moved & np.uint64(0xFFFFFFFF)
        if shift + width > 32:
            out[:, word + 1] |= moved >> np.uint64(32)
    return out[:, :width].astype("<u4").reshape(len(values), width * LANES)


def _unpack_bits(words: np.ndarray, width: int) -> np.ndarray:
    lanes = np.zeros((len(words), width + 1, LANES), np.uint64)
    lanes[:, :width] = words.reshape(len(words), width, LANES)
    out = np.empty((len(words), STEPS, LANES), np.uint64)
    mask = np.uint64((1 << width) - 1)
    for k in range(STEPS):
        word, shift = divmod(k * width, 32)
        pair = lanes[:, word] | lanes[:, word + 1] << np.uint64(32) if shift + width > 32 else lanes[:, word]
        out[:, k] = pair >> np.uint64(shift) & mask
    return out.reshape(len(words), BLOCK)


def compress(ids: np.ndarray, percentile: int = PERCENTILE) -> bytes:
    """One segment."""
    n = len(ids)
    count = -(-n // BLOCK)
    if not n:
        return MAGIC + np.array([0, 0], "<u4").tobytes()
    full = np.full(count * BLOCK, ids[(count - 1) * BLOCK :].min(), np.uint32)
    full[:n] = ids
    full = full.reshape(count, BLOCK)
    low = full.min(1)
    rest = full - low[:, None]
    at = min(BLOCK - 1, BLOCK * percentile // 100)
    widths = np.frexp(np.partition(rest, at, 1)[:, at].astype(np.float64))[1].astype(np.uint8)
    high = rest >> np.minimum(widths, 31)[:, None].astype(np.uint32)
    high[widths == 32] = 0
    out: list[bytes] = [b""] * count
    for width in np.unique(widths).tolist():
        mine = np.flatnonzero(widths == width)
        packed = _pack_bits(rest[mine] & np.uint32((1 << width) - 1), width) if width else np.zeros((len(mine), 0), "<u4")
        for k, words in zip(mine.tolist(), packed, strict=True):
            places = np.flatnonzero(high[k])
            head = int(low[k]).to_bytes(4, "little") + bytes((width,)) + len(places).to_bytes(2, "little")
            out[k] = b"".join((head, words.tobytes(), places.astype(np.uint8).tobytes(), high[k][places].astype("<u4").tobytes()))
    starts = np.cumsum([0, *map(len, out[:-1])])
    return b"".join((MAGIC, np.array([n, count], "<u4").tobytes(), starts.astype("<u4").tobytes(), *out))


def decompress(blob: bytes, first: int = 0, last: int | None = None) -> np.ndarray:
    """The ids of blocks first to last (exclusive) of a segment; all by default."""
    if blob[:4] != MAGIC:
        raise ValueError("not a segment of packed ids")
    n, count = np.frombuffer(blob, "<u4", 2, 4).tolist()
    last = count if last is None else min(last, count)
    starts = np.frombuffer(blob, "<u4", count, 12) + np.uint32(12 + 4 * count)
    raw = np.frombuffer(blob, np.uint8)
    chosen = starts[first:last].astype(np.int64)
    out = np.empty((len(chosen), BLOCK), np.uint64)
    if not len(chosen):
        return np.empty(0, np.uint32)
    field = lambda at, k: sum(raw[chosen + at + i].astype(np.int64) << (8 * i) for i in range(k))
    low, widths, n_high = field(0, 4), raw[chosen + 4], field(5, 2)
    for width in np.unique(widths).tolist():
        mine = np.flatnonzero(widths == width)
        size = width * LANES * 4
        words = raw[(chosen[mine] + 7)[:, None] + np.arange(size)].view("<u4").reshape(len(mine), width * LANES)
        out[mine] = _unpack_bits(words, width) if width else 0
    for k in np.flatnonzero(n_high).tolist():
        at, m, width = int(chosen[k]) + 7 + int(widths[k]) * LANES * 4, int(n_high[k]), int(widths[k])
        out[k, raw[at : at + m]] |= np.frombuffer(blob, "<u4", m, at + m).astype(np.uint64) << np.uint64(width)
    out += low[:, None].astype(np.uint64)
    return out.astype(np.uint32).reshape(-1)[: min(n, last * BLOCK) - first * BLOCK]


def pack_file(lengths: np.ndarray, ids: np.ndarray) -> bytes:
    """Lengths and ids of some documents."""
    head = compress(lengths.astype(np.uint32))
    return b"".join((len(head).to_bytes(4, "little"), head, compress(ids)))


def unpack_file(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    size = int.from_bytes(blob[:4], "little")
    return decompress(blob[4 : 4 + size]), decompress(blob[4 + size :])


def write(docs: DataFrame, tokenizer: str = TOKENIZER, end_id: int = END_ID, segment_ids: int = SEGMENT_IDS) -> SharedTable:
    """Stores the segments: (part, segment, at, doc_ids, n, ids), in ascending doc_id order."""
    prepare(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType
    schema = pa.schema([("part", pa.int64()), ("segment", pa.int64()), ("at", pa.int64()), ("doc_ids", pa.list_(_arrow(kind))), ("n", pa.int64()), ("ids", pa.binary())])
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = tokens.load(tokenizer).encode, TaskContext.get().partitionId()

        def segments() -> Iterator[tuple]:
            held: list[bytes] = []
            names, at, size, number = [], 0, 0, 0

            def close() -> tuple:
                ids = np.frombuffer(b"".join(held), "<u4")
                return part, number, at, names, len(ids), pack_file(np.array([len(x) // 4 for x in held]), ids)

            for doc_id, text in rows_of(batches, "doc_id", "text"):
                held.append(encode(text) + end)
                names.append(doc_id)
                size += len(held[-1]) // 4
                if size >= segment_ids:
                    yield close()
                    at, size, number, held, names = at + size, 0, number + 1, [], []
            if held:
                yield close()

        return batched(segments(), schema)

    ordered = docs.select("doc_id", "text").repartitionByRange(F.col("doc_id"), F.substring("text", 1, 64)).sortWithinPartitions("doc_id", "text")
    columns = f"part long, segment long, at long, doc_ids array<{kind.simpleString()}>, n long, ids binary"
    return SharedTable(ordered.mapInArrow(run, columns), "packed-ids", codec="none")


def read(stored: DataFrame) -> DataFrame:
    """Per document, from the stored bytes alone: doc_id, start, n_tokens and its ids as bytes."""
    kind = stored.schema["doc_ids"].dataType.elementType
    schema = pa.schema([("doc_id", _arrow(kind)), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.binary())])
    return _located(stored).mapInArrow(_decoder(schema, lambda x: x), f"doc_id {kind.simpleString()}, start long, n_tokens long, ids binary")


def digest(stored: DataFrame) -> DataFrame:
    kind = stored.schema["doc_ids"].dataType.elementType
    schema = pa.schema([("doc_id", _arrow(kind)), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
    return _located(stored).mapInArrow(_decoder(schema, zlib.crc32), f"doc_id {kind.simpleString()}, start long, n_tokens long, ids_crc32 long")


def _located(stored: DataFrame) -> DataFrame:
    totals = stored.groupBy("part").agg(F.sum("n").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    # One row for each range of documents.
    starts = totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("start_of_part"))
    return stored.join(F.broadcast(starts), "part").select((F.col("start_of_part") + F.col("at")).alias("start"), "doc_ids", "ids")


def _decoder(schema: pa.Schema, of):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for start, names, blob in rows_of(batches, "start", "doc_ids", "ids"):
                lengths, ids = unpack_file(blob)
                raw, at = ids.astype("<u4").tobytes(), 0
                for name, n in zip(names, lengths.tolist(), strict=True):
                    yield name, start + at, n, of(raw[4 * at : 4 * (at + n)])
                    at += n

        return batched(rows(), schema)

    return run
