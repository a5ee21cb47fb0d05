"""Concatenate-and-cut packing by two-pass prefix sums.

Pass one encodes each partition of documents where it lies and stores the ids with their
offset inside the partition; no text is shuffled. The partitions' token totals are a row each;
their prefix sum turns local offsets into global ones. Pass two cuts at multiples of the
sequence length with column expressions, one boundary record for each piece. Padding can only
be needed in the very last sequence.

Defined cases: a null or empty text is one document of the end id alone; a document longer than
a sequence lies in several pieces; repeated rows are packed each on its own; a null doc_id is
kept; an empty table gives no pieces; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import tokens
from .common import SharedTable, batched, prepare, rows_of
from .decontaminate import _arrow

LENGTH = 1024
TOKENIZER, END_ID = "byte_bpe_50k.json", 0


def encoded(docs: DataFrame, tokenizer: str = TOKENIZER, end_id: int = END_ID) -> DataFrame:
    """A row for each document: partition, local start, doc_id, number of ids and their bytes."""
    prepare(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType
    schema = pa.schema([("part", pa.int64()), ("at", pa.int64()), ("doc_id", _arrow(kind)), ("n", pa.int64()), ("ids", pa.binary())])
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = tokens.load(tokenizer).encode, TaskContext.get().partitionId()

        def rows() -> Iterator[tuple]:
            at = 0
            for doc_id, text in rows_of(batches, "doc_id", "text"):
                ids = encode(text) + end
                yield part, at, doc_id, len(ids) // 4, ids
                at += len(ids) // 4

        return batched(rows(), schema)

    return docs.select("doc_id", "text").mapInArrow(run, f"part long, at long, doc_id {kind.simpleString()}, n long, ids binary")


def with_global_starts(stored: DataFrame) -> DataFrame:
    """Adds ``first``, the ids of all documents before it in (partition, local) order."""
    totals = stored.groupBy("part").agg(F.sum("n").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    # One row for each input partition: bounded by the number of tasks, not by the rows.
    starts = totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("start_of_part"))
    return stored.join(F.broadcast(starts), "part").withColumn("first", F.col("start_of_part") + F.col("at")).drop("start_of_part")


def pieces(stored: DataFrame, length: int = LENGTH) -> DataFrame:
    """Boundary records: each id of a document lies in exactly one piece. Keeps the piece's ids."""
    at, n = F.col("first"), F.col("n")

    def piece(k: Column) -> Column:
        """The part of a document in sequence k: ids are cut before they are dealt out, so none is copied twice."""
        low, high = F.greatest(at, k * length), F.least(at + n, (k + 1) * length)
        ids = F.substring("ids", ((low - at) * 4 + 1).cast("int"), ((high - low) * 4).cast("int"))
        return F.struct(k.alias("sequence_id"), (low - at).alias("start"), (high - low).alias("length"), (low - k * length).alias("offset"), ids.alias("ids"))

    own = F.transform(F.sequence(F.floor(at / length), F.floor((at + n - 1) / length)), piece)
    cut = with_global_starts(stored).select("doc_id", n.alias("doc_tokens"), F.explode(own).alias("p"))
    return cut.select("doc_id", "p.ids", "doc_tokens", "p.sequence_id", "p.start", "p.length", "p.offset")


def pack(docs: DataFrame, length: int = LENGTH, tokenizer: str = TOKENIZER, end_id: int = END_ID) -> DataFrame:
    """Pieces with their ids: doc_id, start, length, doc_tokens, sequence_id, offset, ids."""
    return pieces(SharedTable(encoded(docs, tokenizer, end_id), "packing").read(), length)


def sequences(packed: DataFrame, length: int = LENGTH, pad_id: int = END_ID) -> DataFrame:
    """The sequences themselves: ids as bytes, padded to ``length`` unless the length is a power of two."""
    joined = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts"), F.sum("length").alias("n_tokens"))
    ids = F.aggregate("parts", F.lit(b""), lambda have, x: F.concat(have, x["ids"]))
    whole = F.bit_count("n_tokens") == 1
    pad = F.unhex(F.repeat(F.lit(pad_id.to_bytes(4, "little").hex()), F.when(whole, 0).otherwise(length - F.col("n_tokens")).cast("int")))
    return joined.select("sequence_id", "n_tokens", F.concat(ids, pad).alias("ids"))


def digest(packed: DataFrame) -> DataFrame:
    return packed.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
