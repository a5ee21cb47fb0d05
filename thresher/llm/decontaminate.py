"""Benchmark decontamination: a broadcast set of normalised test n-grams against training windows.

An item's windows are its runs of ``width`` consecutive words; an item of fewer words is one
window. Words are compared as integers of the items' own vocabulary, so a hit is exact: the
hash set finds a window by its bytes, and equal bytes are equal words. A document word inside
any occurrence is hit.

Size: the windows of a block of items are broadcast, and a block holds at most
``BLOCK_WORDS`` words, about 100 MB in a worker. A larger benchmark is scanned block after block over a
stored copy of the documents, and the hit intervals of the passes are united by row, so a result does not
depend on the size of a block. Spans of all blocks are cut together, again until nothing occurs.

Defined cases: null or empty texts have no words, no hits and the sha256 of nothing; items
without words or without an id have no windows; an id is any text, the empty one and ones with commas too; repeated rows and
repeated ids each give a row of their own; columns besides those named are ignored by ``scan`` and kept by ``clean``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SharedTable, batched, plain_words, prepare, rows_of

WIDTH = 10
BLOCK_WORDS = 500_000

_COLUMNS = "doc_id {id}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


class WindowSet:
    """The windows of some items: by length, from the window's bytes to the items that have it."""

    def __init__(self, items: list[tuple[str, str]], width: int = WIDTH):
        self.vocabulary: dict[bytes, int] = {}
        self.items: list[str] = []
        self.windows: dict[int, dict[bytes, int | tuple[int, ...]]] = {}
        for name, text in items:
            words = plain_words(text)
            if not words:
                continue
            ids = np.fromiter((self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words), np.uint32, len(words))
            length, me = min(width, len(words)), len(self.items)
            self.items.append(name)
            own = self.windows.setdefault(length, {})
            for k in range(len(words) - length + 1):
                key = ids[k : k + length].tobytes()
                have = own.setdefault(key, me)
                # Most windows belong to one item: a tuple only where there are more.
                if isinstance(have, tuple):
                    own[key] = have if have[-1] == me else (*have, me)
                elif have != me:
                    own[key] = (have, me)

    def hits(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[int]]:
        """Intervals [start, end) of occurrences, and the numbers of the items they come from."""
        spans: list[tuple[int, int]] = []
        found: set[int] = set()
        if not words:
            return spans, found
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.uint32, len(words))
        run = np.concatenate(([0], np.cumsum(ids != 0)))
        for length, windows in self.windows.items():
            if len(words) < length:
                continue
            for k in np.flatnonzero(run[length:] - run[:-length] == length).tolist():
                if (have := windows.get(ids[k : k + length].tobytes())) is not None:
                    spans.append((k, k + length))
                    found.update(have if isinstance(have, tuple) else (have,))
        return spans, found


def covered(spans: list[tuple[int, int]], n: int) -> np.ndarray:
    """Which of n words lie in a span."""
    edge = np.zeros(n + 1, np.int32)
    for a, b in spans:
        edge[a] += 1
        edge[b] -= 1
    return np.cumsum(edge[:-1]) > 0


def strip(text: str, windows: WindowSet) -> str:
    """The text without hit words and what joins them; again until no window occurs."""
    while spans := windows.hits(plain_words(text))[0]:
        text = cut(text, spans)
    return text


def cut(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words of the spans and what joins them."""
    raw = text.encode("utf-8", "surrogatepass")
    words = plain_words(text)
    hit = covered(spans, len(words))
    low, at, bounds = raw.lower(), 0, []
    for w in words:
        at = low.index(w, at)
        bounds.append((at, at + len(w)))
        at += len(w)
    kept, k, at = [], 0, 0
    while k < len(words):
        if not hit[k]:
            k += 1
            continue
        end = k
        while end + 1 < len(words) and hit[end + 1]:
            end += 1
        kept.append(raw[at : bounds[k][0]])
        at, k = bounds[end][1], end + 1
    return b"".join([*kept, raw[at:]]).decode("utf-8", "surrogatepass")


def blocks(benchmark: DataFrame, width: int = WIDTH, block_words: int = BLOCK_WORDS) -> Iterator[WindowSet]:
    """Items in blocks of bounded size, streamed through the driver one partition at a time."""
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("item_id"), "text")
    held: list[tuple[str, str]] = []
    weight = 0
    for name, text in items.toLocalIterator():
        size = len(text) // 2 + 1
        if held and weight + size > block_words:
            yield WindowSet(held, width)
            held, weight = [], 0
        held.append((name, text))
        weight += size
    if held or not weight:
        yield WindowSet(held, width)


def _digest(items: set[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()


def scan(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Per document: words, hit words, items with occurring windows and whether any was hit."""
    spark = docs.sparkSession
    prepare(spark)
    first, *more = _peeked(blocks(benchmark, width, block_words))
    kind = docs.schema["doc_id"].dataType
    columns = _COLUMNS.format(id=kind.simpleString())
    if more:
        return _scan_in_passes(docs, chain([first], *more), columns)
    held = spark.sparkContext.broadcast(first)
    schema = pa.schema([("doc_id", _arrow(kind)), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        windows = held.value

        def rows() -> Iterator[tuple]:
            for doc_id, text in rows_of(batches, "doc_id", "text"):
                words = plain_words(text)
                spans, found = windows.hits(words)
                n = int(covered(spans, len(words)).sum()) if spans else 0
                names = {windows.items[k] for k in found}
                yield doc_id, len(words), n, len(names), _digest(names), n > 0

        return batched(rows(), schema)

    return docs.select("doc_id", "text").mapInArrow(run, columns)


def _peeked(found: Iterator[WindowSet]) -> list:
    """The first block; where there are more, the second alone and an iterator of the rest behind it."""
    first, second = next(found), next(found, None)
    return [first] if second is None else [first, [second], found]


def _arrow(kind) -> pa.DataType:
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)


def _hits_in_passes(rows: DataFrame, found: Iterable[WindowSet]) -> DataFrame:
    """(row, spans, items): for each block and row with hits, a stored pass over the rows (row, text) for each block."""
    spark = rows.sparkSession
    part = pa.schema([("row", pa.int64()), ("spans", pa.binary()), ("items", pa.list_(pa.string()))])
    passes: DataFrame | None = None
    for windows in found:
        held = spark.sparkContext.broadcast(windows)

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            def out() -> Iterator[tuple]:
                for row, text in rows_of(batches, "row", "text"):
                    spans, numbers = held.value.hits(plain_words(text))
                    if spans:
                        yield row, np.array(spans, "<i8").tobytes(), [held.value.items[k] for k in sorted(numbers)]

            return batched(out(), part)

        one = SharedTable(rows.select("row", "text").mapInArrow(run, "row long, spans binary, items array<string>"), "decontaminate-pass").read()
        passes = one if passes is None else passes.unionByName(one)
        held.unpersist()
    return passes


def _together(hits: DataFrame) -> DataFrame:
    return hits.groupBy("row").agg(F.collect_list("spans").alias("spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"))


def _spans(parts: list[bytes]) -> list[tuple[int, int]]:
    return np.concatenate([np.frombuffer(x, "<i8") for x in parts]).reshape(-1, 2).tolist()


def _scan_in_passes(docs: DataFrame, found: Iterable[WindowSet], columns: str) -> DataFrame:
    """For a benchmark beyond one block: a pass for each block, then the union of hits by row."""
    kind = _arrow(docs.schema["doc_id"].dataType)
    rows = SharedTable(docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text"), "decontaminate-rows").read()
    schema = pa.schema([("doc_id", kind), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())])

    def unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            for doc_id, text, spans, items in rows_of(batches, "doc_id", "text", "spans", "items"):
                n = len(plain_words(text))
                hit = int(covered(_spans(spans), n).sum()) if spans else 0
                names = set(items or ())
                yield doc_id, n, hit, len(names), _digest(names), hit > 0

        return batched(out(), schema)

    return rows.join(_together(_hits_in_passes(rows, found)), "row", "left").select("doc_id", "text", "spans", "items").mapInArrow(unite, columns)


def clean(docs: DataFrame, benchmark: DataFrame, mode: str = "documents", width: int = WIDTH, block_words: int = BLOCK_WORDS) -> DataFrame:
    """The documents without hits (``documents``), or all with the hit words cut out (``spans``).

    Keeps every column. A benchmark beyond one block is worked off block by block: documents over a stored
    copy of what the block before has left; spans of all blocks together, in rounds until no block has any.
    """
    if mode not in ("documents", "spans"):
        raise ValueError(f"no such mode: {mode}")
    prepare(docs.sparkSession)
    first, *more = _peeked(blocks(benchmark, width, block_words))
    if not more:
        return _cleaned(docs, first, mode)
    if mode == "documents":
        docs = _cleaned(docs, first, mode)
        for windows in chain(*more):
            docs = _cleaned(SharedTable(docs, "decontaminate-clean").read(), windows, mode)
        return docs
    schema = docs.schema
    # Columns travel in a struct, so that none of theirs is taken for one of ours.
    held = SharedTable(docs.select(F.monotonically_increasing_id().alias("row"), F.col("text").alias("text"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("own")), "decontaminate-spans").read()
    while True:
        hits = SharedTable(_together(_hits_in_passes(held, blocks(benchmark, width, block_words))), "decontaminate-hits").read()
        if hits.isEmpty():
            break
        shorter = F.udf(lambda text, spans: cut(text, _spans(spans)) if spans else text, "string", useArrow=True)
        held = SharedTable(held.join(hits.select("row", "spans"), "row", "left").select("row", shorter("text", "spans").alias("text"), "own"), "decontaminate-spans").read()
    return held.select(*[(F.col("text") if f.name == "text" else F.col(f"own.`{f.name}`")).alias(f.name) for f in schema.fields])


def _cleaned(docs: DataFrame, windows: WindowSet, mode: str) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(windows)

    @F.pandas_udf("boolean")
    def is_hit(text):
        return text.map(lambda t: bool(held.value.hits(plain_words(t))[0]))

    @F.pandas_udf("string")
    def stripped(text):
        return text.map(lambda t: strip(t, held.value) if t else t)

    if mode == "documents":
        return docs.where(~is_hit(F.coalesce("text", F.lit(""))))
    return docs.withColumn("text", stripped("text"))
