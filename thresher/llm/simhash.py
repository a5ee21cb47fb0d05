"""SimHash near-duplicates by bit-sliced comparison.

A fingerprint bit is 1 if it is set in over half of the shingle hashes. Comparison works on
vertical bit planes: plane p holds bit p of 64 fingerprints in one word, so one XOR tells for 64
candidates whether they differ from a query there, a carry-save adder takes two planes at a time
into bitwise counters, and a block of candidates is abandoned once every lane is over the radius.

Which fingerprints are compared:

* ``exact`` links (``link``): fingerprints within ``radius`` bits agree on some
  ``blocks - radius`` of ``blocks`` stripes, so a row goes to one bucket for each such choice of
  stripes (pigeonhole). The number of stripes follows the number of fingerprints, which keeps
  buckets small at every size. No link is lost.
* ``similar`` links: fingerprints over distinct shingles, of several words, whose texts share one of
  their smallest shingle hashes. Two texts whose shingle sets have Jaccard similarity 0.8 share
  none of six such keys with probability under 0.2 ** 6. The radius only leaves out what is four
  deviations beyond the threshold; what is within it is decided by the shingle sets themselves.

A bucket over ``BUCKET`` rows is cut into chunks and every pair of chunks is a task of its own,
so that no bucket lands in one task. A task emits for each fingerprint at most one link, to the
smallest of its component in the task: as many links as rows, the same components. Up to ``FEW``
links are joined up in one task; components of more come from alternating star rounds over tables in
the shared folder, each of which is some ten stages for the driver to plan and to follow.

Defined cases: null and empty texts have the zero fingerprint and are linked like any other;
equal texts have equal fingerprints and one component; repeated rows stay repeated; a null id is never the
smallest of a component while another is there, and rows without one are linked and returned; an empty
table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SharedTable, batched, blank_words, prepare, rows_of
from .decontaminate import _arrow

SHINGLE, RADIUS, SEED = 4, 4, 42
#: Rows of a bucket that one task compares with each other.
BUCKET = 1024
#: Mean rows of a bucket from which on more stripes are used.
MEAN_BUCKET = 512
KEYS = 6
#: Edges of a node from which on it is a hub, and hubs that are broadcast at most (16 to 40 bytes each).
HUB, HUBS = 1024, 1_000_000
#: Links that one task joins up (some 550 bytes each in a worker); beyond that, star rounds.
FEW = 200_000
#: Deviations beyond the mean distance at the threshold up to which shingle sets are compared.
DEVIATIONS = 4
_GOLDEN = 0x9E3779B97F4A7C15


def shingle_hashes(text: str | None, size: int = SHINGLE) -> np.ndarray:
    words = blank_words(text)
    if not words:
        return np.empty(0, np.uint64)
    grams = map(b" ".join, zip(*(words[k:] for k in range(size)), strict=False)) if len(words) >= size else [b" ".join(words)]
    return np.fromiter(map(xxhash.xxh64_intdigest, grams, repeat(SEED)), np.uint64)


def _mixed(h: np.ndarray, k: int) -> np.ndarray:
    """Further 64 bits of a hash (a splitmix step)."""
    z = h + np.uint64(_GOLDEN * k % (1 << 64))
    z = (z ^ z >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ z >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return z ^ z >> np.uint64(31)


def fingerprint(hashes: np.ndarray, words: int = 1) -> bytes:
    """``words`` times 8 bytes; each word has its highest bit first."""
    out = []
    for k in range(words):
        h = _mixed(hashes, k) if k else hashes
        bits = np.zeros(64, np.int64)
        for at in range(0, len(h), 8160):
            some = np.unpackbits(h[at : at + 8160].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            for low in range(0, len(some), 255):
                bits += np.add.reduce(some[low : low + 255], axis=0, dtype=np.uint8)
        out.append(np.packbits(bits * 2 > len(h), bitorder="little").view("<u8").byteswap().tobytes())
    return b"".join(out)


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, words: int = 1, keys: int = 0) -> DataFrame:
    """doc_id, mark (a hash of the text), fp, and the ``keys`` smallest distinct shingle hashes (as signed longs).

    With keys, fingerprints are of distinct shingles and end with the mark: different texts stay apart.
    """
    prepare(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType
    schema = pa.schema([("doc_id", _arrow(kind)), ("mark", pa.int64()), ("fp", pa.binary()), ("keys", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for doc_id, mark, text in rows_of(batches, "doc_id", "mark", "text"):
                h = shingle_hashes(text, shingle)
                if keys:
                    h = np.unique(h)
                    yield doc_id, mark, fingerprint(h, words) + mark.to_bytes(8, "big", signed=True), h[:keys].view(np.int64).tolist()
                else:
                    yield doc_id, mark, fingerprint(h, words), []

        return batched(rows(), schema)

    return docs.select("doc_id", F.xxhash64("text").alias("mark"), "text").mapInArrow(run, f"doc_id {kind.simpleString()}, mark long, fp binary, keys array<long>")


def stripes_for(n: int, bits: int, radius: int) -> int:
    """The fewest stripes with which the mean bucket of one choice holds MEAN_BUCKET rows at most."""
    for stripes in range(radius + 1, 2 * radius + 1):
        if n / 2 ** (bits * (stripes - radius) / stripes) <= MEAN_BUCKET:
            return stripes
    return 2 * radius + 1


def pigeonhole_keys(fp: Column, n: int, words: int, radius: int) -> Column:
    """One bucket key for each choice of stripes: its number and the bits that must agree."""
    bits = 64 * words
    stripes = stripes_for(n, bits, radius)
    edges = [round(k * bits / stripes) for k in range(stripes + 1)]
    parts = [F.conv(F.hex(F.substring(fp, 8 * w + 1, 8)), 16, -10).cast("long") for w in range(words)]

    def masked(chosen: tuple[int, ...]) -> Column:
        keep = [sum(1 << (63 - b % 64) for s in chosen for b in range(edges[s], edges[s + 1]) if b // 64 == w) for w in range(words)]
        signed = [m - (1 << 64) if m >> 63 else m for m in keep]
        return F.xxhash64(*[p.bitwiseAND(F.lit(m)) for p, m in zip(parts, signed, strict=True)]) if words > 1 else parts[0].bitwiseAND(F.lit(signed[0]))

    return F.array(*[F.struct(F.lit(k).alias("table"), masked(c).alias("key")) for k, c in enumerate(combinations(range(stripes), stripes - radius))])


def close_pairs(bits: np.ndarray, group: np.ndarray, radius: int, side: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs i < j of one group within ``radius``; with ``side``, only across its two values.

    ``bits``: a row of 64-bit words for each fingerprint; rows of a group stand together.
    """
    n, words = bits.shape
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]) if n else np.empty(0, np.int64)
    sizes = np.diff(np.r_[first, n])
    blocks = -(-sizes // 64)
    block_of_group = np.cumsum(np.r_[0, blocks])
    which = np.repeat(np.arange(len(first)), sizes)
    place = np.arange(n) - first[which]
    lane, block = place % 64, block_of_group[which] + place // 64
    total = int(block_of_group[-1])
    start_of_block = np.repeat(first, blocks) + 64 * (np.arange(total) - np.repeat(block_of_group[:-1], blocks))
    one = np.uint64(1) << lane.astype(np.uint64)

    def plane(mask: np.ndarray) -> np.ndarray:
        out = np.zeros(total, np.uint64)
        np.bitwise_or.at(out, block[mask], one[mask])
        return out

    def vertical(p: int) -> tuple[np.ndarray, np.ndarray]:
        set_ = (bits[:, p // 64] >> np.uint64(p % 64) & np.uint64(1)).astype(bool)
        return plane(set_), np.where(set_, ~np.uint64(0), np.uint64(0))

    planes = [vertical(p) for p in range(64 * words)]
    exists = plane(np.ones(n, bool))
    right = plane(side) if side is not None else None
    levels = max(2, (radius + 1).bit_length() + 1)
    # A task is a query and a block at or behind the query's own.
    per_query = block_of_group[which + 1] - block
    ends = np.cumsum(per_query)
    step = 1 << 16
    for low in range(0, int(ends[-1]) if n else 0, step):
        task = np.arange(low, min(low + step, int(ends[-1])))
        query = np.searchsorted(ends, task, "right")
        word = block[query] + task - (ends[query] - per_query[query])
        alive = exists[word].copy()
        own = word == block[query]
        # In its own block a query meets only the lanes behind it.
        alive[own] &= ~((one[query[own]] << np.uint64(1)) - np.uint64(1))
        if right is not None:
            across = right[word]
            alive &= np.where(side[query], ~across, across)
        keep = np.flatnonzero(alive)
        query, word, alive = query[keep], word[keep], alive[keep]
        counters = [np.zeros(len(query), np.uint64) for _ in range(levels)]
        for p in range(0, 64 * words, 2):
            (a, qa), (b, qb) = planes[p], planes[p + 1]
            x, y = a[word] ^ qa[query], b[word] ^ qb[query]
            either = counters[0] ^ x
            carry = counters[0] & x | either & y
            counters[0] = either ^ y
            for k in range(1, levels):
                counters[k], carry = counters[k] ^ carry, counters[k] & carry
            alive &= ~carry
            if p % 8 == 6:
                alive &= ~_over(counters, radius)
                if not alive.all():
                    keep = np.flatnonzero(alive)
                    if not len(keep):
                        break
                    if len(keep) < 0.8 * len(alive):
                        query, word, alive = query[keep], word[keep], alive[keep]
                        counters = [c[keep] for c in counters]
        keep = np.flatnonzero(alive)
        if len(keep):
            lanes = np.unpackbits(alive[keep].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            row, at = np.nonzero(lanes)
            yield query[keep][row], start_of_block[word[keep][row]] + at


def _over(counters: list[np.ndarray], radius: int) -> np.ndarray:
    """Lanes whose counter is over the radius, compared bit by bit from the top."""
    over, equal = np.zeros_like(counters[0]), np.full_like(counters[0], ~np.uint64(0))
    for k in reversed(range(len(counters))):
        if radius >> k & 1:
            equal = equal & counters[k]
        else:
            over = over | equal & counters[k]
            equal = equal & ~counters[k]
    return over


def smallest_linked(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]], alike: Callable[[int, int], bool] | None = None) -> np.ndarray:
    """For each index the smallest index that it reaches by pairs; with ``alike``, by those that pass it."""
    label = np.arange(n)
    for i, j in pairs if alike is None else _passing(pairs, label, alike):
        while True:
            low = np.minimum(label[i], label[j])
            if (label[i] == low).all() and (label[j] == low).all():
                break
            np.minimum.at(label, label[i], low)
            np.minimum.at(label, label[j], low)
            while (label[label] != label).any():
                label[:] = label[label]
    return label


def _passing(pairs: Iterator[tuple[np.ndarray, np.ndarray]], label: np.ndarray, alike: Callable[[int, int], bool], lot: int = 4096) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs that pass; those that ``label``, which the caller keeps up to date, has joined already are not tried."""
    for i, j in pairs:
        # A pair of each index first: that joins most of a large group.
        first = np.zeros(len(i), bool)
        first[np.unique(i, return_index=True)[1]] = True
        order = np.argsort(~first, kind="stable")
        i, j, low, high = i[order], j[order], 0, int(first.sum())
        while low < len(i):
            a, b = i[low:high], j[low:high]
            apart = label[a] != label[b]
            a, b = a[apart], b[apart]
            passed = np.fromiter(map(alike, a.tolist(), b.tolist()), bool, len(a))
            if passed.any():
                yield a[passed], b[passed]
            low, high = high, high + lot


class ShingleSets:
    """Whether two texts' sets of shingles reach a Jaccard similarity; sets are kept by name."""

    def __init__(self, size: int, similarity: float):
        self.size, self.similarity = size, similarity
        self.kept: dict[bytes, np.ndarray] = {}

    def of(self, name: bytes, text: str) -> np.ndarray:
        if (found := self.kept.get(name)) is None:
            found = self.kept[name] = np.unique(shingle_hashes(text, self.size))
        return found

    def alike(self, a: np.ndarray, b: np.ndarray) -> bool:
        if min(len(a), len(b)) < self.similarity * max(len(a), len(b)) - 1e-6:
            return False
        both = np.concatenate((a, b))
        both.sort()
        common = int(np.count_nonzero(both[1:] == both[:-1]))
        return common / (len(both) - common) >= self.similarity if len(both) else True


def link(nodes: DataFrame, keys: Column, words: int, radius: int, bucket: int = BUCKET, texts: DataFrame | None = None, size: int = 0, similarity: float = 0.0) -> DataFrame:
    """Links (a, b) between different fingerprints that share a key and lie within the radius.

    With ``texts`` (mark, text), only where the sets of shingles of ``size`` words reach the similarity.
    """
    rows = nodes.select("fp", F.explode(keys).alias("k")).select("fp", "k.table", "k.key")
    # Buckets of several rows, with the number of their chunks.
    chunks = F.when(F.col("count") > bucket, F.ceil(F.col("count") / (bucket // 2))).otherwise(1).cast("int")
    met = rows.groupBy("table", "key").count().where("count > 1").select("table", "key", chunks.alias("chunks"))
    rows = rows.join(met, ["table", "key"]).withColumn("chunk", F.pmod(F.xxhash64("fp", F.lit(7)), "chunks").cast("int"))
    others = F.sequence(F.lit(0), F.col("chunks") - 1)
    rows = rows.withColumn("other", F.explode(others)).select("fp", "table", "key", "chunk", F.least("chunk", "other").alias("low"), F.greatest("chunk", "other").alias("high"))
    rows = rows.withColumn("text", F.lit(None).cast("string")) if texts is None else rows.withColumn("mark", F.conv(F.hex(F.substring("fp", 8 * words + 1, 8)), 16, -10).cast("long")).join(texts, "mark").drop("mark")
    schema = pa.schema([("a", pa.binary()), ("b", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            for part in _whole_groups(batches):
                fps, held, group, chunk, low, high = part
                bits = np.frombuffer(b"".join(fps), ">u8").reshape(len(fps), -1)[:, :words].astype(np.uint64)
                sets = ShingleSets(size, similarity)
                for cross in (False, True):
                    mine = np.flatnonzero((low != high) == cross)
                    if len(mine) < 2:
                        continue
                    side = chunk[mine] == high[mine] if cross else None

                    def alike(i: int, j: int, mine: np.ndarray = mine, fps: list = fps, held: list = held, sets: ShingleSets = sets) -> bool:
                        x, y = mine[i], mine[j]
                        return sets.alike(sets.of(fps[x], held[x]), sets.of(fps[y], held[y]))

                    label = smallest_linked(len(mine), close_pairs(bits[mine], group[mine], radius, side), alike if similarity else None)
                    for k in np.flatnonzero(label != np.arange(len(mine))).tolist():
                        yield fps[mine[k]], fps[mine[label[k]]]

        return batched(out(), schema, 8192)

    return rows.repartition("table", "key", "low", "high").sortWithinPartitions("table", "key", "low", "high").mapInArrow(run, "a binary, b binary")


def _whole_groups(batches: Iterator[pa.RecordBatch], least: int = 1 << 15, least_chars: int = 1 << 24) -> Iterator[tuple]:
    """Rows of sorted batches in lots of whole groups: fingerprints, texts, group numbers, chunk, low, high."""
    held: list[tuple] = []
    number, last, chars = 0, None, 0
    for fp, text, table, key, chunk, low, high in rows_of(batches, "fp", "text", "table", "key", "chunk", "low", "high"):
        if (me := (table, key, low, high)) != last:
            if len(held) >= least or chars >= least_chars:
                yield _columns(held)
                held, chars = [], 0
            number, last = number + 1, me
        held.append((fp, text, number, chunk, low, high))
        chars += len(text or "")
    if held:
        yield _columns(held)


def _columns(held: list[tuple]) -> tuple:
    fps, texts, *rest = zip(*held, strict=True)
    return (list(fps), list(texts), *(np.array(x) for x in rest))


def components(links: DataFrame) -> DataFrame:
    """(node, root): the smallest node that each linked node reaches, for all but the roots themselves."""
    found = SharedTable(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v"), "links")
    if found.read().count() <= FEW:
        roots = SharedTable(_joined_up(found.read()), "roots")
        found.drop()
        return roots.read()
    return _star_rounds(found)


def _joined_up(edges: DataFrame) -> DataFrame:
    """The components of at most ``FEW`` edges (u, v), in one task."""
    kind = edges.schema["u"].dataType
    schema = pa.schema([("node", _arrow(kind)), ("root", _arrow(kind))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs = list(rows_of(batches, "u", "v"))
        nodes = sorted({x for pair in pairs for x in pair})
        place = {x: k for k, x in enumerate(nodes)}
        i, j = (np.fromiter((place[pair[side]] for pair in pairs), np.int64, len(pairs)) for side in (0, 1))
        label = smallest_linked(len(nodes), iter([(i, j)]))
        return batched(((nodes[k], nodes[label[k]]) for k in np.flatnonzero(label != np.arange(len(nodes))).tolist()), schema, 8192)

    return edges.coalesce(1).mapInArrow(run, f"node {kind.simpleString()}, root {kind.simpleString()}")


def _star_rounds(found: SharedTable) -> DataFrame:
    """The components of any number of edges by alternating star rounds; drops the table of the edges."""
    now = SharedTable(found.read().distinct(), "links")
    found.drop()
    seen = None
    while True:
        edges = now.read()
        # Every node's larger neighbours move to its smallest neighbour, or to itself.
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        large = _with_least(both.where(F.col("v") > F.col("u")), least).select(F.col("v").alias("u"), F.col("m").alias("v"))
        # Every node and its smaller neighbours move to the smallest of these.
        least = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        small = _with_least(large, least).select(F.explode(F.array("u", "v")).alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        after = SharedTable(small, "links")
        state = after.read().agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        now.drop()
        now = after
        if tuple(state) == seen:
            return now.read().select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = tuple(state)


def _with_least(edges: DataFrame, least: DataFrame) -> DataFrame:
    """Edges with the smallest neighbour ``m`` of their node ``u``.

    The nodes with over ``HUB`` edges, of which there is one for each ``HUB`` edges at most, are broadcast while they are
    no more than ``HUBS``: the edges of a node that all copies hang on stay where they are.
    """
    hubs = least.where(F.col("n") > HUB).select("u", "m")
    found = hubs.limit(HUBS + 1).count()
    if not 0 < found <= HUBS:
        return edges.join(least.select("u", "m"), "u")
    marked = edges.join(F.broadcast(hubs.withColumnRenamed("m", "_hub")), "u", "left")
    rest = marked.where("_hub is null").drop("_hub").join(least.where(F.col("n") <= HUB).select("u", "m"), "u")
    return marked.where("_hub is not null").withColumnRenamed("_hub", "m").select(*rest.columns).unionByName(rest)


def clusters(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """doc_id, fp and component_id: the smallest doc_id reachable by links of at most ``radius`` bits."""
    prints = SharedTable(fingerprints(docs, shingle).select("doc_id", "fp"), "fingerprints").read()
    nodes = prints.groupBy("fp").agg(F.min("doc_id").alias("least_id"))
    n = nodes.count()
    roots = components(link(nodes, pigeonhole_keys(F.col("fp"), n, 1, radius), 1, radius))
    return _labelled(prints, nodes, roots)


def _labelled(prints: DataFrame, nodes: DataFrame, roots: DataFrame) -> DataFrame:
    rooted = nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least_id").alias("component_id"))
    names = rooted.join(least, "root").select("fp", "root", "component_id")
    # A fingerprint that a third of the documents have is dealt out by AQE's skew join.
    return prints.join(names, "fp")


def radius_for(similarity: float, words: int) -> int:
    """Bits by which fingerprints of sets with that Jaccard similarity hardly ever differ: the mean and ``DEVIATIONS``.

    The mean is the larger one of big sets of one size and of the smallest set that the threshold
    lets differ, with one more shingle: a bit of it flips where the common shingles are at the border.
    """
    cosine = 2 * similarity / (1 + similarity)
    common = math.ceil(round(similarity / (1 - similarity), 9))
    share = max(math.acos(cosine) / math.pi, math.comb(common, (common + 1) // 2) / 2 ** (common + 1))
    bits = 64 * words
    return round(bits * share + DEVIATIONS * math.sqrt(bits * share * (1 - share)))


def similar_clusters(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, words: int = 4, keys: int = KEYS) -> DataFrame:
    """doc_id, mark, fp, root and component_id for texts whose sets of shingles reach a Jaccard similarity.

    Texts of fewer words than a shingle are one shingle: only equal ones are linked.
    """
    prints = SharedTable(fingerprints(docs, shingle, words, keys), "fingerprints").read()
    nodes = prints.groupBy("fp").agg(F.min("doc_id").alias("least_id"))
    keyed = prints.dropDuplicates(["fp"]).select("fp", "keys")
    every = F.transform("keys", lambda k: F.struct(F.lit(0).alias("table"), k.alias("key")))
    # One text for each hash of a text.
    texts = docs.select(F.xxhash64("text").alias("mark"), "text").groupBy("mark").agg(F.first("text").alias("text"))
    roots = components(link(keyed, every, words, radius_for(similarity, words), BUCKET, texts, shingle, similarity))
    return _labelled(prints.select("doc_id", "mark", "fp"), nodes, roots)


def keep_one(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """The documents with one row of each group of near copies: the one with the smallest doc_id.

    Every row of a group but one goes, repeated rows too. Texts without words and rows without an
    id stay, all of them.
    """
    apart = F.col("doc_id").isNull() | ~F.rlike(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]"))
    found = similar_clusters(docs.where(~apart).select("doc_id", "text"), shingle, similarity)
    kept = found.groupBy("root").agg(F.min(F.struct("doc_id", "mark")).alias("kept")).select(F.col("kept.doc_id").alias("_id"), F.col("kept.mark").alias("_mark"))
    met = (F.col("doc_id") == F.col("_id")) & (F.xxhash64("text") == F.col("_mark"))
    first = docs.where(~apart).join(kept, met).dropDuplicates(["_id", "_mark"]).drop("_id", "_mark")
    return docs.where(apart).unionByName(first)


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", F.lower(F.hex("fp")).alias("fingerprint"), "component_id")

