"""Exact top-k inner products by best-first search in M-trees.

Vectors are dealt to shards of bounded size and each shard becomes one M-tree of several levels: pages of
entries, every entry with its routing vector, covering radius and stored distance to the parent. Trees are
built once and stored; a tree then moves to one task, and the blocks of queries go to all trees.

A block of queries descends together, best first: the page whose bound exceeds some query's k-th best by most comes
next. For a node with routing vector c and radius r no vector below it has a larger inner product
than q.c + |q| r; and since |q.c - q.p| <= |q| d(c, p), the stored parent distance bounds an entry
from its parent's product before the entry's own is computed. A page is computed for those queries and
entries alone that such a bound leaves, so ties are searched. The first shard's k-th best scores are where the
search of all other shards begins.

Queries come in blocks of bounded size; a block meets every shard (that is the stated query
set against all rows). Each returns its best k, and the best of these are the result.

Scores are whole numbers: products of floats are exact below 2**53, and where norms allow more, leaves are
computed in whole numbers of any size. Bounds of pages leave a relative slack for rounding.

Defined cases: vectors that are null or hold null or non-finite components take no part, nor do
vectors of another length than the query's; equal vectors are told apart by id, smaller first;
rows with a null id take no part; a query does not meet rows of its own id; a repeated id that asks is one query for
each of its rows; fewer candidates than k give fewer rows; scores beyond 64 bits are the ends of that range; an empty
table gives none; further columns are ignored.
"""

from __future__ import annotations

import heapq
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import SharedTable, batched, prepare, rows_of

K, SCALE, QUERY_EVERY = 5, 256, 50
PAGE, FANOUT = 128, 16
#: Rows of a shard: a 64th of the table within these limits.
SHARD_ROWS, SHARD_MAX, BLOCK_ROWS = 16_384, 131_072, 512
#: Products below this are exact as floats.
EXACT = 2.0**52
#: What rounding may add to a bound, as a share of the norms' product.
SLACK = 1e-9


class Node:
    """A page: routing vector, radius, and entries; leaves hold distinct vectors with their ids."""

    __slots__ = ("children", "ids", "owner", "parent_distances", "radii", "vectors")

    def __init__(self, vectors: np.ndarray, radii: np.ndarray | None, parent_distances: np.ndarray, children: list[Node] | None, ids: np.ndarray | None, owner: np.ndarray | None):
        self.vectors, self.radii, self.parent_distances = vectors, radii, parent_distances
        self.children, self.ids, self.owner = children, ids, owner


def build(vectors: np.ndarray, ids: np.ndarray) -> tuple[Node, np.ndarray]:
    """The M-tree of a shard and its root's routing vector. Distances are Euclidean; equal vectors share a leaf entry."""
    distinct, owner = np.unique(vectors, axis=0, return_inverse=True)
    order = np.lexsort((ids, owner := owner.reshape(-1)))
    bounds = np.searchsorted(owner[order], np.arange(len(distinct) + 1))
    center = distinct.mean(0)
    return _grow(distinct, np.arange(len(distinct)), ids[order], bounds, center), center


def _distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.sqrt(((x - c) ** 2).sum(1))


def _grow(x: np.ndarray, rows: np.ndarray, ids: np.ndarray, bounds: np.ndarray, parent: np.ndarray) -> Node:
    mine = x[rows]
    if len(rows) <= PAGE:
        counts = bounds[rows + 1] - bounds[rows]
        own = np.concatenate([ids[bounds[r] : bounds[r + 1]] for r in rows]) if len(rows) else ids[:0]
        return Node(mine, None, _distances(mine, parent), None, own, np.repeat(np.arange(len(rows)), counts))
    # Rows are in order of their components, so evenly spaced ones lie apart.
    pivots = np.unique(np.linspace(0, len(rows) - 1, FANOUT).astype(int)).tolist()
    nearest, home = _distances(mine, mine[pivots[0]]), np.zeros(len(rows), np.int64)
    for k, p in enumerate(pivots[1:], 1):
        d = _distances(mine, mine[p])
        home[d < nearest] = k
        nearest = np.minimum(nearest, d)
    vectors, radii, children = [], [], []
    for k, p in enumerate(pivots):
        part = rows[home == k]
        center = mine[p]
        children.append(_grow(x, part, ids, bounds, center))
        vectors.append(center)
        radii.append(_distances(x[part], center).max())
    vectors = np.array(vectors)
    return Node(vectors, np.array(radii), _distances(vectors, parent), children, None, None)


class Best:
    """The best k (score, id) of each query of a block, larger scores and then smaller ids first."""

    def __init__(self, own: np.ndarray, k: int, floor: np.ndarray | None = None):
        self.own, self.k = own, k
        self.found: list[list[tuple[int, int]]] = [[] for _ in own]
        #: What a score must reach: the k-th best, or what is known from elsewhere.
        self.worst = np.full(len(own), -np.inf) if floor is None else floor.copy()

    def offer(self, query: int, scores: np.ndarray, ids: np.ndarray) -> None:
        fit = np.flatnonzero((scores >= self.worst[query]) & (ids != self.own[query]))
        if not len(fit):
            return
        have = sorted(self.found[query] + [(-_whole(scores[i]), int(ids[i])) for i in fit.tolist()])[: self.k]
        self.found[query] = have
        if len(have) == self.k:
            self.worst[query] = max(self.worst[query], float(-have[-1][0]))


def _whole(score) -> int:
    return max(-(1 << 63), min((1 << 63) - 1, int(score)))


def search(root: Node, center: np.ndarray, queries: np.ndarray, own: np.ndarray, k: int, floor: np.ndarray | None = None) -> tuple[Best, int]:
    """The best of a block of queries, and the number of products that the bounds did not spare."""
    best, computed, tick = Best(own, k, floor), 0, 0
    norms = np.sqrt((queries * queries).sum(1))
    size = float(np.sqrt((center * center).sum()))
    everyone = np.arange(len(queries))
    # (least promise first, tick, node, its queries, their bounds, their products with the node's routing vector, the routing vector's norm)
    queue = [(-np.inf, 0, root, everyone, np.full(len(queries), np.inf), queries @ center, size)]
    while queue:
        _, _, node, who, bound, at_parent, size = heapq.heappop(queue)
        left = bound >= best.worst[who]
        if not left.any():
            continue
        who, at_parent = who[left], at_parent[left]
        reach = node.parent_distances + (node.radii if node.radii is not None else 0.0)
        slack = SLACK * norms[who][:, None] * (size + reach)[None, :] + 1e-6
        # From the stored distance to the parent alone.
        open_ = at_parent[:, None] + norms[who][:, None] * reach[None, :] + slack >= best.worst[who][:, None]
        asks, entries = np.flatnonzero(open_.any(1)), np.flatnonzero(open_.any(0))
        if not len(asks):
            continue
        computed += int(open_.sum())
        who, vectors = who[asks], node.vectors[entries]
        open_ = open_[np.ix_(asks, entries)]
        if node.children is None:
            _leaf(best, node, who, entries, queries[who], vectors, open_, norms[who])
            continue
        products = queries[who] @ vectors.T
        bounds = products + norms[who][:, None] * node.radii[entries][None, :] + slack[np.ix_(asks, entries)]
        bounds[~open_] = -np.inf
        for e, child in enumerate(entries.tolist()):
            mine = np.flatnonzero(bounds[:, e] >= best.worst[who])
            if len(mine):
                tick += 1
                gain = bounds[mine, e] - best.worst[who[mine]]
                own_size = float(np.sqrt(vectors[e] @ vectors[e]))
                heapq.heappush(queue, (-float(gain.max()), tick, node.children[child], who[mine], bounds[mine, e], products[mine, e], own_size))
    return best, computed


def _leaf(best: Best, node: Node, who: np.ndarray, entries: np.ndarray, queries: np.ndarray, vectors: np.ndarray, open_: np.ndarray, norms: np.ndarray) -> None:
    if len(vectors) and norms.max() * np.sqrt((vectors * vectors).sum(1)).max() < EXACT:
        products = queries @ vectors.T
    else:
        products = _wholes(queries) @ _wholes(vectors).T
    # Equal vectors share an entry: their ids follow each other.
    starts = np.searchsorted(node.owner, entries)
    counts = np.searchsorted(node.owner, entries, "right") - starts
    ids = node.ids[np.arange(counts.sum()) + np.repeat(starts - np.cumsum(counts) + counts, counts)]
    column = np.repeat(np.arange(len(entries)), counts)
    fits = open_ & (products >= best.worst[who][:, None])
    for row in np.flatnonzero(fits.any(1)).tolist():
        best.offer(int(who[row]), products[row][column], ids)


def _wholes(x: np.ndarray) -> np.ndarray:
    """Whole numbers of any size."""
    return np.array([[int(v) for v in row] for row in x], object).reshape(x.shape)


def usable(vectors: DataFrame, is_query: Column, scale: int = SCALE) -> DataFrame:
    """vec_id, floor(scale * x) as 8-byte floats, and whether it is a query, of the vectors that take part."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    x = F.transform("embedding", lambda v: v.cast("double"))
    ok = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.forall(x, finite)
    return vectors.where(F.coalesce(ok, F.lit(False))).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda v: F.floor(v * scale).cast("double")).alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))


def _lots(rows: DataFrame, lot: Column, extra: str) -> DataFrame:
    """Rows of a lot together: its number, dimension, ids, vectors and a further number of each row as bytes."""
    schema = pa.schema([("lot", pa.int64()), ("dim", pa.int64()), ("ids", pa.binary()), ("data", pa.binary()), ("extra", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            last, ids, data, more = None, [], [], []
            pack = lambda: (*last, np.array(ids, "<i8").tobytes(), np.array(data, "<f8").tobytes(), np.array(more, "<f8").tobytes())
            for number, dim, vec_id, v, x in rows_of(batches, "lot", "dim", "vec_id", "v", "extra"):
                if (number, dim) != last and ids:
                    yield pack()
                    ids, data, more = [], [], []
                last = number, dim
                ids.append(vec_id)
                data.append(v)
                more.append(x)
            if ids:
                yield pack()

        return batched(out(), schema, 1)

    numbered = rows.select(lot.cast("long").alias("lot"), F.size("v").cast("long").alias("dim"), "vec_id", "v", F.col(extra).alias("extra"))
    return numbered.repartition("dim", "lot").sortWithinPartitions("dim", "lot", "vec_id").mapInArrow(run, "lot long, dim long, ids binary, data binary, extra binary")


def _trees(lots: DataFrame) -> DataFrame:
    """A tree for each lot."""
    schema = pa.schema([("lot", pa.int64()), ("dim", pa.int64()), ("tree", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            for lot, dim, ids, data in rows_of(batches, "lot", "dim", "ids", "data"):
                tree = build(np.frombuffer(data, "<f8").reshape(len(ids) // 8, dim), np.frombuffer(ids, "<i8"))
                yield lot, dim, pickle.dumps(tree, protocol=5)

        return batched(out(), schema, 1)

    return lots.mapInArrow(run, "lot long, dim long, tree binary")


def _met(trees: DataFrame, asks: DataFrame, k: int) -> DataFrame:
    """(query_id, vec_id, score): what each block of queries (block, dim, q_ids, q_data, floors, lot) finds in its tree.

    A tree goes to one task, once, and the blocks that it meets come behind it.
    """
    none = F.lit(None)
    stems = trees.select("lot", "dim", F.lit(-1).cast("long").alias("block"), "tree", *[none.cast("binary").alias(c) for c in ("q_ids", "q_data", "floors")])
    rows = stems.unionByName(asks.select("lot", "dim", "block", none.cast("binary").alias("tree"), "q_ids", "q_data", "floors"))
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            have, root, center = None, None, None
            for lot, dim, tree, q_ids, q_data, floors in rows_of(batches, "lot", "dim", "tree", "q_ids", "q_data", "floors"):
                if tree is not None:
                    have, (root, center) = (lot, dim), pickle.loads(tree)
                elif have == (lot, dim):
                    own = np.frombuffer(q_ids, "<i8")
                    best, _ = search(root, center, np.frombuffer(q_data, "<f8").reshape(len(own), dim), own, k, np.frombuffer(floors, "<f8"))
                    for me, found in zip(own.tolist(), best.found, strict=True):
                        for score, other in found:
                            yield me, other, -score

        return batched(out(), schema, 4096)

    ordered = rows.repartition("lot", "dim").sortWithinPartitions("lot", "dim", "block")
    return ordered.mapInArrow(run, "query_id long, vec_id long, score long")


def _blocks(asking: DataFrame, blocks: int) -> DataFrame:
    """Queries (vec_id, v, floor) in blocks, each one row."""
    lots = _lots(asking, F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)), "floor")
    return lots.select(F.col("lot").alias("block"), "dim", F.col("ids").alias("q_ids"), F.col("data").alias("q_data"), F.col("extra").alias("floors"))


def top_k(vectors: DataFrame, is_query: Column, k: int = K, shard_rows: int | None = None, block_rows: int = BLOCK_ROWS, scale: int = SCALE) -> DataFrame:
    """query_id, rank, vec_id and score of each query's best k among all other rows."""
    prepare(vectors.sparkSession)
    rows = usable(vectors, is_query, scale)
    n, asked = rows.agg(F.count("*"), F.count_if("asks")).first()
    shard_rows = shard_rows or min(SHARD_MAX, max(SHARD_ROWS, n // 64))
    shards, blocks = max(1, -(-n // shard_rows)), max(1, -(-asked // block_rows))
    trees = SharedTable(_trees(_lots(rows.withColumn("floor", F.lit(0.0)), F.pmod(F.xxhash64("vec_id"), F.lit(shards)), "floor")), "mtree-shards").read()
    asking, lowest = rows.where("asks").drop("asks"), F.lit(float("-inf"))
    one = F.lit(0).cast("long").alias("lot")
    found = _met(trees.where("lot = 0"), _blocks(asking.withColumn("floor", lowest), blocks).select("*", one), k)
    if shards > 1:
        first = SharedTable(found, "mtree-first").read()
        # The k-th best of one shard is a bound for all: the same query meets vectors of its own length there.
        floors = first.groupBy(F.col("query_id").alias("vec_id")).agg(F.when(F.count("*") >= k, F.min(F.struct("score"))["score"].cast("double")).alias("floor"))
        single = asking.groupBy("vec_id").count().where("count = 1").select("vec_id")
        known = asking.join(floors.join(single, "vec_id", "left_semi"), "vec_id", "left").withColumn("floor", F.coalesce("floor", lowest))
        others = F.explode(F.sequence(F.lit(1).cast("long"), F.lit(shards - 1).cast("long"))).alias("lot")
        found = first.unionByName(_met(trees.where("lot > 0"), _blocks(known, blocks).select("*", others), k))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
