"""Sharding by sampled splitters, with DataFrame functions only.

A row's key is a hash of its text with a hash of its id behind it, so that equal texts are
neighbours in key order. Keys are drawn with a probability proportional to the row's size, by a
hash of the row and not by a random number, and their quantiles are the splitters. Rows are dealt
to ranges by binary search in the splitters; a range's sizes are then summed in key order, and
the totals of the ranges before it turn that into a global offset. A shard is the part of the
total that the offset lies in, so a range that holds more than its share is subdivided where the
share ends. Rows above a fiftieth of a share, of which there is a bounded number, are placed
before the others, and the ranges fill what they leave: shards differ by less than a fiftieth of
a share, whatever one text's share of the rows is, unless one row alone is beyond a share.

The law is ``bytes``. Groups of equal texts stay in one shard unless it is full.

Defined cases: null texts have no bytes and the checksum of nothing; rows that are equal in
text and id are told apart by nothing and may swap places; null ids sort by the hash of no id;
an empty table gives no rows; one document larger than a share takes a shard's place alone;
further columns are ignored by ``assign`` and kept by ``deal``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import SharedTable, prepare

SHARDS, ROW_BYTES = 40, 16
#: Rows above this part of a share are placed first, one by one; there are at most shards * PARTS.
PARTS = 50
#: Ranges of the splitters at least, and expected draws for each of them.
RANGES, DRAWS = 64, 64
#: Bytes of rows (not of texts) that a range should hold at most at larger sizes.
RANGE_ROWS = 2_000_000


def keyed(docs: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, size, text_crc32, the key (k, t), and the columns to keep."""
    text = F.coalesce("text", F.lit(""))
    size = (F.octet_length(text) + ROW_BYTES).cast("long")
    return docs.select("doc_id", size.alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("k"), F.xxhash64("doc_id", text, F.lit(1)).alias("t"), *keep)


def splitters(rows: DataFrame, ranges: int, total: int) -> list[tuple[int, int]]:
    """Quantile boundaries of a size-weighted sample of about ``ranges * DRAWS`` keys."""
    chance = F.col("size") * (ranges * DRAWS / max(1, total))
    draw = F.pmod(F.xxhash64("k", "t", F.lit(2)), F.lit(1 << 53)) / float(1 << 53)
    # A row larger than a draw's worth counts as often as its size says: it fills a range.
    times = F.floor(chance) + (draw < chance - F.floor(chance)).cast("int")
    drawn = rows.select("k", "t", times.alias("times")).where("times > 0")
    order = Window.orderBy("k", "t")
    # Bounded: ranges * DRAWS draws are expected from any number of rows.
    weighed = drawn.select("k", "t", "times", F.sum("times").over(order).alias("upto"), F.sum("times").over(Window.partitionBy()).alias("all"))
    slot = F.floor((F.col("upto") - F.col("times")) * ranges / F.col("all"))
    cuts = weighed.groupBy(slot.alias("slot")).agg(F.min(F.struct("k", "t")).alias("cut")).where("slot > 0")
    return sorted({(x.cut.k, x.cut.t) for x in cuts.collect()})


def range_of(cuts: list[tuple[int, int]]) -> Column:
    """The number of splitters at or below the row's key, by binary search."""
    if not cuts:
        return F.lit(0)
    held = F.array(*[F.struct(F.lit(k).cast("long").alias("k"), F.lit(t).cast("long").alias("t")) for k, t in cuts])
    steps = F.array(*[F.lit(1 << b) for b in reversed(range(len(cuts).bit_length()))])
    me = F.struct("k", "t")

    def move(at: Column, step: Column) -> Column:
        there = at + step
        return F.when((there <= len(cuts)) & (F.get(held, there - 1) <= me), there).otherwise(at)

    return F.aggregate(steps, F.lit(0), move)


def heavy_places(groups: list[tuple[int, int, int]], shards: int, share: float) -> tuple[dict[int, int], list[tuple[int, list[int]]], list[int]]:
    """Shards for the rows above the limit: (key, row size, rows) groups, largest first, to the lightest shard.

    Returns the shard of each group that stays whole, the shards of each group's rows that doesn't,
    and the bytes that every shard then holds.
    """
    load = [0] * shards
    whole, spread = {}, []
    for k, size, rows in sorted(groups, key=lambda g: (-g[1] * g[2], g[0])):
        least = min(range(shards), key=load.__getitem__)
        if rows == 1 or load[least] + size * rows <= share:
            whole[k] = least
            load[least] += size * rows
            continue
        places = []
        for _ in range(rows):
            least = min(range(shards), key=load.__getitem__)
            places.append(least)
            load[least] += size
        spread.append((k, sorted(places)))
    return whole, spread, load


def quotas(load: list[int], light: int) -> list[int]:
    """Light bytes for each shard, so that all reach one level; a shard beyond it gets none."""
    low, high = min(load), max(load) + light
    while low < high:
        level = (low + high) // 2
        if sum(max(0, level - x) for x in load) >= light:
            high = level
        else:
            low = level + 1
    return [max(0, low - x) for x in load]


def assign(docs: DataFrame, shards: int = SHARDS, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard (null: the law is not ``key``), and the columns to keep."""
    spark = docs.sparkSession
    prepare(spark)
    # The texts are read once; what follows reads five numbers a row.
    rows = SharedTable(keyed(docs, keep), "sharding-keys").read()
    n, total = rows.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    limit = total // (shards * PARTS)
    heavy, light = rows.where(F.col("size") > limit), rows.where(F.col("size") <= limit)
    # At most shards * PARTS rows can be larger than that part of a share.
    groups = [(x.k, x.size, x["count"]) for x in heavy.groupBy("k", "size").count().collect()]
    whole, spread, load = heavy_places(groups, shards, total / shards)
    places = [(k, 0, s) for k, s in whole.items()] + [(k, i + 1, s) for k, some in spread for i, s in enumerate(some)]
    named = spark.createDataFrame(places, "k long, nth int, shard int")
    torn = [k for k, _ in spread]
    nth = F.when(F.col("k").isin(torn), F.row_number().over(Window.partitionBy("k").orderBy("t"))).otherwise(0) if torn else F.lit(0)
    placed_heavy = heavy.withColumn("nth", nth).join(F.broadcast(named), ["k", "nth"])
    slot = F.row_number().over(Window.partitionBy("shard").orderBy("k", "t")) - 1
    placed_heavy = placed_heavy.select("doc_id", "size", "text_crc32", *keep, "shard", slot.cast("long").alias("slot"))

    light_total = total - sum(size * count for _, size, count in groups)
    ranges = max(RANGES, -(-n // RANGE_ROWS))
    cuts = splitters(light, ranges, light_total)
    own = Window.partitionBy("range").orderBy("k", "t").rowsBetween(Window.unboundedPreceding, -1)
    local = light.withColumn("range", range_of(cuts)).select(
        "doc_id", "size", "text_crc32", *keep, "range", F.coalesce(F.sum("size").over(own), F.lit(0)).alias("bytes_in"), F.coalesce(F.count("*").over(own), F.lit(0)).alias("rows_in")
    )
    local = SharedTable(local, "sharding").read()
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = local.groupBy("range").agg(F.sum("size").alias("b"), F.count("*").alias("r"))
    # One row for each range.
    starts = sums.select("range", F.coalesce(F.sum("b").over(before), F.lit(0)).alias("bytes_at"), F.coalesce(F.sum("r").over(before), F.lit(0)).alias("rows_at"))
    ends, at = [], 0
    for x in quotas(load, light_total):
        ends.append(at := at + x)
    middle = F.col("bytes_at") + F.col("bytes_in") + F.floor(F.col("size") / 2)
    placed = local.join(F.broadcast(starts), "range").select("doc_id", "size", "text_crc32", *keep, _part_of(ends, middle).alias("shard"), (F.col("rows_at") + F.col("rows_in")).alias("row"))
    # One row for each shard.
    first = placed.groupBy("shard").agg(F.min("row").alias("first_row"))
    before_light = F.get(F.array(*[F.lit(c) for c in _counts(whole, spread, groups, shards)]), F.col("shard"))
    placed = placed.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", *keep, "shard", (F.col("row") - F.col("first_row") + before_light).cast("long").alias("slot"))
    every = placed.unionByName(placed_heavy)
    return every.select("doc_id", "size", "text_crc32", *keep, F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def _part_of(ends: list[int], offset: Column) -> Column:
    """The first part whose end lies beyond the offset, the last one for the rest: binary search."""
    held = F.array(*[F.lit(x).cast("long") for x in ends])
    steps = F.array(*[F.lit(1 << b) for b in reversed(range(len(ends).bit_length()))])
    move = lambda at, step: F.when((at + step < len(ends)) & (F.get(held, at + step - 1) <= offset), at + step).otherwise(at)
    return F.aggregate(steps, F.lit(0), move)


def _counts(whole: dict[int, int], spread: list[tuple[int, list[int]]], groups: list[tuple[int, int, int]], shards: int) -> list[int]:
    """Heavy rows of each shard."""
    found = [0] * shards
    for k, _, rows in groups:
        if k in whole:
            found[whole[k]] += rows
    for _, places in spread:
        for s in places:
            found[s] += 1
    return found


def deal(docs: DataFrame, path: str, shards: int = SHARDS, block_rows: int = 100_000) -> None:
    """Writes the documents, all columns, into one folder for each shard, as files of consecutive slots.

    A task writes ``block_rows`` slots of a shard, so a shard's size does not bound a task; a file's rows are in
    order and its place is the column ``slot_block``. Columns go through as a struct, whatever their names.
    """
    own = docs.select(F.monotonically_increasing_id().alias("_row"), "doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("own"))
    stored = SharedTable(own, "sharding-rows")
    rows = stored.read()
    placed = assign(rows.select("doc_id", "text", "_row"), shards, ("_row",)).select("_row", "shard", "slot")
    out = rows.select("_row", "own").join(placed, "_row").withColumn("slot_block", F.floor(F.col("slot") / block_rows))
    blocks = out.select("own", "slot", "shard", "slot_block").repartition("shard", "slot_block").sortWithinPartitions("shard", "slot_block", "slot")
    blocks.write.partitionBy("shard", "slot_block").parquet(path)
    stored.drop()
