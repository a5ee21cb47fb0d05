"""Prefix sums over any number of rows without a one-task window."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .held import hold


def ranged(df: DataFrame, *keys: str) -> DataFrame:
    """Rows range-partitioned by the keys, with ``_range``, the number of their range. Held, so that bounds are drawn once."""
    return hold(df.repartitionByRange(*keys).withColumn("_range", F.spark_partition_id()))


def scan(df: DataFrame, key: str, cols: Sequence[str], by: Sequence[str] = ()) -> DataFrame:
    """Adds ``<col>_upto``: the sum over the rows of the same ``by`` whose key is not larger.

    Keys must be distinct within ``by``. Rows are range-partitioned by (by, key); each range is
    scanned alone and shifted by the totals of the ranges before it. Without groups these are a row for
    each range, broadcast; with groups their number follows the data and the join is Spark's choice.
    """
    parts = ranged(df, *by, key)
    own = Window.partitionBy("_range", *by)
    totals = parts.groupBy("_range", *by).agg(*[F.sum(c).alias(f"_{c}") for c in cols])
    before = Window.partitionBy(*by).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_range", *by, *[F.sum(f"_{c}").over(before).alias(f"_{c}_before") for c in cols])
    upto = own.orderBy(key).rowsBetween(Window.unboundedPreceding, 0)
    local = parts.select("*", *[F.sum(c).over(upto).alias(f"{c}_upto") for c in cols])
    out = local.join(offsets if by else F.broadcast(offsets), ["_range", *by])
    for c in cols:
        out = out.withColumn(f"{c}_upto", F.col(f"{c}_upto") + F.coalesce(F.col(f"_{c}_before"), F.lit(0)))
    return out.drop("_range", *[f"_{c}_before" for c in cols])


def next_key(df: DataFrame, key: str, name: str) -> DataFrame:
    """Adds the next larger key (null for the last): a range's last row looks at the first key of the ranges behind it."""
    parts = ranged(df, key)
    firsts = parts.groupBy("_range").agg(F.min(key).alias("_first"))
    after = Window.orderBy("_range").rowsBetween(1, Window.unboundedFollowing)
    # A row for each range.
    following = firsts.select("_range", F.min("_first").over(after).alias("_following"))
    inside: Column = F.lead(key).over(Window.partitionBy("_range").orderBy(key))
    return parts.withColumn(name, inside).join(F.broadcast(following), "_range").withColumn(name, F.coalesce(name, "_following")).drop("_range", "_following")
