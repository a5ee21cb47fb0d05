"""Relational operators around the searches: labelled and unlabelled rows, set tests, as-of and interval joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .held import hold


def labelled(rows: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    return rows.join(labels.select(key), key, "left_semi")


def unlabelled(rows: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    return rows.join(labels.select(key), key, "left_anti")


def shared(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Elements of both sets: empty if and only if the two are disjoint."""
    return a.select(key).intersect(b.select(key))


def without(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Elements of the first set only, such as values that no sample row has."""
    return a.select(key).subtract(b.select(key))


def as_of(rows: DataFrame, points: DataFrame, on: str, value: str) -> DataFrame:
    """Each row with the value of the last point at or before it, by merging both in order of range.

    The last point of all ranges before a row's own comes from a row for each range, which are few.
    """
    # A point stands before the rows of its own place.
    tagged = rows.withColumns({"_side": F.lit(1), "_at": F.lit(None).cast(points.schema[on].dataType), "_value": F.lit(None).cast(points.schema[value].dataType)})
    blank = [F.lit(None).cast(f.dataType).alias(f.name) for f in rows.schema if f.name != on]
    named = points.select(F.col(on), *blank, F.lit(0).alias("_side"), F.col(on).alias("_at"), F.col(value).alias("_value"))
    ranged = hold(tagged.unionByName(named).repartitionByRange(on).withColumn("_range", F.spark_partition_id()))
    inside = Window.partitionBy("_range").orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    point = F.when(F.col("_side") == 0, F.struct("_at", "_value"))
    ends = ranged.groupBy("_range").agg(F.max(point).alias("_end"))
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select("_range", F.max("_end").over(before).alias("_carried"))
    found = ranged.withColumn("_last", F.last(point, ignorenulls=True).over(inside)).where("_side = 1").join(F.broadcast(carried), "_range")
    return found.withColumn(value, F.coalesce("_last", "_carried")["_value"]).select(*rows.columns, value)


def interval_join(events: DataFrame, labels: DataFrame, key: str, time: str, label_time: str, within: str, watermark: str = "1 hour") -> DataFrame:
    """An event with each later label of its key within a time bound; both sides may be streams."""
    a = events.withWatermark(time, watermark) if events.isStreaming else events
    b = labels.withWatermark(label_time, watermark) if labels.isStreaming else labels
    b = b.withColumnRenamed(key, "_key")
    met = (F.col(key) == F.col("_key")) & (F.col(label_time) >= F.col(time)) & (F.col(label_time) <= F.col(time) + F.expr(f"INTERVAL {within}"))
    return a.join(b, met).drop("_key")
