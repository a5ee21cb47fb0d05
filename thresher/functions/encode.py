"""Attributes to the ordered integer domain 1..N, and labels to the forms the methods take."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.prefix import scan


def fixed_point(col: str | Column, scale: int = 100) -> Column:
    """A decimal number as a whole number of its ``1 / scale`` parts."""
    return F.round(_c(col) * scale).cast("long")


def day_number(col: str | Column, first_day: str = "1995-01-01") -> Column:
    """Days since ``first_day``, counted from 1."""
    return (F.datediff(_c(col), F.lit(first_day).cast("date")) + 1).cast("long")


def second_number(col: str | Column, first: str = "2024-01-01") -> Column:
    """Seconds since ``first``, counted from 1."""
    return (F.unix_timestamp(_c(col).cast("timestamp")) - F.unix_timestamp(F.lit(first).cast("timestamp")) + 1).cast("long")


def equal_width(col: str | Column, low: float, high: float, bins: int) -> Column:
    return F.width_bucket(_c(col), F.lit(float(low)), F.lit(float(high)), F.lit(bins)).cast("long")


def quantile(df: DataFrame, col: str, bins: int, accuracy: int = 10_000) -> DataFrame:
    """Adds ``x``: the number of approximate quantiles below the value, plus 1."""
    cuts = df.agg(F.percentile_approx(col, [k / bins for k in range(1, bins)], accuracy)).first()[0] or []
    cuts = sorted(set(cuts))
    return df.withColumn("x", (F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col(col))) + 1).cast("long") if cuts else F.lit(1).cast("long"))


def dense_rank(df: DataFrame, col: str) -> DataFrame:
    """Adds ``x``: the value's rank among distinct values, from 1, without a one-task window."""
    distinct = df.select(col).where(F.col(col).isNotNull()).distinct().withColumn("one", F.lit(1).cast("long"))
    ranked = scan(distinct, col, ["one"]).select(col, F.col("one_upto").alias("x"))
    return df.join(ranked, col)


def categorical_index(df: DataFrame, col: str) -> DataFrame:
    """Adds ``x``: categories numbered by their text."""
    return dense_rank(df, col)


def to_pm1(condition: Column) -> Column:
    return F.when(condition, F.lit(1)).otherwise(F.lit(-1))


def rescale(y: str | Column, maximum: float) -> Column:
    """Labels of [0, maximum] to [0, 1]."""
    return _c(y) / F.lit(float(maximum))


def shift(y: str | Column, minimum: float) -> Column:
    """Labels with the given minimum to labels from 0; squared error does not change."""
    return _c(y) - F.lit(minimum)


def observations(df: DataFrame, x: Column, y: Column, *keys: str) -> DataFrame:
    """(x, y, keys) without null or not-a-number values; everything else is pruned from the scan."""
    out = df.select(x.cast("long").alias("x"), y.alias("y"), *keys).where("x is not null and y is not null")
    return out.where(~F.isnan("y")) if dict(out.dtypes)["y"] in ("double", "float") else out


def dropped_rows(df: DataFrame, x: Column, y: Column) -> DataFrame:
    """One row: rows, and rows that ``observations`` would drop."""
    bad = x.isNull() | y.isNull() | F.coalesce(F.isnan(y.cast("double")), F.lit(False))
    return df.select(bad.alias("bad")).agg(F.count("*").alias("rows"), F.count_if("bad").alias("dropped"))


def _c(col: str | Column) -> Column:
    return F.col(col) if isinstance(col, str) else col
