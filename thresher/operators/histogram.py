"""Sufficient statistics: everything a split's loss needs, in one mergeable aggregate.

Sums of labels and of their squares are exact at any number of rows. A row adds digits to the base
2**21 to long sums, which stay inside generated code and hold for 2**40 rows of a group; ``joined``
puts the digits together as decimals, a row for each group.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labels must be smaller than this, two digits; larger ones need a coarser fixed point.
LABEL_LIMIT = 1 << 42
BITS = 21
PARTS = {"mse": ("n", "s0", "s1", "q0", "q1", "q2", "q3"), "label": ("pos", "neg")}


def part_names(criterion: str) -> tuple[str, ...]:
    return PARTS["mse" if criterion == "mse" else "label"]


def part_columns(criterion: str, y: Column) -> dict[str, Column]:
    """What a row adds to each part; null labels add nothing."""
    if criterion != "mse":
        return {"pos": (y > 0).cast("long"), "neg": (y <= 0).cast("long")}
    number = y.cast("long")
    number = F.when(F.abs(number) < LABEL_LIMIT, number).when(number.isNotNull(), F.raise_error(F.lit("labels must be below 2**42 fixed-point units")).cast("long"))
    low = lambda c: c.bitwiseAND(F.lit((1 << BITS) - 1))
    high = lambda c: F.shiftright(c, BITS)
    v, u = low(number), high(number)
    ends, cross, tops = v * v, F.lit(2) * u * v, u * u
    return {"n": number.isNotNull().cast("long"), "s0": v, "s1": u, "q0": low(ends), "q1": high(ends) + low(cross), "q2": high(cross) + low(tops), "q3": high(tops)}


def part_sums(criterion: str, y: Column) -> list[Column]:
    return [F.coalesce(F.sum(c), F.lit(0).cast("long")).alias(name) for name, c in part_columns(criterion, y).items()]


def joined(criterion: str, prefix: str = "") -> list[Column]:
    """n, s, q (or pos, neg) from summed parts."""
    if criterion != "mse":
        return [F.col(f"{prefix}{c}").alias(f"{prefix}{c}") for c in ("pos", "neg")]
    part = lambda c: F.col(f"{prefix}{c}").cast("decimal(20,0)")
    digits = lambda name, k: part(f"{name}{k}") * whole(1 << BITS * k, "decimal(20,0)") if k else part(f"{name}0")
    s = (digits("s", 1) + digits("s", 0)).cast("decimal(38,0)")
    q = (digits("q", 3) + digits("q", 2) + digits("q", 1) + digits("q", 0)).cast("decimal(38,0)")
    return [F.col(f"{prefix}n").alias(f"{prefix}n"), s.alias(f"{prefix}s"), q.alias(f"{prefix}q")]


def whole_sums(criterion: str, row: Sequence[int]) -> tuple[int, ...]:
    """The same on the driver, of one row of parts."""
    if criterion != "mse":
        return tuple(row)
    n, s0, s1, *q = row
    return n, (s1 << BITS) + s0, sum(d << BITS * k for k, d in enumerate(q))


def whole(value: int, kind: str) -> Column:
    """A whole number of any size as a column: it travels as text."""
    return F.lit(str(int(value))).cast(kind)


def aggregate_over(grouped, keys: Sequence[str], criterion: str, y: Column) -> DataFrame:
    """Keys and exact sums of grouped data, which may be a rollup or a cube: sums stay mergeable."""
    return grouped.agg(*part_sums(criterion, y)).select(*keys, *joined(criterion))


def aggregate(df: DataFrame, keys: Sequence[str | Column], criterion: str, y: Column) -> DataFrame:
    """A row for each group: keys and exact sums; partial sums are taken before the shuffle."""
    parts = df.groupBy(*keys).agg(*part_sums(criterion, y))
    names = set(part_names(criterion))
    return parts.select(*[F.col(f"`{c}`") for c in parts.columns if c not in names], *joined(criterion))


def histogram(obs: DataFrame, criterion: str = "mse", by: Sequence[str] = (), x: str = "x", y: str = "y") -> DataFrame:
    """A row for each distinct x (and ``by``)."""
    return aggregate(obs, [*by, x], criterion, F.col(y))
