"""Two-way groupings of unordered categories for the misclassification rate."""

from __future__ import annotations

from collections.abc import Sequence
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .sampling import bernoulli

ENUMERATE_MAX = 12


def counts(df: DataFrame, cat: str, y: str) -> DataFrame:
    return df.where(F.col(cat).isNotNull() & F.col(y).isNotNull()).groupBy(F.col(cat).alias("category")).agg(F.count_if(F.col(y) > 0).alias("pos"), F.count_if(F.col(y) <= 0).alias("neg"))


def sides(by_category: DataFrame) -> DataFrame:
    """Every category to its majority side (ties to A, the side of +1): no grouping does better."""
    return by_category.select("category", F.when(F.col("pos") >= F.col("neg"), "A").otherwise("B").alias("side"), "pos", "neg")


def loss_of(split: DataFrame, digits: int = 6) -> DataFrame:
    """One row: the loss of a grouping, each side predicting its majority, and the number of categories."""
    per_side = split.groupBy("side").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"), F.count("*").alias("n"))
    return per_side.agg(F.round(F.sum(F.least("pos", "neg")) / F.sum(F.col("pos") + F.col("neg")), digits).alias("loss"), F.sum("n").alias("categories"))


def exact_split(df: DataFrame, cat: str, y: str) -> DataFrame:
    return sides(counts(df, cat, y))


def enumerate_split(df: DataFrame, cat: str, y: str, digits: int = 6) -> DataFrame:
    """All subsets, for at most 12 categories: one row (loss, groupings)."""
    rows = counts(df, cat, y).orderBy("category").limit(ENUMERATE_MAX + 1).collect()
    if len(rows) > ENUMERATE_MAX:
        raise ValueError(f"over {ENUMERATE_MAX} categories")
    m, least = sum(r.pos + r.neg for r in rows), None
    for chosen in product((0, 1), repeat=len(rows)):
        loss = sum(min(sum(r.pos for r, c in zip(rows, chosen, strict=True) if c == side), sum(r.neg for r, c in zip(rows, chosen, strict=True) if c == side)) for side in (0, 1))
        least = loss if least is None else min(least, loss)
    return df.sparkSession.createDataFrame([(round((least or 0) / max(1, m), digits), 2 ** len(rows))], "loss double, groupings long")


def rate(m: int, n_categories: int, eps: float, c: float = 9.0, kind: str = "printed") -> float:
    """C N / (m eps) as printed; ``eps2`` divides by the square of eps."""
    return min(1.0, c * n_categories / (m * (eps if kind == "printed" else eps**2)))


def additive_split(df: DataFrame, cat: str, y: str, keys: Sequence[str | Column], eps: float, n_categories: int, m: int, c: float = 9.0, rate_kind: str = "printed", seed: int = 0, kind: str = "xxhash64") -> DataFrame:
    """The best grouping of a sample; categories that were not sampled are missing and go to side A."""
    p = rate(m, n_categories, eps, c, rate_kind)
    return sides(counts(bernoulli(df, keys, p, seed, kind), cat, y))


def loss_on(df: DataFrame, split: DataFrame, cat: str, y: str, digits: int = 6) -> DataFrame:
    """The loss over all rows of a grouping that was found on a sample."""
    true = counts(df, cat, y).join(split.select("category", "side"), "category", "left")
    return loss_of(true.withColumn("side", F.coalesce("side", F.lit("A"))), digits)


def disjointness_stream(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """(category, y): +1 for every element of a, -1 for every element of b."""
    one = lambda df, y: df.select(F.col(key).alias("category")).distinct().withColumn("y", F.lit(y))
    return one(a, 1).unionByName(one(b, -1))


def is_separable(stream: DataFrame) -> DataFrame:
    """One row: whether some grouping has no error, which is whether the two sets are disjoint, and the least loss."""
    by = counts(stream, "category", "y")
    return by.agg((F.coalesce(F.sum(F.least("pos", "neg")), F.lit(0)) == 0).alias("separable"), F.count_if((F.col("pos") > 0) & (F.col("neg") > 0)).alias("shared"), F.round(F.sum(F.least("pos", "neg")) / F.sum(F.col("pos") + F.col("neg")), 6).alias("loss"))
