"""Samples that depend on row keys and a seed only: not on partitions, retries or row order."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A prime modulus, a multiplier of full period, and weights of the key columns.
MODULUS, MULTIPLIER = 2147483647, 48271
WEIGHTS = (7919, 104729, 1299709, 15485863, 32452843)


def lcg(keys: Sequence[str | Column], seed: int) -> Column:
    """A hash in [0, MODULUS) of non-negative integers, in integer steps that any SQL engine can repeat."""
    at: Column = F.lit(seed % MODULUS).cast("long")
    for key, weight in zip(keys, WEIGHTS, strict=False):
        col = F.col(key) if isinstance(key, str) else key
        at = ((at + col.cast("long") % MODULUS * weight) % MODULUS * MULTIPLIER + 11) % MODULUS
    return (at * MULTIPLIER + 12345) % MODULUS


def lcg_sql(keys: Sequence[str], seed: int) -> str:
    """The same as SQL."""
    at = f"CAST({seed % MODULUS} AS BIGINT)"
    for key, weight in zip(keys, WEIGHTS, strict=False):
        at = f"((({at} + CAST({key} AS BIGINT) % {MODULUS} * {weight}) % {MODULUS}) * {MULTIPLIER} + 11) % {MODULUS}"
    return f"(({at}) * {MULTIPLIER} + 12345) % {MODULUS}"


def _hash(keys: Sequence[str | Column], seed: int, kind: str) -> tuple[Column, int]:
    if kind == "lcg":
        return lcg(keys, seed), MODULUS
    return F.shiftrightunsigned(F.xxhash64(*keys, F.lit(seed)), 11), 1 << 53


def bernoulli(df: DataFrame, keys: Sequence[str | Column], p: float, seed: int = 0, kind: str = "xxhash64") -> DataFrame:
    """Every row on its own with probability p: a filter, nothing is shuffled."""
    return df if p >= 1 else df.where(kept(keys, p, seed, kind))


def kept(keys: Sequence[str | Column], p: float, seed: int = 0, kind: str = "xxhash64") -> Column:
    """Whether a row is in the sample."""
    h, size = _hash(keys, seed, kind)
    return F.lit(True) if p >= 1 else h < math.floor(p * size)


def bottom_k(df: DataFrame, keys: Sequence[str], k: int, seed: int = 0, kind: str = "xxhash64") -> DataFrame:
    """A uniform sample of k rows in random order, with that order's key as ``_h``: a mergeable reservoir."""
    h, _ = _hash(keys, seed, kind)
    return df.withColumn("_h", h).orderBy("_h", *keys).limit(k)


def adaptive(df: DataFrame, keys: Sequence[str], cap: int, seed: int = 0, kind: str = "xxhash64") -> tuple[DataFrame, float]:
    """For an unknown number of rows: the largest halving of the rate whose sample has at most ``cap`` rows.

    Samples of one seed nest, so a streaming sample that grows over the cap is cut down to the next one.
    """
    h, size = _hash(keys, seed, kind)
    level = F.least(F.floor(F.log2(F.lit(float(size)) / F.greatest(h.cast("double"), F.lit(1.0)))), F.lit(62))
    counts = {int(r.level): r.n for r in df.groupBy(level.cast("int").alias("level")).agg(F.count("*").alias("n")).collect()}
    halvings = 0
    while sum(n for lv, n in counts.items() if lv >= halvings) > cap and halvings < 62:
        halvings += 1
    p = 0.5**halvings
    return df.where(level >= halvings), p


def rate(m: int, n_domain: int, eps: float, c: float = 9.0, power: int = 1) -> float:
    """C log N / (m eps**power), at most 1."""
    return min(1.0, c * math.log(max(2, n_domain)) / (max(1, m) * eps**power))


def range_count(obs: DataFrame, keys: Sequence[str], ranges: Sequence[tuple[int, int]], alpha: float, n_domain: int, m: int, c: float = 9.0, seed: int = 0, kind: str = "xxhash64") -> DataFrame:
    """(lo, hi, sampled, estimate, heavy, light) for ranges [lo, hi] by a sample of rate C log N / m**alpha.

    An estimate of at least 2 m**alpha calls a range heavy, one of at most m**alpha light.
    """
    p = min(1.0, c * math.log(max(2, n_domain)) / m**alpha)
    sample = bernoulli(obs, keys, p, seed, kind).select("x")
    spark = obs.sparkSession
    asked = spark.createDataFrame([(int(a), int(b)) for a, b in ranges], "lo long, hi long")
    # The ranges are a list of the caller's.
    hits = sample.join(F.broadcast(asked), F.col("x").between(F.col("lo"), F.col("hi"))).groupBy("lo", "hi").agg(F.count("*").alias("sampled"))
    got = asked.join(hits, ["lo", "hi"], "left").select("lo", "hi", F.coalesce("sampled", F.lit(0)).alias("sampled"))
    estimate = F.col("sampled") / F.lit(p)
    return got.select("*", F.round(estimate, 4).alias("estimate"), (estimate >= 2 * m**alpha).alias("heavy"), (estimate <= m**alpha).alias("light"))
