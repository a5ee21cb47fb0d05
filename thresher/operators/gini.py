"""Approximate optimal splits for the Gini impurity from samples of fixed size."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import classification
from .domain import Domain, resolve
from .held import hold
from .prefix import scan
from .sampling import bottom_k
from .workers import importable

SIDES, LABELS = ("left", "right"), (1, -1)
#: Rows of the two samples that the paired estimator broadcasts.
PAIRED_MAX = 2_000_000


def sample_size(n_domain: int, eps: float, c: float) -> int:
    return math.ceil(c * math.log(max(2, n_domain)) / eps**2)


def least_matches(n_domain: int, eps: float, k: float, threshold: str) -> int:
    """Matching samples below which a term is estimated as 0."""
    return math.ceil(k * math.log(max(2, n_domain)) / (eps**2 if threshold == "printed" else eps))


def reservoirs(obs: DataFrame, keys: Sequence[str], size: int, seed: int, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """Two independent uniform samples in random order, as (x, y) rows; never shortened: too small an eps raises."""
    if size > PAIRED_MAX:
        raise ValueError(f"the paired estimator would need {size} rows of each sample, over {PAIRED_MAX}; take a larger eps or estimator='plugin'")
    out = []
    for s in (seed, seed + 1):
        rows = bottom_k(obs, keys, size, s, kind).select("x", F.col("y").cast("long").alias("y"), "_h", *[k for k in keys if k != "x"]).toArrow()
        rows = rows.sort_by([("_h", "ascending"), *[(k, "ascending") for k in keys]])
        out.append(np.stack([rows.column("x").to_numpy(), rows.column("y").to_numpy()], 1).astype(np.int64))
    return out[0], out[1]


def estimate(s1: np.ndarray, s2: np.ndarray, j: int, label: int, side: str, least: int, threshold: str) -> float:
    """f(label, side)**2 / (m f(side)): the mean of products of an event inside the side and one of all rows."""
    inside = s2[:, 0] <= j if side == "left" else s2[:, 0] > j
    match = np.flatnonzero(inside)
    if len(match) < least or not len(match):
        return 0.0
    t = min(least if threshold == "printed" else len(match), len(s1))
    a = s2[match[:t], 1] == label
    x, y = s1[:t, 0], s1[:t, 1]
    b = (y == label) & (x <= j if side == "left" else x > j)
    return float(np.mean(a[: len(b)] & b[: len(a)]))


def paired_terms(obs: DataFrame, keys: Sequence[str], eps: float, domain: Domain | None = None, c: float = 3.0, k: float = 1.0, threshold: str = "repaired", seed: int = 0, kind: str = "xxhash64") -> DataFrame:
    """(j, label, side, est) for every sampled value: the four terms of 1 - loss.

    The samples are broadcast, their size follows eps alone; the sampled values are dealt to tasks.
    """
    domain = domain or resolve(obs)
    spark = obs.sparkSession
    importable(spark)
    s1, s2 = reservoirs(obs, keys, sample_size(domain.n, eps, c), seed, kind)
    least = least_matches(domain.n, eps, k, threshold)
    held = spark.sparkContext.broadcast((s1, s2))
    schema = pa.schema([("j", pa.int64()), ("label", pa.int32()), ("side", pa.string()), ("est", pa.float64())])

    def run(batches):
        for batch in batches:
            rows = [(j, label, side, estimate(*held.value, j, label, side, least, threshold)) for j in batch.column("j").to_pylist() for label in LABELS for side in SIDES]
            yield pa.RecordBatch.from_arrays([pa.array(col, f.type) for col, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema) if rows else pa.RecordBatch.from_pylist([], schema=schema)

    values = spark.createDataFrame(pa.table({"j": pa.array(np.unique(np.concatenate([s1[:, 0], s2[:, 0]])), pa.int64())}))
    tasks = max(1, min(1024, len(s1) // 256))
    return values.repartition(tasks, "j").mapInArrow(run, "j long, label int, side string, est double")


def estimate_term(obs: DataFrame, keys: Sequence[str], label: int, side: str, **options) -> DataFrame:
    return paired_terms(obs, keys, **options).where((F.col("label") == label) & (F.col("side") == side)).select("j", "est")


def additive_split(obs: DataFrame, keys: Sequence[str], eps: float, domain: Domain | None = None, c: float = 3.0, k: float = 1.0, estimator: str = "paired", threshold: str = "repaired", seed: int = 0, kind: str = "xxhash64", digits: int = 6) -> DataFrame:
    """(j, loss): the sampled value of least estimated impurity, within O(eps) of the optimum.

    ``paired``: products of two independent samples; ``plugin``: sampled counts in the impurity's formula, for
    samples of any size.
    """
    domain = domain or resolve(obs)
    if estimator == "plugin":
        size = sample_size(domain.n, eps, c)
        return classification.additive_split(bottom_k(obs, keys, size, seed, kind), keys, 1.0, Domain(size, domain.n, -1, 1), c=float("inf"), digits=digits, criterion="gini").select("j", "loss")
    terms = paired_terms(obs, keys, eps, domain, c, k, threshold, seed, kind)
    return terms.groupBy("j").agg(F.round(1 - F.sum("est"), digits).alias("loss")).orderBy("loss", "j").limit(1)


def coverage(sample: DataFrame, n_domain: int, eps: float, k: float = 1.0, threshold: str = "repaired") -> DataFrame:
    """(x, left, right, enough_left, enough_right): sampled rows on each side of every sampled value."""
    least = least_matches(n_domain, eps, k, threshold)
    hist = hold(sample.groupBy("x").agg(F.count("*").alias("n")))
    total = hist.agg(F.sum("n")).first()[0] or 0
    left, right = F.col("n_upto"), F.lit(total) - F.col("n_upto")
    return scan(hist, "x", ["n"]).select("x", left.alias("left"), right.alias("right"), (left >= least).alias("enough_left"), (right >= least).alias("enough_right"))
