"""Losses of a given list of splits: the evaluator that all approximate searches share.

``bsearch``: each row falls into one interval between splits, found by binary search inside the
JVM; sums per interval are a partial and a final aggregate over at most k + 1 groups, and the
driver adds up these few in whole numbers. ``arrow``: the same by numpy, which emits one partial row
per interval and batch, and a prefix scan; for large k. ``merge``: splits join the histogram as rows
without observations and one prefix scan gives all; the splits may be a table of any size.
``naive``: every row updates every split. ``two_pass``: means first, then squared deviations, from
the definition.
"""

from __future__ import annotations

from collections.abc import Sequence
from itertools import accumulate

import pyarrow as pa
from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..functions import losses as L
from . import histogram as H
from .curves import curve_of, with_losses
from .held import hold
from .prefix import scan
from .workers import importable

#: Splits up to which each physical form is taken.
BSEARCH_MAX, ARROW_MAX = 20_000, 1_000_000
METHODS = ("bsearch", "arrow", "merge", "naive", "two_pass")


def method_for(k: int) -> str:
    return "bsearch" if k <= BSEARCH_MAX else "arrow" if k <= ARROW_MAX else "merge"


def parts_of(obs: DataFrame, criterion: str) -> DataFrame:
    """(x, parts): what each row adds to the sums. Nothing is aggregated yet."""
    return obs.select("x", *[c.alias(name) for name, c in H.part_columns(criterion, F.col("y")).items()])


def compact(obs: DataFrame, criterion: str, rows: int) -> DataFrame:
    """For searches that pass again: held observations, or held sums by value where values are far fewer than rows."""
    distinct = obs.agg(F.approx_count_distinct("x")).first()[0]
    if 4 * distinct <= rows:
        return hold(obs.groupBy("x").agg(*H.part_sums(criterion, F.col("y"))))
    return parts_of(hold(obs.select("x", "y")), criterion)


def interval_sums(parts: DataFrame, splits: Sequence[int], criterion: str, method: str = "bsearch") -> DataFrame:
    """Summed parts by ``t``, the number of splits below x."""
    names = H.part_names(criterion)
    if method == "bsearch":
        return with_interval(parts, splits).groupBy("t").agg(*[F.sum(c).alias(c) for c in names])
    return _arrow_sums(parts, splits, names)


def with_interval(rows: DataFrame, splits: Sequence[int]) -> DataFrame:
    """Adds ``t``, the number of splits below x: in the JVM for few splits, by numpy for many."""
    if len(splits) <= BSEARCH_MAX:
        edges = [float("-inf"), *[float(j + 1) for j in splits], float("inf")]
        binned = Bucketizer(splits=edges, inputCol="_xd", outputCol="_td").transform(rows.withColumn("_xd", F.col("x").cast("double")))
        return binned.withColumn("t", F.col("_td").cast("long")).drop("_xd", "_td")
    import numpy as np

    importable(rows.sparkSession)
    held = rows.sparkSession.sparkContext.broadcast(np.array(splits, np.int64))

    def run(batches):
        for batch in batches:
            t = np.searchsorted(held.value, batch.column("x").to_numpy(zero_copy_only=False), "left")
            yield batch.append_column("t", pa.array(t, pa.int64()))

    return rows.mapInArrow(run, StructType([*rows.schema.fields, StructField("t", LongType())]))


def _arrow_sums(parts: DataFrame, splits: Sequence[int], names: Sequence[str]) -> DataFrame:
    import numpy as np

    importable(parts.sparkSession)
    held = parts.sparkSession.sparkContext.broadcast(np.array(splits, np.int64))

    def run(batches):
        for batch in batches:
            t = np.searchsorted(held.value, batch.column("x").to_numpy(zero_copy_only=False), "left")
            ids, at = np.unique(t, return_inverse=True)
            own = [_exact_sums(at, batch.column(c).to_numpy(zero_copy_only=False), len(ids)) for c in names]
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in (ids, *own)], names=["t", *names])

    partial = parts.mapInArrow(run, "t long, " + ", ".join(f"{c} long" for c in names))
    return partial.groupBy("t").agg(*[F.sum(c).alias(c) for c in names])


def _exact_sums(at, values, n: int):
    """Whole sums by group: halves of 31 bits add up exactly as floats in any batch of under 2**22 rows."""
    import numpy as np

    high, low = values >> 31, values & 0x7FFFFFFF
    return (np.bincount(at, weights=high, minlength=n).astype(np.int64) << 31) + np.bincount(at, weights=low, minlength=n).astype(np.int64)


def side_error(criterion: str, *sums: int) -> float:
    """The same arithmetic as the column expressions."""
    if criterion == "mse":
        n, s, q = sums
        return max(float(q) - float(s) * float(s) / float(n), 0.0) if n else 0.0
    pos, neg = sums
    n = float(pos + neg)
    if criterion == "misclassification":
        return float(min(pos, neg))
    return n - (float(pos) * pos + float(neg) * neg) / n if n else 0.0


def sides(parts: DataFrame, splits: Sequence[int], criterion: str, method: str = "bsearch") -> list[tuple]:
    """(j, left sums, right sums) on the driver: k + 1 rows are collected."""
    return prefix_sides({r[0]: tuple(r[1:]) for r in interval_sums(parts, splits, criterion, method).collect()}, splits, criterion)


def prefix_sides(by_t: dict[int, tuple], splits: Sequence[int], criterion: str) -> list[tuple]:
    """The same from the summed parts of each interval."""
    width = len(H.part_names(criterion))
    upto = list(accumulate((by_t.get(t, (0,) * width) for t in range(len(splits) + 1)), lambda a, b: tuple(x + y for x, y in zip(a, b, strict=True))))
    every = H.whole_sums(criterion, upto[-1])
    out = []
    for j, row in zip(splits, upto, strict=False):
        left = H.whole_sums(criterion, row)
        out.append((j, left, tuple(a - b for a, b in zip(every, left, strict=True))))
    return out


def errors(parts: DataFrame, splits: Sequence[int], criterion: str) -> dict[int, tuple[float, float]]:
    """Both sides' errors of each split, for searches that the driver steers."""
    splits = sorted(set(splits))
    return {j: (side_error(criterion, *a), side_error(criterion, *b)) for j, a, b in sides(parts, splits, criterion, "bsearch" if len(splits) <= BSEARCH_MAX else "arrow")}


def losses(obs: DataFrame, splits: Sequence[int] | DataFrame, criterion: str = "mse", scale: int = 1, method: str | None = None) -> DataFrame:
    """The curve (as ``curves.curve_of`` gives it) at the given splits: a list, or a frame with a column ``x``."""
    if isinstance(splits, DataFrame):
        return _merged(obs, splits.select("x"), criterion, scale)
    splits = sorted(set(splits))
    method = method or method_for(len(splits))
    if method not in METHODS:
        raise ValueError(f"no such method: {method}")
    if method == "merge":
        return _merged(obs, _frame(obs, splits), criterion, scale)
    if method == "naive":
        return _naive(obs, splits, criterion, scale)
    if method == "two_pass":
        return two_pass(obs, splits, scale)
    cols = L.sum_columns(criterion)
    if method == "bsearch":
        return local_curve(obs.sparkSession, sides(parts_of(obs, criterion), splits, criterion), criterion, scale)
    by_t = interval_sums(parts_of(obs, criterion), splits, criterion, method)
    slots = obs.sparkSession.createDataFrame(pa.table({"t": pa.array(range(len(splits) + 1), pa.int64()), "x": pa.array([*splits, None], pa.int64())}))
    filled = slots.join(by_t, "t", "left").select("t", "x", *[F.coalesce(c, F.lit(0)).alias(c) for c in H.part_names(criterion)]).select("t", "x", *H.joined(criterion))
    filled = hold(filled)
    every = filled.agg(*[F.sum(c) for c in cols]).first()
    upto = scan(filled, "t", cols).where("x is not null")
    right = [H.whole(v, "decimal(38,0)" if c in ("s", "q") else "long") - F.col(f"{c}_upto") for v, c in zip(every, cols, strict=True)]
    return with_losses(upto, [F.col(f"{c}_upto") for c in cols], right, criterion, scale, ["x"])


def local_curve(spark: SparkSession, rows: Sequence[tuple], criterion: str, scale: int) -> DataFrame:
    """The curve from (j, left sums, right sums) of the driver; whole numbers travel as text, which has no limit."""
    cols = L.sum_columns(criterion)
    kind = {c: "long" if c in ("n", "pos", "neg") else "decimal(38,0)" for c in cols}
    names = ["x", *[f"{c}_l" for c in cols], *[f"{c}_r" for c in cols]]
    flat = [[str(v) for v in col] for col in zip(*((j, *a, *b) for j, a, b in rows), strict=True)]
    texts = spark.createDataFrame(pa.table(dict(zip(names, flat or [[] for _ in names], strict=True)), schema=pa.schema([(c, pa.string()) for c in names])))
    local = texts.select(F.col("x").cast("long").alias("x"), *[F.col(f"{c}_{k}").cast(kind[c]).alias(f"{c}_{k}") for k in "lr" for c in cols])
    return with_losses(local, [F.col(f"{c}_l") for c in cols], [F.col(f"{c}_r") for c in cols], criterion, scale, ["x"])


def _frame(obs: DataFrame, splits: Sequence[int]) -> DataFrame:
    return obs.sparkSession.createDataFrame(pa.table({"x": pa.array(splits, pa.int64())}))


def _merged(obs: DataFrame, splits: DataFrame, criterion: str, scale: int) -> DataFrame:
    """Splits as tagged rows without observations: no list of them leaves the executors."""
    names = H.part_names(criterion)
    rows = parts_of(obs, criterion).withColumn("_asked", F.lit(0)).unionByName(splits.select("x", *[F.lit(0).cast("long").alias(c) for c in names], F.lit(1).alias("_asked")))
    summed = rows.groupBy("x").agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in names], F.max("_asked").alias("_asked"))
    hist = hold(summed.select("x", *H.joined(criterion), "_asked"))
    # Values that were not asked for leave their sums behind, then go.
    return curve_of(hist, criterion, scale).join(hist.where("_asked = 1").select("x"), "x", "left_semi")


def _naive(obs: DataFrame, splits: Sequence[int], criterion: str, scale: int) -> DataFrame:
    """Every row meets every split at or above it: the quadratic baseline. The right side is what all rows have beyond the left."""
    names, cols = H.part_names(criterion), L.sum_columns(criterion)
    parts = parts_of(obs, criterion)
    whole = H.whole_sums(criterion, parts.agg(*[F.coalesce(F.sum(c), F.lit(0)) for c in names]).first())
    # The list is the caller's; the method is for few splits.
    listed = F.broadcast(_frame(obs, splits).withColumnRenamed("x", "j"))
    met = parts.join(listed, F.col("x") <= F.col("j")).groupBy("j").agg(*[F.sum(c).alias(c) for c in names])
    left = _frame(obs, splits).withColumnRenamed("x", "j").join(met, "j", "left").select("j", *[F.coalesce(c, F.lit(0)).alias(c) for c in names])
    summed = left.select(F.col("j").alias("x"), *H.joined(criterion))
    right = [H.whole(v, "decimal(38,0)" if c in ("s", "q") else "long") - F.col(c) for v, c in zip(whole, cols, strict=True)]
    return with_losses(summed, [F.col(c) for c in cols], right, criterion, scale, ["x"])


def two_pass(obs: DataFrame, splits: Sequence[int], scale: int = 1) -> DataFrame:
    """Squared errors by their definition: a pass for the means, another for the deviations."""
    listed = F.broadcast(_frame(obs, sorted(set(splits))).select(F.col("x").alias("j")))
    y = F.col("y").cast("double") / scale
    met = obs.select("x", y.alias("y")).crossJoin(listed)
    is_left = F.col("x") <= F.col("j")
    means = met.groupBy("j").agg(F.avg(F.when(is_left, F.col("y"))).alias("pred_left"), F.avg(F.when(~is_left, F.col("y"))).alias("pred_right"), F.count_if(is_left).alias("n_left"), F.count_if(~is_left).alias("n_right"))
    # A row for each split of the caller's list.
    off = met.join(F.broadcast(means), "j")
    square = lambda c: (F.col("y") - F.col(c)) * (F.col("y") - F.col(c))
    errors_ = off.groupBy("j", "n_left", "n_right", "pred_left", "pred_right").agg(F.coalesce(F.sum(F.when(is_left, square("pred_left"))), F.lit(0.0)).alias("err_left"), F.coalesce(F.sum(F.when(~is_left, square("pred_right"))), F.lit(0.0)).alias("err_right"))
    return errors_.select(F.col("j").alias("x"), "n_left", "n_right", "err_left", "err_right", "pred_left", "pred_right", ((F.col("err_left") + F.col("err_right")) / (F.col("n_left") + F.col("n_right"))).alias("loss"))


def from_sample(sample: DataFrame, n_domain: int, limit: int = 5_000_000) -> list[int]:
    """Sampled values and their predecessors, with the sentinels 0 and N: the candidates of the additive search."""
    values = sample.select("x").distinct().limit(limit + 1).toArrow().column("x").to_pylist()
    if len(values) > limit:
        raise ValueError(f"over {limit} candidates; take a larger eps, or from_sample_table")
    return sorted({v for x in values for v in (x, x - 1) if 0 <= v <= n_domain} | {0, n_domain})


def from_sample_table(sample: DataFrame, n_domain: int) -> DataFrame:
    """The same as a frame, for samples that should not visit the driver."""
    both = sample.select(F.explode(F.array(F.col("x"), F.col("x") - 1)).alias("x")).where(F.col("x").between(0, n_domain))
    ends = sample.sparkSession.range(2).select(F.when(F.col("id") == 0, 0).otherwise(F.lit(n_domain)).cast("long").alias("x"))
    return both.unionByName(ends).distinct()
