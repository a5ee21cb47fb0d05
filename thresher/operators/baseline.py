"""Baselines: sort everything, evaluate from the definition, or do not split."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import losses as L
from . import candidates
from . import histogram as H
from .curves import best
from .prefix import next_key, scan

#: Distinct values up to which the definition is evaluated at all of them.
BRUTE_MAX = 10_000


def offline(obs: DataFrame, criterion: str = "mse", scale: int = 1, digits: int = 6) -> DataFrame:
    """Keeps and sorts all rows and scans them one by one: state is the input, not the distinct values."""
    cols = L.sum_columns(criterion)
    rows = candidates.parts_of(obs, criterion).select("x", F.monotonically_increasing_id().alias("_row"), *H.joined(criterion))
    upto = scan(rows.withColumn("_at", F.struct("x", "_row")), "_at", cols)
    # Only the last row of a value is a split.
    last = upto.groupBy("x").agg(F.max_by(F.struct(*[f"{c}_upto" for c in cols]), "_row").alias("u"))
    total = H.whole_sums(criterion, obs.agg(*H.part_sums(criterion, F.col("y"))).first())
    left = [F.col(f"u.{c}_upto") for c in cols]
    right = [H.whole(v, "decimal(38,0)" if c in ("s", "q") else "long") - e for v, e, c in zip(total, left, cols, strict=True)]
    return best(candidates.with_losses(last, left, right, criterion, scale, ["x"]), digits)


def brute_force(obs: DataFrame, splits: Sequence[int] | None = None, criterion: str = "mse", scale: int = 1) -> DataFrame:
    """The curve from two filtered aggregates for each split; all distinct values by default (``BRUTE_MAX`` at most)."""
    if splits is None:
        splits = [r.x for r in obs.select("x").distinct().limit(BRUTE_MAX + 1).collect()]
        if len(splits) > BRUTE_MAX:
            raise ValueError(f"over {BRUTE_MAX} distinct values: the definition costs rows times values")
    return candidates.losses(obs, splits, criterion, scale, "naive")


def no_split(df: DataFrame, y: str, criterion: str = "mse", digits: int = 6) -> DataFrame:
    """One row: the loss of one leaf."""
    col = F.col(y)
    n = F.count(col).cast("double")
    pos = F.count_if(col > 0).cast("double")
    loss = {"mse": F.var_pop(col), "misclassification": F.least(pos, n - pos) / n, "gini": 1 - (pos * pos + (n - pos) * (n - pos)) / (n * n)}[criterion]
    return df.agg(F.round(loss, digits).alias("loss"), F.count(col).alias("n"))


def no_split_rollup(df: DataFrame, y: str, by: Sequence[str], scale: int = 1, digits: int = 6) -> DataFrame:
    """The squared error of one leaf for every prefix of ``by``: moment sums stay mergeable under rollup."""
    rolled = H.aggregate_over(df.rollup(*by), by, "mse", F.col(y))
    return rolled.select(*by, "n", F.round(L.sse(F.col("n"), F.col("s"), F.col("q")) / F.col("n") / float(scale * scale), digits).alias("loss"))


def value_gaps(obs: DataFrame, bins: int = 4) -> DataFrame:
    """(x, n, gap, bin): rows and gap to the next value of every distinct value, and equal-depth bins of the values.

    The shape of a domain before a search: neither the gaps nor the bins need a window over all values.
    """
    distinct = obs.groupBy("x").agg(F.count("*").alias("n"))
    spaced = next_key(distinct, "x", "_next").withColumn("one", F.lit(1).cast("long"))
    ranked = scan(spaced, "x", ["one"])
    d = distinct.count()
    small, larger = divmod(d, bins)
    # As ntile deals them: the first bins take one value more.
    at = F.col("one_upto") - 1
    bin_ = F.when(at < larger * (small + 1), F.floor(at / (small + 1))).otherwise(larger + F.floor((at - larger * (small + 1)) / max(1, small))) + 1
    return ranked.select("x", "n", (F.col("_next") - F.col("x")).alias("gap"), bin_.cast("int").alias("bin"))
