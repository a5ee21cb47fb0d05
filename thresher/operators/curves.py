"""Loss curves and exact best splits."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import losses
from .held import hold
from .histogram import histogram, whole
from .prefix import scan

#: Totals below this are scanned as longs: squares bound the sums of labels.
LONG_LIMIT = 1 << 62


def curve_of(hist: DataFrame, criterion: str = "mse", scale: int = 1, by: Sequence[str] = (), x: str = "x") -> DataFrame:
    """(by, x, n_left, n_right, err_left, err_right, loss, pred_left, pred_right) at every x of a histogram.

    Errors are in units of the label as it was before it was multiplied by ``scale``. One scan gives both sides:
    the right one is the total less the left one.
    """
    cols = losses.sum_columns(criterion)
    if by:
        upto = scan(hist, x, cols, by)
        upto = upto.join(hist.groupBy(*by).agg(*[F.sum(c).alias(f"{c}_all") for c in cols]), list(by))
    else:
        row = [int(v or 0) for v in hist.agg(*[F.sum(c) for c in cols]).first()]
        kind = "long" if max(map(abs, row)) < LONG_LIMIT else "decimal(38,0)"
        upto = scan(hist.select(*[F.col(c).cast(kind).alias(c) if c in cols else F.col(c) for c in hist.columns]), x, cols)
        upto = upto.withColumns({f"{c}_all": whole(v, kind) for c, v in zip(cols, row, strict=True)})
    left = [F.col(f"{c}_upto") for c in cols]
    right = [F.col(f"{c}_all") - F.col(f"{c}_upto") for c in cols]
    return with_losses(upto, left, right, criterion, scale, [*by, x])


def with_losses(df: DataFrame, left: list, right: list, criterion: str, scale: int, keep: Sequence[str]) -> DataFrame:
    unit = float(scale * scale) if criterion == "mse" else 1.0
    n_left, n_right = losses.side_rows(criterion, *left), losses.side_rows(criterion, *right)
    sides = df.select(
        *keep,
        n_left.cast("long").alias("n_left"),
        n_right.cast("long").alias("n_right"),
        (losses.side_error(criterion, *left) / unit).alias("err_left"),
        (losses.side_error(criterion, *right) / unit).alias("err_right"),
        losses.prediction(criterion, scale, *left).alias("pred_left"),
        losses.prediction(criterion, scale, *right).alias("pred_right"),
    )
    return sides.withColumn("loss", (F.col("err_left") + F.col("err_right")) / (F.col("n_left") + F.col("n_right")))


def loss_curve(obs: DataFrame, criterion: str = "mse", scale: int = 1) -> DataFrame:
    """The loss of the split at every distinct x."""
    return curve_of(hold(histogram(obs, criterion)), criterion, scale)


def best(curve: DataFrame, digits: int = losses.DIGITS, x: str = "x") -> DataFrame:
    """The split of least loss, the smallest x on ties after rounding."""
    chosen = curve.withColumn("loss", F.round("loss", digits)).orderBy("loss", x).limit(1)
    return chosen.select(F.col(x).alias("j"), "loss", F.round("pred_left", digits).alias("pred_left"), F.round("pred_right", digits).alias("pred_right"), "n_left", "n_right")


def exact_split(obs: DataFrame, criterion: str = "mse", scale: int = 1, digits: int = losses.DIGITS) -> DataFrame:
    """The optimal split: one pass over the observations, then work in the number of distinct x."""
    return best(loss_curve(obs, criterion, scale), digits)
