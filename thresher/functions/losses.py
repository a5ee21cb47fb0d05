"""Errors of a side and losses of a split, as column expressions over mergeable sums.

Sums of squares stay whole numbers until the last step: labels are fixed-point longs (times
``scale``), sums decimals. A side without rows has error 0 and a null prediction.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

CRITERIA = ("mse", "misclassification", "gini", "entropy")
DIGITS = 6


def sse(n: Column, s: Column, q: Column) -> Column:
    """Squared error of a side around its mean, from its count, sum and sum of squares."""
    return F.when(n > 0, F.greatest(q.cast("double") - s.cast("double") * s.cast("double") / n.cast("double"), F.lit(0.0))).otherwise(0.0)


def minority(pos: Column, neg: Column) -> Column:
    return F.least(pos, neg).cast("double")


def gini(pos: Column, neg: Column) -> Column:
    """Rows of a side times its Gini impurity."""
    n = (pos + neg).cast("double")
    p, q = pos.cast("double"), neg.cast("double")
    return F.when(n > 0, n - (p * p + q * q) / n).otherwise(0.0)


def entropy(pos: Column, neg: Column) -> Column:
    """Rows of a side times its entropy in bits."""
    n = (pos + neg).cast("double")
    part = lambda c: F.when(c > 0, -c.cast("double") * F.log2(c.cast("double") / n)).otherwise(0.0)
    return part(pos) + part(neg)


def side_error(criterion: str, *sums: Column) -> Column:
    """mse: (n, s, q); the others: (pos, neg)."""
    return {"mse": sse, "misclassification": minority, "gini": gini, "entropy": entropy}[criterion](*sums)


def sum_columns(criterion: str) -> list[str]:
    return ["n", "s", "q"] if criterion == "mse" else ["pos", "neg"]


def side_rows(criterion: str, *sums: Column) -> Column:
    return sums[0] if criterion == "mse" else sums[0] + sums[1]


def prediction(criterion: str, scale: int, *sums: Column) -> Column:
    """The mean label, or the more frequent one (ties: +1)."""
    if criterion == "mse":
        return F.when(sums[0] > 0, sums[1].cast("double") / sums[0].cast("double") / scale)
    return F.when(sums[0] + sums[1] > 0, F.when(sums[0] >= sums[1], 1.0).otherwise(-1.0))
