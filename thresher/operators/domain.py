"""Sizes that the searches need: rows, the domain and the label range."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Domain:
    m: int
    n: int
    low: int
    high: int

    @property
    def spread(self) -> int:
        """The largest difference of labels, in fixed-point units."""
        return self.high - self.low


def resolve(obs: DataFrame) -> Domain:
    """One aggregate over the pruned columns."""
    m, n, low, high = obs.agg(F.count("*"), F.max("x"), F.min("y"), F.max("y")).first()
    return Domain(m, int(n or 0), int(low or 0), int(high or 0))
