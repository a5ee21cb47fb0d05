"""Which search a table should get, and how."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import guesses
from ..operators.domain import Domain

#: Distinct values up to which the exact search is taken: it shuffles a row for each.
EXACT_MAX = 50_000_000


@dataclass(frozen=True)
class Choice:
    method: str
    distinct: int
    passes: int
    reason: str


def choose(obs: DataFrame, domain: Domain, eps: float | None = None, relative: bool = False, beta: float = 0.5) -> Choice:
    """Exact while the distinct values are few; else additive, or multiplicative where the error must be relative."""
    distinct = obs.agg(F.approx_count_distinct("x")).first()[0]
    if eps is None or distinct <= EXACT_MAX:
        return Choice("exact", distinct, 1, f"about {distinct} distinct values")
    if not relative:
        return Choice("additive", distinct, 2, f"an additive error of {eps} was asked for")
    levels = guesses.levels_for(domain.n, beta)
    return Choice("frontier", distinct, -(-(domain.n.bit_length() + 1) // levels), f"a relative error of {eps} was asked for")
