"""Approximate optimal splits for the misclassification rate; labels are +1 and -1."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import guesses
from .curves import best, loss_curve
from .domain import Domain, resolve
from .ledger import Ledger
from .regression import found, search_split
from .sampling import bernoulli, rate


def additive_split(obs: DataFrame, keys: Sequence[str | Column], eps: float, domain: Domain | None = None, c: float = 9.0, rate_kind: str = "eps2", seed: int = 0, kind: str = "xxhash64", digits: int = 6, criterion: str = "misclassification", ledger: Ledger | None = None) -> DataFrame:
    """One pass: the best sampled value by estimated loss; counts are estimated as sampled counts / p.

    ``printed`` samples at C log N / (eps m); ``eps2`` at C log N / (eps**2 m), the rate for which
    uniform deviation bounds hold whatever the optimum is. The loss that comes back is the estimate.
    """
    domain = domain or resolve(obs)
    p = rate(domain.m, domain.n, eps, c, 1 if rate_kind == "printed" else 2)
    sample = bernoulli(obs, keys, p, seed, kind).select("x", "y")
    # Losses are shares of rows, so dividing both counts by p leaves them as they are up to m.
    curve = loss_curve(sample, criterion)
    if criterion == "misclassification":
        curve = curve.withColumn("loss", (F.col("err_left") + F.col("err_right")) / F.lit(p) / F.lit(float(domain.m)))
    if ledger:
        ledger.sampled(round(p * domain.m))
        ledger.scanned(round(p * domain.m))
    out = best(curve, digits)
    return out.select("j", "loss", "pred_left", "pred_right", F.round(F.col("n_left") / F.lit(p)).cast("long").alias("n_left"), F.round(F.col("n_right") / F.lit(p)).cast("long").alias("n_right"))


def multiplicative_split(obs: DataFrame, eps: float, domain: Domain | None = None, mode: str = "batched", beta: float = 0.5, grid: str | list[float] = "scaled", ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """A split whose error is at most 1 + eps times the optimum; counts are guessed up to the number of rows."""
    domain = domain or resolve(obs)
    ledger = ledger or Ledger()
    if isinstance(grid, str):
        grid = guesses.printed(domain.m, eps) if grid == "printed" else guesses.geometric(1.0, max(1, domain.m), eps)
    return found(obs, search_split(obs, grid, domain, "misclassification", mode, beta, ledger), "misclassification", 1, digits)
