"""Approximate optimal splits for squared error. Labels are fixed-point longs: value times ``scale``."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import candidates, guesses
from .curves import best
from .domain import Domain, resolve
from .ledger import Ledger
from .sampling import bernoulli, rate

C = 9.0


def additive_split(obs: DataFrame, keys: Sequence[str | Column], eps: float, domain: Domain | None = None, scale: int = 1, c: float = C, seed: int = 0, kind: str = "xxhash64", method: str | None = None, ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """Two passes: sample candidates at rate C log N / (m eps), then their losses.

    With high probability the loss is at most the optimum plus 5/8 eps times the squared label range.
    """
    domain = domain or resolve(obs)
    ledger = ledger or Ledger()
    p = rate(domain.m, domain.n, eps, c)
    sample = bernoulli(obs, keys, p, seed, kind)
    if 2 * p * domain.m > candidates.ARROW_MAX and method in (None, "merge"):
        splits: list[int] | DataFrame = candidates.from_sample_table(sample, domain.n)
        k = round(2 * p * domain.m)
    else:
        with ledger.one_pass(domain.m):
            splits = candidates.from_sample(sample, domain.n)
        k = len(splits)
    ledger.sampled(k // 2)
    ledger.scanned(k)
    with ledger.one_pass(domain.m):
        curve = candidates.losses(obs, splits, "mse", scale, method)
    ledger.scanned(k + 1, k)
    # The split at 0 leaves all rows on the right, which is the split at N.
    return best(curve.where("x > 0"), digits)


def errors_at(parts: DataFrame, criterion: str, ledger: Ledger, rows: int = 0) -> guesses.Evaluate:
    """A pass over the observations (or their sums by value) that evaluates a list of splits."""

    def evaluate(probes: list[int]) -> guesses.Errors:
        with ledger.one_pass(rows):
            found_ = candidates.errors(parts, probes, criterion)
        ledger.scanned(len(probes) + 1, len(probes))
        return found_

    return evaluate


def error_grid(domain: Domain, eps: float, kind: str = "scaled") -> list[float]:
    """Guesses for squared errors of fixed-point labels, in units of squared label steps.

    A squared error of whole numbers that is not 0 is 1/2 at least, which is where ``scaled`` begins.
    """
    high = max(1.0, float(domain.m) * domain.spread**2)
    return guesses.printed(high, eps) if kind == "printed" else guesses.geometric(0.5, high, eps)


def multiplicative_split(obs: DataFrame, eps: float, domain: Domain | None = None, scale: int = 1, mode: str = "batched", beta: float = 0.5, grid: str | list[float] = "scaled", ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """A split whose loss is at most 1 + eps times the optimum, in O(log N) or O(1/beta) passes.

    ``sequential``: one level of bisection for each pass; ``batched``: beta log N levels; ``frontier``: as
    batched, with a search for each grid value in place of one for each pair.
    """
    domain = domain or resolve(obs)
    ledger = ledger or Ledger()
    values = error_grid(domain, eps, grid) if isinstance(grid, str) else grid
    return found(obs, search_split(obs, values, domain, "mse", mode, beta, ledger), "mse", scale, digits)


def search_split(obs: DataFrame, values: list[float], domain: Domain, criterion: str, mode: str, beta: float, ledger: Ledger) -> int:
    evaluate = errors_at(candidates.compact(obs, criterion, domain.m), criterion, ledger, domain.m)
    levels = 1 if mode == "sequential" else guesses.levels_for(domain.n, beta)
    run = guesses.frontier if mode == "frontier" else guesses.search
    return run(values, domain.n, evaluate, levels, ledger.guessing)[0]


def found(obs: DataFrame, j: int, criterion: str, scale: int, digits: int) -> DataFrame:
    """The split's true loss and predictions."""
    return best(candidates.losses(obs, [j], criterion, scale), digits)


def bound_row(result: DataFrame, optimum: DataFrame, allowed: Column) -> DataFrame:
    """One row: the optimum, and whether the result's loss is within ``allowed`` (of ``opt``)."""
    pair = result.select(F.col("loss").alias("got"), F.lit(1).alias("k")).join(optimum.select(F.col("loss").alias("opt"), F.lit(1).alias("k")), "k")
    return pair.select("opt", (F.col("got") <= allowed + 1e-6).alias("within_bound"))
