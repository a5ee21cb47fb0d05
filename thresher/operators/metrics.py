"""Measures of a found split against the optimum."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import candidates
from .curves import exact_split, loss_curve
from .domain import Domain, resolve
from .held import hold
from .histogram import histogram
from .prefix import next_key, scan
from .sampling import kept, rate


def loss(obs: DataFrame, j: int, criterion: str = "mse", scale: int = 1) -> float:
    return candidates.losses(obs, [j], criterion, scale).first()["loss"]


def excess(got: float, optimum: float) -> float:
    return got - optimum


def ratio(got: float, optimum: float) -> float:
    """1 where both are 0; infinite where only the optimum is."""
    return got / optimum if optimum > 0 else (1.0 if got <= 1e-12 else float("inf"))


def success_rate(runs: list[float], allowed: float) -> float:
    return sum(x <= allowed for x in runs) / max(1, len(runs))


def term_error(terms: DataFrame, obs: DataFrame) -> DataFrame:
    """One row: the largest difference of an estimated impurity term from its true value, over all splits.

    Splits are values that occur, so the true terms are read off the label histogram's prefix sums.
    """
    hist = hold(histogram(obs, "gini"))
    pos, neg = (int(v or 0) for v in hist.agg(F.sum("pos"), F.sum("neg")).first())
    upto = scan(hist, "x", ["pos", "neg"])
    left = {1: F.col("pos_upto"), -1: F.col("neg_upto")}
    every = {1: F.lit(pos), -1: F.lit(neg)}
    m = float(max(1, pos + neg))
    entries = []
    for label in (1, -1):
        for side in ("left", "right"):
            f = left[label] if side == "left" else every[label] - left[label]
            n = left[1] + left[-1] if side == "left" else F.lit(pos + neg) - left[1] - left[-1]
            value = F.when(n > 0, f.cast("double") * f / n / m).otherwise(0.0)
            entries.append(F.struct(F.lit(label).alias("label"), F.lit(side).alias("side"), value.alias("true")))
    true = upto.select(F.col("x").alias("j"), F.explode(F.array(*entries)).alias("t")).select("j", "t.*")
    return terms.join(true, ["j", "label", "side"], "left").agg(F.max(F.abs(F.col("est") - F.coalesce("true", F.lit(0.0)))).alias("worst"))


def success_over_seeds(obs: DataFrame, keys: Sequence[str], eps: float, seeds: Sequence[int], allowed: float, domain: Domain | None = None, c: float = 9.0, kind: str = "xxhash64") -> DataFrame:
    """(seed, excess, within): the additive search's excess for each seed, and whether it is within ``allowed``.

    The exact curve has the losses of all candidates, so all seeds share two passes: the sample of a seed is
    a filter, and its candidates are the sampled values and the values before them.
    """
    domain = domain or resolve(obs)
    p = rate(domain.m, domain.n, eps, c)
    curve = hold(loss_curve(obs))
    opt = curve.agg(F.min("loss")).first()[0]
    member = F.array_compact(F.array(*[F.when(kept(keys, p, seed, kind), F.lit(seed)) for seed in seeds]))
    sampled = obs.select("x", F.explode(member).alias("seed")).distinct()
    # The predecessor of a value leaves the value and all after it on the right: the split at the value before it.
    steps = next_key(curve.select("x", "loss"), "x", "after")
    before = steps.select(F.col("after").alias("x"), F.col("loss").alias("loss_before")).where("x is not null")
    at = sampled.join(curve.select("x", "loss"), "x").join(before, "x", "left")
    whole = curve.where("n_right = 0").select("loss").first()[0]
    least = at.groupBy("seed").agg(F.min(F.least("loss", F.coalesce("loss_before", F.lit(whole)))).alias("got"))
    return least.select("seed", F.round(F.col("got") - opt, 6).alias("excess"), (F.col("got") <= opt + allowed).alias("within"))


def compare(obs: DataFrame, found: DataFrame, criterion: str, scale: int = 1) -> dict[str, float]:
    """Excess and ratio of the true loss at the found split."""
    got, best = loss(obs, found.first()["j"], criterion, scale), exact_split(obs, criterion, scale, 12).first()["loss"]
    return {"loss": got, "opt": best, "excess": excess(got, best), "ratio": ratio(got, best)}
