"""The searches as few-round massively parallel computations, with what the model charges for.

``Cluster`` deals the rows to m**(1 - beta) logical machines and counts rounds, the words that the fullest
machine holds, and the messages and words that the centre receives. A machine is a group key, not a Spark
partition, so their number may be the square root of the rows. Sorting places a row by the rank of its
value, and rows of one value take turns in the places that it fills, so no machine has more than its share.
The centre is the driver for k + 1 sums, and a distributed aggregate for samples.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import candidates, classification, gini, guesses, regression
from . import histogram as H
from .curves import best
from .domain import Domain, resolve
from .held import hold
from .ledger import PAIR, TRIPLE, Ledger
from .prefix import scan
from .sampling import bernoulli, rate

Keys = Sequence[str | Column]
#: Rounds of a sort on machines that each hold a share: draw splitters, send them, exchange rows.
SORT_ROUNDS = 3


def machines(m: int, beta: float = 0.5) -> int:
    """m**(1 - beta) machines of about m**beta memory."""
    return max(1, round(m ** (1 - beta)))


class Cluster:
    """Rows on logical machines, before and after the sort, and the ledger of what they exchange."""

    def __init__(self, obs: DataFrame, keys: Keys, beta: float = 0.5, domain: Domain | None = None, ledger: Ledger | None = None):
        self.obs, self.keys, self.domain = obs, list(keys), domain or resolve(obs)
        self.count = machines(self.domain.m, beta)
        self.share = max(1, -(-self.domain.m // self.count))
        self.ledger = ledger or Ledger()
        self.ledger.machines = self.count
        self.sorted: DataFrame | None = None

    def local_sample(self, p: float, seed: int = 0, kind: str = "xxhash64") -> DataFrame:
        """One round: each machine samples the rows that it was given and sends them to the centre."""
        home = F.pmod(F.xxhash64(*self.keys, F.lit(3)), F.lit(self.count))
        sample = hold(bernoulli(self.obs, self.keys, p, seed, kind).select("x", "y", home.alias("_machine")))
        per = sample.groupBy("_machine").count().agg(F.max("count"), F.sum("count")).first()
        most, total = (int(v or 0) for v in per)
        self._held(PAIR * (self.share + most))
        self._received(total, PAIR * total)
        self.ledger.sampled(total)
        self.ledger.rounds += 1
        return sample.select("x", "y")

    def sort(self) -> DataFrame:
        """Rows by value over the machines in order."""
        if self.sorted is None:
            counts = hold(self.obs.groupBy("x").agg(F.count("*").alias("_n")))
            starts = scan(counts, "x", ["_n"]).select("x", "_n", (F.col("_n_upto") - F.col("_n")).alias("_start"))
            turn = F.pmod(F.xxhash64(*self.keys, F.lit(5)), F.col("_n"))
            placed = self.obs.join(starts, "x").withColumn("_machine", F.floor((F.col("_start") + turn) / self.share))
            self.sorted = hold(placed.select("x", "y", "_machine"))
            self._held(PAIR * int(self.sorted.groupBy("_machine").count().agg(F.max("count")).first()[0] or 0))
            self.ledger.rounds += SORT_ROUNDS
        return self.sorted

    def sides(self, splits: Sequence[int], criterion: str) -> list[tuple]:
        """(j, left sums, right sums): two rounds, splits to all machines and their partial sums to the centre.

        A machine sends a row for each interval that it has rows of. Rows are sorted, so an interval inside
        one machine is sent once and only the intervals at machine borders more often: k + 1 + 2 machines at most.
        """
        names = H.part_names(criterion)
        parts = self.sort().select("_machine", "x", *[c.alias(n) for n, c in H.part_columns(criterion, F.col("y")).items()])
        binned = candidates.with_interval(parts, splits)
        with self.ledger.one_pass(self.domain.m):
            partial = binned.groupBy("_machine", "t").agg(*[F.sum(c).alias(c) for c in names])
            rows = partial.groupBy("t").agg(*[F.sum(c).alias(c) for c in names], F.count("*").alias("_senders")).collect()
        sent = sum(r["_senders"] for r in rows)
        self._held(PAIR * self.share + len(splits))
        self._received(sent, (TRIPLE if criterion == "mse" else 2) * sent)
        self.ledger.scanned(len(splits) + 1, len(splits), rounds=2)
        return candidates.prefix_sides({r["t"]: tuple(r[c] for c in names) for r in rows}, splits, criterion)

    def errors(self, criterion: str) -> guesses.Evaluate:
        def evaluate(probes: list[int]) -> guesses.Errors:
            return {j: (candidates.side_error(criterion, *a), candidates.side_error(criterion, *b)) for j, a, b in self.sides(sorted(set(probes)), criterion)}

        return evaluate

    def result(self, rows: list[tuple], criterion: str, scale: int, digits: int) -> DataFrame:
        """The best of the centre's splits; only those that rounding could make the least become a frame."""
        unit = float(scale * scale) if criterion == "mse" else 1.0
        loss = [(candidates.side_error(criterion, *a) + candidates.side_error(criterion, *b)) / unit / max(1, self.domain.m) for _, a, b in rows]
        limit = min((x for x, r in zip(loss, rows, strict=True) if r[0] > 0), default=0.0) + 10.0**-digits
        near = [r for x, r in zip(loss, rows, strict=True) if r[0] > 0 and x <= limit]
        return best(candidates.local_curve(self.obs.sparkSession, near, criterion, scale), digits)

    def _held(self, words: int) -> None:
        self.ledger.machine_words = max(self.ledger.machine_words, words)

    def _received(self, messages: int, words: int) -> None:
        self.ledger.messages = max(self.ledger.messages, messages)
        self.ledger.centre_words = max(self.ledger.centre_words, words)


def evaluate_splits(obs: DataFrame, keys: Keys, splits: Sequence[int], criterion: str = "mse", scale: int = 1, beta: float = 0.5, ledger: Ledger | None = None) -> DataFrame:
    """Losses and side errors of k splits in constant rounds."""
    cluster = Cluster(obs, keys, beta, ledger=ledger)
    return candidates.local_curve(obs.sparkSession, cluster.sides(sorted(set(splits)), criterion), criterion, scale)


def regression_additive(obs: DataFrame, keys: Keys, domain: Domain | None = None, scale: int = 1, seed: int = 0, ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """Constant rounds; the loss is at most the optimum plus O(1 / sqrt m) times the squared label range.

    Local samples of C log N / sqrt(m) go to the centre, which sends the candidates back; sorted machines evaluate them.
    """
    cluster = Cluster(obs, keys, 0.5, domain, ledger)
    eps = 1 / math.sqrt(max(1, cluster.domain.m))
    p = rate(cluster.domain.m, cluster.domain.n, eps, regression.C)
    if 2 * p * cluster.domain.m > candidates.ARROW_MAX:
        # More candidates than the driver should hold: the same two passes with the candidates as a table.
        return regression.additive_split(obs, keys, eps, cluster.domain, scale, seed=seed, ledger=cluster.ledger, digits=digits)
    splits = candidates.from_sample(cluster.local_sample(p, seed), cluster.domain.n)
    return cluster.result(cluster.sides(splits, "mse"), "mse", scale, digits)


def _multiplicative(obs: DataFrame, keys: Keys, eps: float, beta: float, domain: Domain | None, criterion: str, scale: int, mode: str, ledger: Ledger | None, digits: int) -> DataFrame:
    cluster = Cluster(obs, keys, beta, domain, ledger)
    d = cluster.domain
    grid = regression.error_grid(d, eps) if criterion == "mse" else guesses.geometric(1.0, max(1, d.m), eps)
    run = guesses.frontier if mode == "frontier" else guesses.search
    j = run(grid, d.n, cluster.errors(criterion), guesses.levels_for(d.n, beta), cluster.ledger.guessing)[0]
    return cluster.result(cluster.sides([j], criterion), criterion, scale, digits)


def regression_multiplicative(obs: DataFrame, keys: Keys, eps: float, beta: float = 0.5, domain: Domain | None = None, scale: int = 1, mode: str = "batched", ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """O(1/beta) rounds, each for beta log N levels of all searches."""
    return _multiplicative(obs, keys, eps, beta, domain, "mse", scale, mode, ledger, digits)


def classification_additive(obs: DataFrame, keys: Keys, domain: Domain | None = None, rate_kind: str = "printed", seed: int = 0, ledger: Ledger | None = None, criterion: str = "misclassification", digits: int = 6) -> DataFrame:
    """(j, loss) in one round: local samples of C log N / sqrt(m), solved at the centre. The loss is the sample's."""
    cluster = Cluster(obs, keys, 0.5, domain, ledger)
    m = max(1, cluster.domain.m)
    sample = cluster.local_sample(rate(m, cluster.domain.n, 1 / math.sqrt(m), 9.0, 1 if rate_kind == "printed" else 2), seed)
    return classification.additive_split(sample, ["x"], 1.0, Domain(m, cluster.domain.n, -1, 1), c=float("inf"), criterion=criterion, digits=digits).select("j", "loss")


def gini_additive(obs: DataFrame, keys: Sequence[str], domain: Domain | None = None, estimator: str = "plugin", seed: int = 0, ledger: Ledger | None = None) -> DataFrame:
    """(j, loss) in one round; the same local samples serve an error of m**(-1/4)."""
    if estimator == "plugin":
        return classification_additive(obs, keys, domain, "printed", seed, ledger, "gini")
    domain = domain or resolve(obs)
    return gini.additive_split(obs, keys, max(1, domain.m) ** -0.25, domain, estimator=estimator, seed=seed)


def classification_multiplicative(obs: DataFrame, keys: Keys, eps: float, beta: float = 0.5, domain: Domain | None = None, mode: str = "batched", ledger: Ledger | None = None, digits: int = 6) -> DataFrame:
    """O(1/beta) rounds of the same search with minority counts as errors."""
    return _multiplicative(obs, keys, eps, beta, domain, "misclassification", 1, mode, ledger, digits)
