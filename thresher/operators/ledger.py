"""Accounts of a search: passes, rounds, machines, messages, state, samples, update and post-processing time."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

#: Words of a moment triple, of a guess (two errors, two ends) and of a sampled pair.
TRIPLE, GUESS, PAIR = 3, 4, 2


@dataclass
class Ledger:
    passes: int = 0
    rounds: int = 0
    rows: int = 0
    state_rows: int = 0
    sample_rows: int = 0
    broadcast_rows: int = 0
    live_guesses: int = 0
    comparisons: int = 0
    machines: int = 0
    machine_words: int = 0
    messages: int = 0
    centre_words: int = 0
    pass_s: float = 0.0
    began: float = field(default_factory=time.time)
    last_pass: float = 0.0
    ended: float = 0.0

    @contextmanager
    def one_pass(self, rows: int = 0) -> Iterator[None]:
        """Times a scan of the observations; what comes after the last one is post-processing."""
        at = time.time()
        yield
        self.last_pass = time.time()
        self.pass_s += self.last_pass - at
        self.passes += 1
        self.rows += rows

    def scanned(self, state_rows: int = 0, broadcast_rows: int = 0, rounds: int = 1) -> None:
        """The state that a pass held; the largest of any pass counts."""
        self.rounds += rounds
        self.state_rows = max(self.state_rows, state_rows)
        self.broadcast_rows = max(self.broadcast_rows, broadcast_rows)
        self.comparisons = max(self.comparisons, broadcast_rows.bit_length())

    def guessing(self, live: int) -> None:
        self.live_guesses = max(self.live_guesses, live)

    def sampled(self, rows: int) -> None:
        self.sample_rows = max(self.sample_rows, rows)

    def finish(self) -> Ledger:
        self.ended = time.time()
        return self

    @property
    def state_words(self) -> int:
        return TRIPLE * self.state_rows + self.broadcast_rows + GUESS * self.live_guesses + PAIR * self.sample_rows

    def report(self) -> dict:
        """All accounts; ``update_ns`` is the wall time of the passes for each row that they scanned."""
        end = self.ended or time.time()
        return {
            "passes": self.passes,
            "rounds": self.rounds,
            "state_rows": self.state_rows,
            "state_words": self.state_words,
            "sample_rows": self.sample_rows,
            "broadcast_rows": self.broadcast_rows,
            "live_guesses": self.live_guesses,
            "comparisons": self.comparisons,
            "machines": self.machines,
            "machine_words": self.machine_words,
            "messages": self.messages,
            "centre_words": self.centre_words,
            "update_ns": round(1e9 * self.pass_s / self.rows) if self.rows else 0,
            "pass_ms": round(1000 * self.pass_s),
            "post_ms": round(1000 * max(0.0, end - (self.last_pass or end))),
            "wall_ms": round(1000 * (end - self.began)),
        }
