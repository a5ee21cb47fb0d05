"""Search by guessed errors: both sides' errors are guessed on a geometric grid and a split that
meets the guess is found by bisection, since the left error never falls and the right one never
rises with j. Passes only see the probes of live guesses, each once."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from dataclasses import dataclass

Errors = dict[int, tuple[float, float]]
Evaluate = Callable[[list[int]], Errors]


def geometric(low: float, high: float, eps: float) -> list[float]:
    """0 and the powers of 1 + eps times ``low``, up to one that is at least ``high``."""
    grid, z = [0.0], low
    while True:
        grid.append(z)
        if z >= high:
            return grid
        z *= 1 + eps


def printed(high: float, eps: float) -> list[float]:
    """The grid as printed: 0 and the powers of 1 + eps from the first on; it has no value between 0 and 1 + eps."""
    last = max(1, math.ceil(math.log(max(high, 1 + eps), 1 + eps)))
    return [0.0, *[(1 + eps) ** k for k in range(1, last + 1)]]


@dataclass
class Guess:
    left: float
    right: float
    low: int
    high: int
    found: int | None = None

    def live(self) -> bool:
        return self.found is None and self.low <= self.high

    def middle(self) -> int:
        return (self.low + self.high) // 2


def advance(guesses: Iterable[Guess], errors: Errors) -> None:
    """Replays bisection as far as the evaluated splits go. A split that meets the guess ends it."""
    for g in guesses:
        while g.live() and (j := g.middle()) in errors:
            left, right = errors[j]
            fits_left, fits_right = left <= g.left, right <= g.right
            if fits_left and fits_right:
                g.found = j
            elif not fits_left and not fits_right:
                g.low, g.high = 1, 0
            elif fits_right:
                g.high = j - 1
            else:
                g.low = j + 1


def expand(low: int, high: int, levels: int) -> list[int]:
    """The splits that bisection of [low, high] can touch in its next levels."""
    out, ranges = [], [(low, high)]
    for _ in range(levels):
        after = []
        for a, b in ranges:
            if a <= b:
                j = (a + b) // 2
                out.append(j)
                after += [(a, j - 1), (j + 1, b)]
        ranges = after
    return out


def levels_for(n: int, beta: float) -> int:
    """Levels of bisection for each pass: 2**levels is about N**beta."""
    return max(1, math.floor(beta * math.log2(max(2, n))))


def search(grid: list[float], n: int, evaluate: Evaluate, levels: int = 1, note: Callable[[int], None] | None = None) -> tuple[int, float, int]:
    """The split of the least met bound, that bound, and the number of passes. Smallest split on ties."""
    guesses = [Guess(a, b, 1, n) for a in grid for b in grid]
    passes = 0
    while True:
        # A larger guess can't beat a bound that is met already.
        met = min((g.left + g.right for g in guesses if g.found), default=math.inf)
        live = [g for g in guesses if g.live() and g.left + g.right <= met]
        if not live:
            break
        if note:
            note(len(live))
        probes = sorted({j for a, b in {(g.low, g.high) for g in live} for j in expand(a, b, levels)})
        advance(live, evaluate(probes))
        passes += 1
    bound, j = min((g.left + g.right, g.found) for g in guesses if g.found)
    return j, bound, passes


def frontier(grid: list[float], n: int, evaluate: Evaluate, levels: int = 1, note: Callable[[int], None] | None = None) -> tuple[int, float, int]:
    """For each grid value alone: the last split whose left error, and the first whose right error,
    is at most it. A pair is met if the one does not lie before the other; its split is the
    right one's. Two searches for each value in place of one for each pair."""
    last = {z: [0, n] for z in grid}
    first = {z: [1, n + 1] for z in grid}
    passes = 0
    while True:
        ends = [(*r, "l", z) for z, r in last.items() if r[0] < r[1]] + [(*r, "r", z) for z, r in first.items() if r[0] < r[1]]
        if not ends:
            break
        if note:
            note(len(ends))
        probes: set[int] = set()
        for a, b, side, _ in ends:
            probes |= _halvings(a, b, side, levels)
        errors = evaluate(sorted(p for p in probes if 1 <= p <= n))
        passes += 1
        for z, r in last.items():
            while r[0] < r[1] and (j := (r[0] + r[1] + 1) // 2) in errors:
                r[:] = [j, r[1]] if errors[j][0] <= z else [r[0], j - 1]
        for z, r in first.items():
            while r[0] < r[1] and (j := (r[0] + r[1]) // 2) in errors:
                r[:] = [r[0], j] if errors[j][1] <= z else [j + 1, r[1]]
    met = [(a + b, first[b][0]) for a in grid for b in grid if first[b][0] <= last[a][0]]
    bound, j = min(met)
    return j, bound, passes


def _halvings(a: int, b: int, side: str, levels: int) -> set[int]:
    out, ranges = set(), [(a, b)]
    for _ in range(levels):
        after = []
        for lo, hi in ranges:
            if lo < hi:
                j = (lo + hi + 1) // 2 if side == "l" else (lo + hi) // 2
                out.add(j)
                after += [(lo, j - 1), (j, hi)] if side == "l" else [(lo, j), (j + 1, hi)]
        ranges = after
    return out
