"""Cheapest cost at which a lift can pass the plain test, without listing lifts one by one.

The sorted order decides who crosses: behind block i the x that move on are the x highest of blocks 0..i. So a
partial lift is told by i, x, what has been spent, and the demands of those that have settled. Of two with
the same i and x the first may stand for the second if its demands, filled up with unit demands to the same
sum, are majorized by the second's: whatever completes the second to demands that a simple graph can meet
does so for the first, as such demands are closed downwards under majorization. Unit demands on fresh
vertices are what wasting adds, and a closed form tells how many are needed in the end. What is kept are
thus the cores of lifts, and the least cost + waste of a core is a lower bound on every passing lift.

If more than BEAM states stay at one (i, x), they are replaced by one below all of them: least cost, least sum
of the r largest demands for every r (a minimum of concave sums is concave, so these are demands again). The
bound stays valid, but need not be attained any more.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import accumulate

import numpy as np

from crowding.core.feasibility import waste_needed
from crowding.core.lifting import INF, _Walk, check

BEAM = 24
#: Cells of the table of cheapest rests; beyond it the search is not begun.
CELLS = 40_000_000


class Meter:
    """Work that may still be done, in units that don't depend on the machine; seconds, if given, end it as well."""

    def __init__(self, work: float | None = None, seconds: float | None = None):
        import time

        self.clock = time.monotonic
        self.left = float("inf") if work is None else float(work)
        self.end = None if seconds is None else self.clock() + seconds

    def spend(self, units: float = 1.0) -> bool:
        """Take units; False if there is nothing left."""
        self.left -= units
        return not self.over()

    def over(self) -> bool:
        return self.left <= 0 or (self.end is not None and self.clock() > self.end)


@dataclass
class Core:
    """A kept lift: cost, demands of two and more in falling order, unit demands, and its crossings (None if merged)."""

    cost: int
    large: tuple[int, ...]
    units: int
    x: tuple[int, ...] | None

    def histogram(self) -> Counter:
        out = Counter(self.large)
        if self.units:
            out[1] += self.units
        return out


@dataclass
class Search:
    """cost: least cost + waste of the cores; exact: no states were merged on the way; cores attain it."""

    cost: int
    exact: bool
    cores: list[Core]


def _sums(large: tuple[int, ...], units: int, n: int) -> list[int]:
    """Sums of the 1..n largest demands."""
    out = list(accumulate(large[:n]))
    top = out[-1] if out else 0
    return out + [top + min(units, j) for j in range(1, n - len(out) + 1)]


def _front(states: list[tuple], fly: int) -> list[tuple]:
    """States (spent, large, path) that no other stands for; fly: what those on the move have cost so far."""
    states.sort(key=lambda s: (s[0], s[1]))
    kept: list[tuple] = []
    sums: list[list[int]] = []
    for s in states:
        spent, large, _ = s
        units = spent - fly - sum(large)
        mine: list[int] | None = None
        for (_, other, _), theirs in zip(kept, sums):
            n = len(other)
            if mine is None or len(mine) < n:
                mine = _sums(large, units, max(n, len(large)))
            if all(a <= b for a, b in zip(theirs, mine)):
                break
        else:
            kept.append(s)
            sums.append(list(accumulate(large)))
    return kept


def _meet(states: list[tuple], fly: int) -> tuple:
    """One state below all."""
    n = max(s[0] for s in states)
    n = min(n, max(len(s[1]) for s in states) + max(s[0] - fly - sum(s[1]) for s in states))
    least = [min(col) for col in zip(*[_sums(s[1], s[0] - fly - sum(s[1]), n) for s in states])]
    demands = [b - a for a, b in zip([0, *least], least)]
    return min(s[0] for s in states), tuple(d for d in demands if d > 1), None


def passing_cost(blocks, k: int, most: int, meter: Meter | None = None, beam: int = BEAM) -> Search | None:
    """Lower bound on the cost of lifts that pass the plain test, given that it is at most `most`; None if the
    work ran out. Lifts of every span and headroom are covered."""
    b = check(blocks, k)
    meter = meter or Meter()
    if (most + 1) * (len(b) + most // k + 1) > CELLS:
        return None
    walk = _Walk(b, k, most, "complete", None)
    layer: dict[int, list[tuple]] = {0: [(0, (), ())]}  # inflow -> states (spent, large demands, path of outflows)
    tops: list[int] = []  # degrees of the highest members below the block, highest first
    exact = True
    for i, size in enumerate(walk.b.tolist()):
        after: dict[int, list[tuple]] = {}
        rest = walk.rest[i + 1]
        for y, states in layer.items():
            if size == 0 and y < k:  # nobody can settle in an empty block
                price = y + int(rest[y]) if y < len(rest) else INF
                kept = [(spent + y, large, None if path is None else (y, path)) for spent, large, path in states if spent + price <= most]
                if kept:
                    after.setdefault(y, []).extend(kept)
                continue
            gained = [i - d for d in tops[:y]]  # demands of those on the move, smallest first
            low = min(s[0] for s in states)
            for x in walk.outflows(i, y, most - low):
                price = x + int(rest[x])
                settled = min(y, size + y - x)  # those that came furthest settle first
                new = [d for d in gained[y - settled :] if d > 1]
                into = after.setdefault(x, [])
                for spent, large, path in states:
                    if spent + price <= most:
                        into.append((spent + x, tuple(sorted((*large, *new), reverse=True)) if new else large, None if path is None else (x, path)))
        tops = [i] * min(size, walk.width) + tops[: max(0, walk.width - size)]
        work = sum(map(len, after.values()))
        if not meter.spend(work / 100):
            return None
        layer = {}
        for x, states in after.items():
            if not states:
                continue
            fly = sum(i + 1 - d for d in tops[:x])
            kept = _front(states, fly) if len(states) > 1 else states
            if len(kept) > beam:
                kept, exact = [_meet(kept, fly)], False
            layer[x] = kept
    found = []
    for spent, large, path in layer.get(0, []):
        core = Core(spent, large, spent - sum(large), None)
        if path is not None:
            x = []
            while path:
                x.append(path[0])
                path = path[1]
            core.x = tuple(reversed(x))
        found.append((spent + waste_needed(core.histogram()), core))
    if not found:
        return None
    cost = min(c for c, _ in found)
    return Search(cost, exact, [core for c, core in found if c == cost])
