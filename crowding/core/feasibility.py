"""Tests whether demands can be met by a simple graph, alone and beside the edges that exist already."""

from __future__ import annotations

from collections import Counter

import numpy as np

from crowding.core.lifting import lifted


def demand_histogram(before, x) -> Counter:
    """Demand -> vertices, of the matching that keeps the sorted order (nobody overtakes)."""
    after = lifted(before, x)
    out: Counter = Counter()
    i = j = 0
    left, room = [int(v) for v in before], [int(v) for v in after]
    while i < len(left):
        if not left[i]:
            i += 1
        elif not room[j]:
            j += 1
        else:
            n = min(left[i], room[j])
            if j > i:
                out[j - i] += n
            left[i] -= n
            room[j] -= n
    return out


def eg_test(demands) -> bool:
    """Sum even, and every prefix of the descending demands within what it can get."""
    d = np.sort(np.asarray([x for x in demands if x], dtype=np.int64))[::-1]
    if d.sum() % 2:
        return False
    prefix = np.cumsum(d)
    for r in range(1, len(d) + 1):
        if prefix[r - 1] > r * (r - 1) + np.minimum(d[r:], r).sum():
            return False
    return True


def deficit(hist: dict[int, int]) -> int:
    """Most by which a prefix asks more than it can get; one check a distinct demand."""
    values = sorted((v for v in hist if v > 0 and hist[v]), reverse=True)
    worst, r, total = 0, 0, 0
    counts = np.array([hist[v] for v in values], dtype=np.int64)
    vals = np.array(values, dtype=np.int64)
    for i, v in enumerate(values):
        r += hist[v]
        total += v * hist[v]
        rest = int((np.minimum(vals[i + 1 :], r) * counts[i + 1 :]).sum())
        worst = max(worst, total - r * (r - 1) - rest)
        # within the run the worst prefix ends where the vertices stop gaining from each other
        lo, hi = r - hist[v] + 1, r - 1
        for q in {max(lo, min(hi, v)), max(lo, min(hi, v + 1))} if lo <= hi else ():
            part = total - v * (r - q)
            behind = int((np.minimum(vals[i + 1 :], q) * counts[i + 1 :]).sum()) + (r - q) * min(v, q)
            worst = max(worst, part - q * (q - 1) - behind)
    return worst


def eg_test_blocks(hist: dict[int, int]) -> bool:
    """eg_test on demand -> vertices."""
    return sum(v * n for v, n in hist.items()) % 2 == 0 and deficit(hist) <= 0


def waste_needed(hist: dict[int, int]) -> int:
    """Fewest unit demands on vertices without one that make the demands pass.

    Each adds one to what every prefix can get, so the deficit is needed, and one more if the sum stays odd.
    """
    need = max(0, deficit(hist))
    return need + (sum(v * n for v, n in hist.items()) + need) % 2


def targets(before, x) -> list[tuple[int, int | None]]:
    """Per block (largest degree its members may reach, target if it is the only one).

    Its members reach j when block j ends non-empty and something crosses every level on the way.
    """
    after = lifted(before, x)
    out: list[tuple[int, int | None]] = []
    far = near = None  # of the block above: largest and first degree that may be reached
    for i in range(len(after) - 1, -1, -1):
        if x[i] == 0:
            far = near = None
        if after[i] > 0:
            far, near = (i if far is None else far), i
        top = i if far is None else far
        out.append((top, near if near is not None and x[near] == 0 else None))
    return out[::-1]


def pinned(before, x) -> dict[int, int]:
    """Non-empty blocks whose members all end at one degree."""
    return {i: t for i, (_, t) in enumerate(targets(before, x)) if t is not None and i < len(before) and before[i]}


def graph_eg_test(before, x, members: dict[int, list[int]], adjacent: dict[int, set[int]]) -> bool:
    """eg_test_blocks, refined by edges among vertices whose demand is certain.

    The reference defers its details; this is a reconstruction from the stated idea. members: vertices per degree, as
    far as known; adjacent: edges among known vertices. Unknown ones count as if adjacent to nobody, so a
    refusal stays sound.
    """
    if not eg_test_blocks(demand_histogram(before, x)):
        return False
    cost = int(sum(x))
    reach = targets(before, x)
    fixed: list[tuple[int, int]] = []
    certain: dict[int, int] = {}
    for d, t in pinned(before, x).items():
        known = members.get(d, [])
        if len(known) >= before[d]:
            for v in known[: int(before[d])]:
                certain[v] = t - d
                if t > d:
                    fixed.append((t - d, v))
    fixed.sort(reverse=True)
    sure = sum(d for d, _ in fixed)
    loose = [(d, reach[d][0] - d) for d in range(len(before)) if before[d] and reach[d][0] > d and not (members.get(d) and members[d][0] in certain)]
    degree_of = {v: d for d, vs in members.items() for v in vs}
    most = dict(loose)
    chosen: set[int] = set()
    asked = inner = 0
    touched: dict[int, int] = {}
    for i, (dem, v) in enumerate(fixed):
        inner += touched.get(v, 0)
        chosen.add(v)
        asked += dem
        for u in adjacent.get(v, ()):
            touched[u] = touched.get(u, 0) + 1
        if i + 1 < len(fixed) and fixed[i + 1][0] == dem:
            continue
        a = len(chosen)
        room = a * (a - 1) - 2 * inner
        room += sum(min(d, a - touched.get(u, 0)) for d, u in fixed[i + 1 :])
        free = sum(int(before[d]) * min(m, a) for d, m in loose)
        for u, t in touched.items():
            d = degree_of.get(u)
            if d in most and u not in chosen:
                free -= min(most[d], a) - min(most[d], a - t)
        if asked > room + min(free, cost - sure):
            return False
    return True
