"""Bounds and solutions of one instance: lower bounds by refutation, upper bounds by wasting, baselines.

How long anything may take is told by one measure, work: lifts tested, states kept, demands realized, in
units of a few ms. It doesn't depend on the machine, so equal calls give equal rows. A time limit in seconds, as
the reference has one, can be set beside it. Whatever ends early gives the bounds reached so far.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain, groupby, islice

import numpy as np

from crowding.core import feasibility as fe
from crowding.core import realization as re_
from crowding.core.jump import Meter, Search, passing_cost
from crowding.core.lifting import Lift, check, enumerate_lifts, is_crowded, lifted, min_cost, min_lift, reduce_pattern
from crowding.core.realization import Instance

#: Units of work of a phase, for one graph and one k.
WORK = 2000
#: Lifts near which the heuristic also ends.
NEAR = 3


@dataclass
class Bound:
    """Lower bound in edges, lifts that passed at its cost, more of them on demand, and how the search ended.

    upper_edges is the upper end of the number problem: a lift of that cost passes the test, or is not refuted.
    status: ok (a lift passed at the bound), limit (the work or the time ran out before).
    """

    min_cost: int
    lower_edges: int
    upper_edges: int | None
    passing: list[Lift] = field(default_factory=list)
    status: str = "ok"
    refuted: int = 0
    mode: str = "complete"
    more: Iterator[Lift] = field(default_factory=lambda: iter(()))


def realizable_lower_bound(
    inst: Instance, k: int, test: str = "graph_eg", span: str = "complete", reduce: bool = False, climb: str = "jump",
    work: float | None = WORK, seconds: float | None = None,
) -> Bound:
    """Raise the cost, over even values, until some lift passes the test.

    test: none, eg or graph_eg. climb: "jump" finds the least cost of lifts that pass the plain test in one search
    over cores and their waste (see jump.py), then looks for a lift of that cost that passes; "step" tests every
    lift of a cost before the next. The pattern rule orders the jump's search: lifts of the reduced sequence come first,
    but only all lifts together refute a cost, so the bound is proven. With reduce, lifts of the reduced sequence are the
    only ones; on small instances the bound can then come out too high (mode says "reduced", and no optimum is
    claimed from it).
    """
    if test not in ("none", "eg", "graph_eg") or climb not in ("step", "jump"):
        raise ValueError("unknown test or climb")
    b = check(inst.blocks, k)
    meter = Meter(work, seconds)
    mode = "reduced" if reduce else span
    least = min_cost(b, k)
    if least == 0:
        return Bound(0, 0, 0, [Lift((0,) * len(b))], mode=mode)
    first = min_lift(b, k)
    upper = least + fe.waste_needed(fe.demand_histogram(b, first.x))
    cost, search = least + least % 2, None
    if climb == "jump" and test != "none" and not reduce and span == "complete":
        search, proven = climb_by_cores(b, k, least, upper, meter)
        cost = proven + proven % 2
        if search is None:
            return Bound(least, cost // 2, (max(upper, cost) + 1) // 2, [], "limit", 0, mode)
        upper = search.cost if search.exact else upper
    refuted = [0]
    while True:
        passed = _passing(inst, b, k, cost, search, test, span, reduce, meter, refuted)
        found = next(passed, None)
        if isinstance(found, Lift):
            return Bound(least, cost // 2, cost // 2, [found], "ok", refuted[0], mode, passed)
        if found is _OVER or meter.over():
            return Bound(least, cost // 2, (max(upper, cost) + 1) // 2, [], "limit", refuted[0], mode)
        cost += 2


def climb_by_cores(b: np.ndarray, k: int, least: int, upper: int, meter: Meter) -> tuple[Search | None, int]:
    """(search that ended, least cost not refuted): searches with growing slack over the minimum, as a short one
    that finds nothing is a proof up to its slack."""
    proven, slack = least, 0
    while True:
        most = min(upper, least + slack)
        got = passing_cost(b, k, most, meter)
        if got is None:
            return None, proven
        if got.cost <= most or most == upper:
            return got, min(got.cost, upper)
        proven, slack = min(got.cost, most + 1), max(4, 4 * slack)


_OVER = object()


def _passing(inst: Instance, b: np.ndarray, k: int, cost: int, search: Search | None, test: str, span: str, reduce: bool, meter: Meter, refuted: list[int]) -> Iterator:
    """Lifts of a cost that pass, each once; _OVER if the work ends before all lifts have been seen. refuted counts the others."""
    seen: dict[tuple, bool] = {}
    given: set[tuple] = set()
    for x in _lifts(b, k, cost, search, span, reduce, meter):
        if x is None or not meter.spend():
            yield _OVER
            return
        runs = tuple((v, sum(1 for _ in run)) for v, run in groupby(x))  # a hub far above the others makes x long, not its runs
        if runs in given:
            continue
        given.add(runs)
        hist = fe.demand_histogram(b, x)
        ok = True
        if test != "none":
            key = tuple(sorted(hist.items()))
            if key not in seen:
                seen[key] = fe.eg_test_blocks(hist)
            ok = seen[key] and (test == "eg" or fe.graph_eg_test(b, x, inst.members, inst.adjacent))
        if ok:
            yield Lift(x)
        else:
            refuted[0] += 1


def _lifts(b: np.ndarray, k: int, cost: int, search: Search | None, span: str, reduce: bool, meter: Meter) -> Iterator[tuple[int, ...] | None]:
    """Crossings of lifts of a cost: those that the cores lead to, those of the reduced sequence, then all; None where
    the work ran out. Some come twice."""
    for core in search.cores if search is not None else ():
        if core.x is not None:
            yield from _trimmed(re_.waste_spread(b, core.x, k, cost - core.cost), len(b))
    base, paid, log = reduce_pattern(b, k) if reduce or span == "complete" else (b, None, [])
    rounds = ([(base, paid)] if log or reduce else []) + ([] if reduce else [(b, np.zeros(len(b), np.int64))])
    for blocks, done in rounds:
        left = cost - int(done.sum())
        if left < 0:
            continue
        try:
            for lift in enumerate_lifts(blocks, k, left, span, None if span == "complete" else 0, over=lambda: not meter.spend(0.02)):
                x = np.zeros(max(len(done), len(lift.x)), np.int64)
                x[: len(done)] += done
                x[: len(lift.x)] += np.asarray(lift.x, np.int64)
                yield from _trimmed([tuple(x.tolist())], len(b))
        except TimeoutError:
            yield None
            return


def _trimmed(xs, n: int) -> Iterator[tuple[int, ...]]:
    """Without levels above the maximum that nobody reaches, so that equal lifts are equal."""
    for x in xs:
        x = list(x)
        while len(x) > n and not x[-1] and not x[-2]:
            x.pop()
        yield tuple(int(v) for v in x)


@dataclass
class Found:
    """Insertions of an upper bound, and the crossings they realize."""

    edges: set[tuple[int, int]]
    x: tuple[int, ...]
    variant: str
    wasted: int


def _attempt(inst: Instance, x, variants, meter: Meter):
    if not meter.spend(len(variants) * (1 + sum(x) / 50)):
        return None
    return re_.realize(inst, x, variants=variants)


def upper_bound(inst: Instance, k: int, lifts, work: float | None = WORK, seconds: float | None = None, lower: int = 0) -> Found | None:
    """Realize one of the lifts; of those that fail, waste units until one is realized; the smallest result.

    lower: a cost that no solution can beat. Waste is looked for by doubling, and from there back down by halving; a
    later lift begins with the most waste that would still give a smaller result.
    """
    b = inst.blocks
    meter = Meter(work, seconds)
    best: Found | None = None
    for lift in lifts:
        if meter.over():
            break
        if not fe.eg_test_blocks(fe.demand_histogram(b, lift.x)):
            got = None
        elif (got := _attempt(inst, lift.x, re_.VARIANTS, meter)) is not None:
            if best is None or len(got[0]) < len(best.edges):
                best = Found(got[0], lift.x, got[1], 0)
            if lift.cost <= lower:
                return best
            continue
        waste = max(1, re_.waste_of(lift, b))
        waste += (lift.cost + waste) % 2

        def tried(units: int) -> Found | None:
            if not units:
                return None
            some = list(re_.waste_spread(b, lift.x, k, units, most=2))
            # only where no two neighbouring blocks can take it: every other way
            for x in some or re_.waste_dp(b, lift.x, k, units, over=lambda: not meter.spend(0.02)):
                if meter.over() or (not some and not meter.spend()):  # a lift tested is work, also if it is refused
                    return None
                if (some or fe.eg_test_blocks(fe.demand_histogram(b, x))) and (hit := _attempt(inst, x, re_.VARIANTS[:3], meter)) is not None:
                    return Found(hit[0], x, hit[1], units)
            return None

        limit, failed, hit = int(b.sum()) * 2, waste - 2, None
        if best is not None:  # only what is smaller is of use
            high = 2 * len(best.edges) - 2 - lift.cost
            hit = tried(high) if high >= waste else None
        else:
            high, step = waste, 2
            while high <= limit and not meter.over() and (hit := tried(high)) is None:
                failed, high, step = high, high + step, 2 * step
        while hit is not None:  # halve what is between waste that failed and waste that did not
            best = hit
            middle = failed + (high - failed) // 4 * 2
            if not failed < middle < high or meter.over():
                break
            if (hit := tried(middle)) is None:
                failed, hit = middle, best
            else:
                high = middle
    return best


def complete_bound(n: int, m: int) -> int:
    """Insertions that make the graph complete, which is always crowded."""
    return n * (n - 1) // 2 - m


def greedy_groups(degrees: np.ndarray, k: int) -> np.ndarray:
    """Targets of vertices in descending order of degree: groups of k or more near degrees, each raised to its
    first; the next vertex joins if that is cheaper than to begin a group with it; under 2k vertices never split."""
    n = len(degrees)
    out = np.zeros(n, np.int64)
    start = 0
    while start < n:
        if n - start < 2 * k:
            out[start:] = degrees[start]
            break
        end = start + k
        while n - end >= k + 1 and end - start < 2 * k - 1:
            join = (degrees[start] - degrees[end]) + (degrees[end + 1 : end + k + 1].size * degrees[end + 1] - degrees[end + 1 : end + k + 1].sum() if end + 1 < n else 0)
            new = degrees[end : end + k].size * degrees[end] - degrees[end : end + k].sum()
            if join > new:
                break
            end += 1
        while n - end >= k and degrees[end] == degrees[start]:
            end += 1  # equal degrees cost nothing
        out[start:end] = degrees[start]
        start = end
    return out


def cluster_baseline(inst: Instance, k: int, rounds: int = 40, seed: int = 0, x=None) -> set[tuple[int, int]] | None:
    """Clustering baseline, only named in the reference: a reconstruction.

    x: crossings of a lift that take the place of the first round's groups; then this is no baseline, but ends near the lift.

    Group, raise every group to its top, join those that ask among themselves, and give what is left to
    non-neighbours of low degree; repeat until the graph is crowded. Those who are given an edge beyond their own
    demand move up a block, so they are taken where the block they leave and the one they enter stay full, as long as there are such.
    Vertices that are not known only count. If nothing else ends it, a graph known as a whole is made complete.
    """
    check(inst.blocks, k)
    known = {v: d for d, vs in inst.members.items() for v in vs}
    unknown = Counter({d: int(n) - len(inst.members.get(d, ())) for d, n in enumerate(inst.blocks)})
    adj = re_.Joined(inst.adjacent, known)
    deg = dict(known)
    out: set[tuple[int, int]] = set()

    def join(u: int, v: int) -> None:
        adj.add(u, v)
        deg[u] += 1
        deg[v] += 1
        out.add((min(u, v), max(u, v)))

    for r in range(rounds):
        now = Counter(deg.values())
        for d, n in unknown.items():
            now[d] += n
        if all(n == 0 or n >= k for n in now.values()):
            return out
        if r == 0 and x is not None:
            dem = re_.choose(inst, re_.decompose(inst.blocks, x), "least_conflict")
            if dem is None:
                return None
            target = {v: d + dem.get(v, 0) for v, d in deg.items()}
            size = Counter({d: int(n) for d, n in enumerate(lifted(inst.blocks, x)) if n})
        else:
            # unknown members of a block stand before its known ones, so that known ones are those that move
            more = np.array([(d, n) for d, n in unknown.items() if n > 0], np.int64).reshape(-1, 2)
            n = int(more[:, 1].sum())
            ds = np.concatenate([np.repeat(more[:, 0], more[:, 1]), np.fromiter(deg.values(), np.int64, len(deg))])
            vs = np.concatenate([np.zeros(n, np.int64), np.fromiter(deg, np.int64, len(deg))])
            told = np.arange(len(ds)) >= n
            order = np.lexsort((vs, told, -ds))
            want = greedy_groups(ds[order], k)
            seen = told[order]
            target = dict(zip(vs[order][seen].tolist(), want[seen].tolist()))
            dem = {v: t - deg[v] for v, t in target.items() if t > deg[v]}
            size = Counter(dict(zip(*(x.tolist() for x in np.unique(want, return_counts=True)))))
        edges, stuck = re_.greedy_connect(dem, adj, "largest" if r == 0 else "random", seed + r)
        for u, v in edges:
            join(u, v)
        # size is what blocks have once all demands are met; level tells who will be where
        level: dict[int, list[int]] = {}
        for v in sorted(target):
            level.setdefault(target[v], []).append(v)

        def given(units: int, free: dict[int, Iterator[int]]) -> Iterator[int]:
            """Non-neighbours for units of one vertex, which move up; free: those of each level."""
            first = {t: v for t in sorted(free) if (v := next(free[t], None)) is not None}
            for _ in range(units):
                best = None
                for t in first:
                    full = (size[t] > k or size[t] == 1) and size[t + 1] >= k - 1
                    if full or best is None:
                        best = t
                    if full:
                        break
                if best is None:
                    return
                v = first[best]
                size[best] -= 1
                size[best + 1] += 1
                target[v] = best + 1
                yield v
                if (after := next(free[best], None)) is None:
                    del first[best]
                else:
                    first[best] = after

        for u in sorted(stuck, key=lambda v: (-stuck[v], v)):
            near, moved = adj[u], {}
            for v in given(stuck[u], {t: (v for v in vs if v not in near and v not in stuck) for t, vs in level.items()}):
                join(u, v)
                moved.setdefault(target[v] - 1, []).append(v)
            # who has moved is u's neighbour now, so that lists need not change before
            for t, vs in moved.items():
                if len(vs) < 8:
                    for v in vs:
                        level[t].remove(v)
                else:
                    gone = set(vs)
                    level[t] = [v for v in level[t] if v not in gone]
            for t, vs in moved.items():
                level.setdefault(t + 1, []).extend(vs)
    if any(unknown.values()):
        return None
    vs = sorted(adj)
    return out | {(u, v) for i, u in enumerate(vs) for near in (adj[u],) for v in vs[i + 1 :] if v not in near}


def two_phase_baseline(inst: Instance, k: int, rounds: int = 60) -> set[tuple[int, int]] | None:
    """The older scheme: one cheapest lift, local exchange; if stuck, end near the target and crowd again."""
    members = {d: list(vs) for d, vs in inst.members.items()}
    adj = re_.Joined(inst.adjacent, (v for vs in members.values() for v in vs))
    now = Instance(np.array(inst.blocks), members, adj)
    out: set[tuple[int, int]] = set()
    for r in range(rounds):
        if is_crowded(now.blocks, k):
            return out
        x = min_lift(now.blocks, k).x
        dem = re_.choose(now, re_.decompose(now.blocks, x, "fifo"), "lowest_id" if r == 0 else "random", r)
        if dem is None:
            return None
        edges = re_.local_exchange(dem, now.adjacent, r)
        if edges is None:
            edges, stuck = re_.greedy_connect(dem, now.adjacent, "random", r)
            low = [v for d in sorted(now.members) for v in now.members[d][: 4 * k]]
            extra: set[tuple[int, int]] = set()
            for u, need in stuck.items():
                for v in low:
                    e = (min(u, v), max(u, v))
                    if need and v != u and v not in now.adjacent.get(u, ()) and e not in edges and e not in extra:
                        extra.add(e)
                        need -= 1
            edges = edges | extra
        if not edges:
            return None
        out |= edges
        now = insert(now, edges)
    return None


def insert(inst: Instance, edges) -> Instance:
    """The instance with edges among known vertices added."""
    deg = {v: d for d, vs in inst.members.items() for v in vs}
    adj = re_.Joined(inst.adjacent, deg)
    blocks = Counter({d: int(n) for d, n in enumerate(inst.blocks)})
    for u, v in edges:
        adj.add(u, v)
        for p in (u, v):
            blocks[deg[p]] -= 1
            deg[p] += 1
            blocks[deg[p]] += 1
    members: dict[int, list[int]] = {}
    for v in sorted(deg):
        members.setdefault(deg[v], []).append(v)
    top = max(d for d, n in blocks.items() if n)
    return Instance(np.array([blocks[d] for d in range(top + 1)], np.int64), members, adj)


@dataclass
class Row:
    """One line of a result table; sizes in edges, times in seconds, None where the limit was hit."""

    k: int
    n: int
    max_degree: int
    ch: int | None
    oh: int | None
    opt: int | None
    dp_lo: int
    dp_hi: int | None
    t_ch: float
    t_oh: float
    t_dp: float
    status: str
    lb_mode: str
    variant: str
    verified: bool
    edges: list[tuple[int, int]]


def solve(inst: Instance, k: int, work: float | None = WORK, seconds: float | None = None, with_cluster: bool = True) -> Row:
    """Bounds, a realized solution, checked, and the clustering baseline; each stage with its own time."""
    t0 = time.monotonic()
    bound = realizable_lower_bound(inst, k, work=work, seconds=seconds)
    t1 = time.monotonic()
    lifts = chain(bound.passing, bound.more) if bound.passing else iter(_cheap_lifts(inst.blocks, k, Meter(work, seconds)))
    lifts = (x for x in lifts if isinstance(x, Lift))
    first = list(islice(lifts, NEAR))
    found = upper_bound(inst, k, chain(first, lifts), work, seconds, 2 * bound.lower_edges)
    if found is None or len(found.edges) > bound.lower_edges:  # end near a lift and crowd again
        for lift in first:
            near = cluster_baseline(inst, k, x=lift.x)
            if near is not None and (found is None or len(near) < len(found.edges)):
                found = Found(near, lift.x, "near", 0)
    if found is None and (near := two_phase_baseline(inst, k)) is not None:
        found = Found(near, (), "near", 0)
    t2 = time.monotonic()
    ch = cluster_baseline(inst, k) if with_cluster else None
    t3 = time.monotonic()
    if found is None and ch is not None:
        found = Found(ch, (), "clusters", 0)
    oh = len(found.edges) if found else None
    opt = oh if oh is not None and bound.mode == "complete" and oh == bound.lower_edges else None
    hi = bound.upper_edges if bound.upper_edges is not None else oh
    return Row(
        k, inst.n, len(inst.blocks) - 1, None if ch is None else len(ch), oh, opt, bound.lower_edges, hi, round(t3 - t2, 3), round(t2 - t1, 3), round(t1 - t0, 3),
        bound.status, bound.mode, found.variant if found else "", found is not None and solves(inst, found.edges, k), sorted(found.edges) if found else [],
    )


def solves(inst: Instance, edges, k: int) -> bool:
    """Whether edges among known vertices are new, distinct and no loops, and make the graph crowded."""
    new = {(min(e), max(e)) for e in edges}
    if len(new) != len(edges) or any(u == v or v in inst.adjacent.get(u, ()) for u, v in new):
        return False
    return is_crowded(insert(inst, new).blocks, k)


def _cheap_lifts(blocks, k: int, meter: Meter, most: int = 20) -> list[Lift]:
    """Of cheapest lifts those that need the least waste: what there is to begin with if no lift has passed."""
    out = []
    try:
        for lift in enumerate_lifts(blocks, k, min_cost(blocks, k), "narrow", limit=400, over=lambda: not meter.spend(0.02)):
            out.append((re_.waste_of(lift, blocks), lift))
    except TimeoutError:
        pass
    out.sort(key=lambda f: (f[0], f[1].x))
    return [lift for _, lift in out[:most]] or [min_lift(blocks, k)]


def lifted_blocks(inst: Instance, x) -> np.ndarray:
    return lifted(inst.blocks, x)
