"""Goldens, invariants and brute-force comparisons of the kernels."""

import random
from itertools import combinations

import numpy as np
import pytest

from crowding.core import feasibility as fe
from crowding.core import jump
from crowding.core import realization as rz
from crowding.core import solve as sv
from crowding.core.lifting import (
    count_lifts,
    crossings,
    dominates,
    enumerate_lifts,
    is_crowded,
    lift_exists,
    lifted,
    min_cost,
    min_cost_by_segments,
    min_lift,
    raise_cost,
    reduce_pattern,
    section_cost,
    section_cuts,
)

WALK_A = [(1, 2), (2, 3), (2, 4), (3, 4)]
WALK_B = [(1, 4), (2, 4), (3, 4), (4, 5), (4, 7), (5, 6), (5, 7), (5, 8), (5, 9), (5, 10), (6, 10), (9, 10), (8, 9), (7, 8)]


def all_lifts(blocks, k, cost, headroom):
    """Every crossing vector by plain recursion."""
    b = [*blocks, *[0] * headroom]

    def go(i, y, left, x):
        if i == len(b):
            if y == 0 and left == 0:
                yield tuple(x)
            return
        for out in range(0, min(left, b[i] + y) + 1):
            r = b[i] + y - out
            if r == 0 or r >= k:
                yield from go(i + 1, out, left - out, [*x, out])

    return list(go(0, 0, cost, []))


def random_blocks(rng, n=5, top=6):
    return [0] + [rng.randint(0, top) for _ in range(n - 1)] + [rng.randint(1, 3)]


def degrees_of(blocks):
    return [d for d, n in enumerate(blocks) for _ in range(n)]


def test_first_walkthrough():
    b = rz.Instance.of_edges(WALK_A).blocks
    assert list(b) == [0, 1, 2, 1]
    assert min_cost(b, 4) == 4
    assert [list(x.blocks(b)) for x in enumerate_lifts(b, 4, 4, headroom=0)] == [[0, 0, 0, 4]]
    row = sv.solve(rz.Instance.of_edges(WALK_A), 4)
    assert row.opt == 2 and row.edges == [(1, 3), (1, 4)]
    assert rz.brute_force(WALK_A, (), 4) == 2


def test_second_walkthrough():
    inst = rz.Instance.of_edges(WALK_B)
    assert list(inst.blocks) == [0, 3, 1, 4, 0, 1, 1] and min_cost(inst.blocks, 2) == 2
    lifts = list(enumerate_lifts(inst.blocks, 2, 2, headroom=0))
    assert sorted(list(x.blocks(inst.blocks)) for x in lifts) == [[0, 2, 2, 4, 0, 0, 2], [0, 3, 0, 5, 0, 0, 2]]
    kept = [x for x in lifts if fe.graph_eg_test(inst.blocks, x.x, inst.members, inst.adjacent)]
    assert [list(x.blocks(inst.blocks)) for x in kept] == [[0, 3, 0, 5, 0, 0, 2]]
    assert all(fe.eg_test_blocks(fe.demand_histogram(inst.blocks, x.x)) for x in lifts)
    row = sv.solve(inst, 2)
    assert row.opt == 1 and row.edges == [(4, 6)]
    assert rz.verify(WALK_B, (), row.edges, 2, kept[0].blocks(inst.blocks))


@pytest.mark.parametrize("p", [1, 2, 3])
def test_alternating_pattern(p):
    b = [0] + [3, 1] * p + [3]
    assert min_cost(b, 2) == p and count_lifts(b, 2, p, headroom=0) == 2**p
    left, x, log = reduce_pattern(b, 2)
    assert x.sum() == p and min_cost(left, 2) == 0 and len(log) == p


def test_pattern_414():
    b = [0, 4, 1, 4]
    assert sorted(list(x.blocks(b)) for x in enumerate_lifts(b, 2, 1, headroom=0)) == [[0, 3, 2, 4], [0, 4, 0, 5]]


def test_beyond_minimum_needs_complete_span():
    b = [0, 5, 1, 1]
    c = min_cost(b, 2) + 2
    full = {tuple(x.blocks(b)) for x in enumerate_lifts(b, 2, c, "complete", headroom=0)}
    assert (0, 3, 2, 2) in full
    assert (0, 3, 2, 2) not in {tuple(x.blocks(b)) for x in enumerate_lifts(b, 2, c, "narrow")}


def test_minimum_agrees_across_methods():
    rng = random.Random(3)
    for _ in range(300):
        k = rng.choice([2, 3, 4])
        b = random_blocks(rng, rng.randint(2, 8), 9)
        if sum(b) < k:
            continue
        want = section_cost(degrees_of(b), k)
        assert min_cost(b, k) == min_cost_by_segments(b, k) == want == min_lift(b, k).cost
        assert min_cost(b, k, headroom=2) == want
        x = min_lift(b, k)
        assert is_crowded(x.blocks(b), k) and dominates(x.blocks(b), b)
        assert lift_exists(b, k, want) and lift_exists(b, k, want, "narrow")
        assert not any(lift_exists(b, k, c) for c in range(want))


def test_enumeration_against_plain_recursion():
    rng = random.Random(5)
    for _ in range(60):
        k = rng.choice([2, 3])
        b = random_blocks(rng, 4, 4)
        if sum(b) < k:
            continue
        for c in range(min_cost(b, k), min_cost(b, k) + 4):
            want = sorted(all_lifts(b, k, c, c // k))
            got = [x.x for x in enumerate_lifts(b, k, c)]
            assert len(set(got)) == len(got) and sorted(got) == want
            assert count_lifts(b, k, c) == len(want) and lift_exists(b, k, c) == bool(want)
            narrow = [x.x for x in enumerate_lifts(b, k, c, "narrow")]
            assert count_lifts(b, k, c, "narrow") == len(narrow)
            assert {(*x, *[0] * (c // k)) for x in narrow} <= set(got)


def test_lifts_to_a_distant_hub_take_little_memory():
    """What is held follows the lifts that can be, not blocks times cost."""
    import tracemalloc

    b = [0, 40_000, 900, 30, *[0] * 800, 1]
    inst, cost = rz.Instance(np.array(b), {}, {}), min_cost(b, 5)
    tracemalloc.start()
    try:
        lifts = list(enumerate_lifts(b, 5, cost, limit=5))
        step = sv.realizable_lower_bound(inst, 5, test="eg", climb="step", work=40)
        assert tracemalloc.get_traced_memory()[1] < 15e6
    finally:
        tracemalloc.stop()
    assert cost > 3000 and lifts and all(x.cost == cost and is_crowded(x.blocks(b), 5) for x in lifts)
    assert step.lower_edges >= (cost + 1) // 2


def test_tables_go_when_the_work_runs_out(monkeypatch):
    """Not only once cycles are looked for."""
    import gc
    import weakref

    from crowding.core import lifting

    made = []

    class Walk(lifting._Walk):
        def __init__(self, *a):
            super().__init__(*a)
            made.append(weakref.ref(self))

    monkeypatch.setattr(lifting, "_Walk", Walk)
    gc.disable()
    try:
        with pytest.raises(TimeoutError):
            list(enumerate_lifts([0, 9, 9, 5, 0, 0, 1], 3, 20, over=lambda: True))
        left = [w() for w in made]
    finally:
        gc.enable()
    assert left == [None]


def test_section_cuts_repeat_lifts():
    d = [1] * 9 + [3]
    cuts = list(section_cuts(d, 2))
    assert len(cuts) > len(set(cuts)) == 1


def test_raise_cost_is_crossing_price():
    assert raise_cost([0, 3, 1, 4], 2, 3) == 1 + 2 + 2
    assert list(crossings([0, 3, 1], [0, 2, 2])) == [0, 1, 0]


def test_eg_cases():
    assert not fe.eg_test([3, 3, 1, 1]) and fe.eg_test([2, 2, 2]) and not fe.eg_test([1, 1, 1]) and fe.eg_test([])


def test_eg_by_blocks_and_waste():
    rng = random.Random(7)
    for _ in range(3000):
        d = [rng.randint(0, 6) for _ in range(rng.randint(0, 9))]
        h = {v: d.count(v) for v in set(d) if v}
        assert fe.eg_test(d) == fe.eg_test_blocks(h)
        w = fe.waste_needed(h)
        assert fe.eg_test(d + [1] * w)
        assert not any(fe.eg_test(d + [1] * v) for v in range(w))


def random_graph(rng, n):
    p = rng.random()
    return [e for e in combinations(range(n), 2) if rng.random() < p]


def test_bounds_sandwich_brute_force():
    rng = random.Random(11)
    for _ in range(120):
        n, k = rng.randint(4, 7), rng.choice([2, 3])
        edges = random_graph(rng, n)
        inst = rz.Instance.of_edges(edges, range(n))
        best = rz.brute_force(edges, range(n), k)
        lo = {t: sv.realizable_lower_bound(inst, k, test=t, work=None) for t in ("none", "eg", "graph_eg")}
        assert lo["none"].lower_edges <= lo["eg"].lower_edges <= lo["graph_eg"].lower_edges <= best
        up = sv.upper_bound(inst, k, lo["graph_eg"].passing)
        if up:
            assert best <= len(up.edges) <= sv.complete_bound(n, len(edges))
            assert rz.verify(edges, range(n), up.edges, k)
        for base in (sv.cluster_baseline(inst, k), sv.two_phase_baseline(inst, k)):
            if base is not None:
                assert len(base) >= best and rz.verify(edges, range(n), base, k)


def test_refusals_of_the_graph_aware_test_are_right():
    rng = random.Random(13)
    refused = 0
    for _ in range(150):
        edges = random_graph(rng, 6)
        inst = rz.Instance.of_edges(edges, range(6))
        c = min_cost(inst.blocks, 2)
        for cost in range(c + c % 2, c + 5, 2):
            for x in enumerate_lifts(inst.blocks, 2, cost):
                if not fe.graph_eg_test(inst.blocks, x.x, inst.members, inst.adjacent):
                    refused += 1
                    assert not rz.realizable_exact(inst, x.x)
    assert refused > 100


def test_reduction_keeps_minimum_and_mostly_the_plain_bound():
    rng = random.Random(17)
    used = same = 0
    for _ in range(300):
        k = rng.choice([2, 3])
        b = [0] + [rng.choice([0, 1, 2, k - 1, 2 * k, 3 * k]) for _ in range(7)] + [2 * k]
        left, x, log = reduce_pattern(b, k)
        assert min_cost(left, k) + x.sum() == min_cost(b, k)
        assert list(lifted(b, x)) == list(left)
        if log and sum(b) < 25:
            used += 1
            inst = rz.Instance(np.array(b), {}, {})
            a, z = (sv.realizable_lower_bound(inst, k, test="eg", reduce=r, climb="step", work=20_000) for r in (False, True))
            if a.status == z.status == "ok":
                # fewer lifts are left above the minimum, so the reduced bound may only be higher
                assert a.lower_edges <= z.lower_edges
                same += a.lower_edges == z.lower_edges
    assert used > 10 and same >= 0.8 * used


def test_hardness_gadget():
    cube = [(a, b) for a, b in combinations(range(8), 2) if (a ^ b).bit_count() == 1]
    inst = rz.Instance.of_edges(cube)

    def target(s):
        return crossings(inst.blocks, [0, 0, 0, 8 - s, *[0] * (s - 2), s])

    assert rz.realizable_exact(inst, target(4)) and rz.realize(inst, tuple(target(4)), variants=[("fifo", "least_conflict")]) is not None
    assert not rz.realizable_exact(inst, target(5))


def test_exchange_against_exact_factor():
    rng = random.Random(19)
    hit = possible = 0
    for _ in range(200):
        inst = rz.Instance.of_edges(random_graph(rng, 8), range(8))
        dem = {v: rng.randint(0, 3) for v in range(8)}
        exact = rz.exact_factor(dem, inst.adjacent)
        got = rz.local_exchange(dem, inst.adjacent)
        if exact is None:
            assert got is None
        else:
            possible += 1
            hit += got is not None
    assert hit >= 0.8 * possible


def test_edges_of_the_domain():
    none = rz.Instance.of_edges([], range(4))
    assert sv.solve(none, 3).oh == 0
    full = rz.Instance.of_edges(list(combinations(range(5), 2)))
    assert sv.solve(full, 5).opt == 0
    with pytest.raises(ValueError):
        min_cost([0, 1, 2], 4)
    assert min_cost([0], 2) == 0
    assert sv.solve(rz.Instance.of_edges(WALK_A), 1).opt == 0
    assert rz.guaranteed_large(1, 24) and not rz.guaranteed_large(1, 23)


def test_jump_is_the_first_passing_cost():
    """Cores and their waste against testing every lift of every cost."""
    rng = random.Random(23)
    met = 0
    for _ in range(250):
        k = rng.choice([2, 3])
        b = [rng.choice([0, 0, 1, 1, 2, 3, 5, 8]) for _ in range(rng.randint(3, 7))] + [rng.randint(1, 3)]
        if sum(b) < k or min_cost(b, k) > 12:
            continue
        first = min_lift(b, k)
        most = first.cost + fe.waste_needed(fe.demand_histogram(b, first.x))
        got = jump.passing_cost(b, k, most)
        for core in got.cores:
            assert sum(core.x) == core.cost and is_crowded(lifted(b, core.x), k) and fe.demand_histogram(b, core.x) == core.histogram()
        step = next((c for c in range(first.cost, got.cost + 5) for x in enumerate_lifts(b, k, c) if fe.eg_test_blocks(fe.demand_histogram(b, x.x))), None)
        assert step is None or got.cost <= step
        met += got.cost == step
        assert jump.passing_cost(b, k, most, beam=1).cost <= got.cost  # merged states only weaken the bound
    assert met > 150


def test_bounds_on_many_small_graphs():
    """No bound above the optimum, no false optimum, every solution valid, every baseline ends."""
    rng = random.Random(29)
    optimal = 0
    for _ in range(1000):
        n, k = rng.randint(4, 7), rng.choice([2, 2, 3, 4])
        edges = random_graph(rng, n)
        r = sv.solve(rz.Instance.of_edges(edges, range(n)), k)
        best = rz.brute_force(edges, range(n), k)
        assert r.dp_lo <= best <= r.oh and best <= r.ch and r.opt in (None, best)
        assert r.verified and rz.verify(edges, range(n), r.edges, k)
        optimal += r.opt is not None
    assert optimal > 900


def test_equal_calls_give_equal_rows():
    rng = random.Random(31)
    edges = [e for e in combinations(range(60), 2) if rng.random() < 0.08]
    inst = rz.Instance.of_edges(edges, range(60))
    for work in (5, 50, 500):
        a, b = (sv.solve(inst, 4, work) for _ in range(2))
        assert [getattr(a, c) for c in ("ch", "oh", "opt", "dp_lo", "dp_hi", "status", "edges")] == [getattr(b, c) for c in ("ch", "oh", "opt", "dp_lo", "dp_hi", "status", "edges")]


def test_more_work_never_loosens_bounds():
    rng = random.Random(37)
    for _ in range(10):
        edges = [e for e in combinations(range(40), 2) if rng.random() < 0.4]
        inst = rz.Instance.of_edges(edges, range(40))
        low = [sv.realizable_lower_bound(inst, 5, work=w).lower_edges for w in (1, 10, 100, 1000)]
        assert low == sorted(low)


def test_clustering_ends_and_is_crowded():
    rng = random.Random(41)
    for n, p in ((80, 0.05), (120, 0.3), (60, 0.8)):
        edges = [e for e in combinations(range(n), 2) if rng.random() < p]
        inst = rz.Instance.of_edges(edges, range(n))
        for k in (2, 3, 5, 10, 20, n):
            got = sv.cluster_baseline(inst, k)
            assert got is not None and rz.verify(edges, range(n), got, k)


def test_small_left_blocks_are_reduced_only_if_the_cost_stays():
    rng = random.Random(43)
    small = 0
    for _ in range(400):
        k = rng.choice([3, 4, 5])
        b = [0] + [rng.choice([0, 1, k - 1, k, k + 1, 2 * k]) for _ in range(8)] + [3 * k]
        left, x, log = reduce_pattern(b, k)
        assert min_cost(left, k) + x.sum() == min_cost(b, k) and list(lifted(b, x)) == list(left)
        small += any(b[i] < 2 * k - 1 for i, _ in log)
    assert small > 20


def test_realize_sequence():
    inst = rz.Instance.of_edges(WALK_B)
    assert rz.realize_sequence(inst, [0, 3, 0, 5, 0, 0, 2])[0] == {(4, 6)}
    assert rz.realize_sequence(inst, [0, 4, 0, 4, 0, 1, 1]) is None  # it does not dominate
    with pytest.raises(ValueError):
        rz.realize_sequence(inst, [0, 3, 0, 5])


def test_refused_ways_to_waste_are_work(monkeypatch):
    """Where no two neighbouring blocks take the waste, every other way is tested, and each test is work."""
    inst, seen = rz.Instance.of_edges([(0, i) for i in range(1, 6)] + [(1, 2)]), []

    def refused(b, x, k, units, over):
        for i in range(5_000):
            seen.append(i)
            yield (0, 0, 0, 0, 0, 7)
        raise AssertionError("more ways were tested than there is work")

    monkeypatch.setattr(rz, "waste_spread", lambda *a, **kw: iter(()))
    monkeypatch.setattr(rz, "waste_dp", refused)
    monkeypatch.setattr(fe, "demand_histogram", lambda b, x: {})
    monkeypatch.setattr(fe, "eg_test_blocks", lambda hist: False)
    assert sv.upper_bound(inst, 2, [min_lift(inst.blocks, 2)], work=200) is None
    assert 100 <= len(seen) <= 200


def test_baseline_goes_through_levels_once_a_vertex(monkeypatch):
    """A hub far above the others makes few vertices ask for many edges: levels are put in order for each of these, not for each edge."""
    from crowding.core import realization as rz
    from crowding.core import solve as sv

    inst = rz.Instance.of_edges({(0, v) for v in range(1, 400)} | {(400 + 2 * i, 401 + 2 * i) for i in range(600)}, range(1600))
    calls = [0]

    def counted(*args, **named):
        calls[0] += 1
        return sorted(*args, **named)

    monkeypatch.setattr(sv, "sorted", counted, raising=False)
    got = sv.cluster_baseline(inst, 5)
    assert got is not None and sv.solves(inst, got, 5) and calls[0] < len(got) // 2
