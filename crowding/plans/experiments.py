"""The experiments: result table, random family, size against n, ablations, k sweep.

Grids are parameters and by default the whole ones: 13 values of k, all graphs, 170 random graphs. work is the budget of a
phase of one instance (see core.solve); seconds, unset by default, is a time limit as the reference has one.
"""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.core import solve as sv
from crowding.core.lifting import count_lifts, enumerate_lifts, min_cost, min_cost_by_segments, reduce_pattern, section_cost
from crowding.core.realization import VARIANTS, passing, realize
from crowding.plans import measures as ms
from crowding.plans.solver import GRID, Prepared, collect_blocks, instance, solve_graphs
from crowding.plans.workloads import GRAPHS, graph_of, grow_family

#: The graphs that stand for the published ones.
TABLE = ("parts", "cust_supp", "part_supp", "users_minute", "doc_lines", "page_links", "cust_day")
SIZES = range(400, 34_001, 400)


def table1(spark: SparkSession, sf: str, graphs=TABLE, ks=GRID, work: float | None = sv.WORK, seconds: float | None = None) -> DataFrame:
    """One line per graph and k: sizes, bounds, times."""
    return ms.table_lines(solve_graphs(spark, {n: graph_of(spark, sf, n) for n in graphs}, ks, work, seconds))


def random_family(spark: SparkSession, m0s=(3, 5), ts=SIZES, ks=(2, 3, 10), seed: int = 7, work: float | None = sv.WORK, seconds: float | None = None) -> DataFrame:
    """Bounds on preferential-attachment graphs, 170 by default."""
    return ms.table_lines(solve_graphs(spark, grow_family(spark, [(m, t) for m in m0s for t in ts], seed), ks, work, seconds))


def fig3(family: DataFrame, ks=(2, 3)) -> DataFrame:
    return ms.regression(family.filter(F.col("k").isin(list(ks))))


def upper_bound_share(spark: SparkSession, m0s=(3, 5), ts=SIZES, ks=(30, 150), seed: int = 7, work: float | None = sv.WORK) -> DataFrame:
    """(k, bounded): share of random graphs with a solution of the heuristic's own (not the baseline's) within the budget."""
    b = solve_graphs(spark, grow_family(spark, [(m, t) for m in m0s for t in ts], seed), ks, work)
    own = (F.col("oh").isNotNull() & ~F.col("variant").isin("near", "clusters")).cast("double")
    return b.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.avg(own).alias("bounded"))


def k_sweep(spark: SparkSession, sf: str, graph: str = "parts", ks=GRID) -> DataFrame:
    """Minimum cost, edges at least, and number of cheapest lifts against k, from the blocks alone."""
    from crowding.operators import graph as g

    b = collect_blocks(g.block_sequence(g.degrees(GRAPHS[graph](spark, sf))))[graph]
    rows = []
    for k in ks:
        if k <= b.sum():
            c = min_cost(b, k)
            rows.append((graph, k, c, (c + 1) // 2, float(count_lifts(b, k, c, "narrow"))))
    return spark.createDataFrame(rows, "graph string, k int, cost_deg long, lower_edges long, n_lifts double")


def ablation_tests(spark: SparkSession, sf: str, graph: str = "users_minute", ks=GRID, work: float | None = sv.WORK) -> DataFrame:
    """Lower bounds with no test, the plain one and the graph-aware one, with and without the pattern rule, climbing by
    cores and step by step."""
    inst = instance(GRAPHS[graph](spark, sf), graph, max(ks))
    shared = spark.sparkContext.broadcast(inst)  # bounded by instance()

    def run(parts):
        for part in parts:
            rows = []
            for k, test, reduce, climb in zip(part["k"], part["test"], part["reduce"], part["climb"]):
                t = time.monotonic()
                b = sv.realizable_lower_bound(shared.value, int(k), test=test, reduce=bool(reduce), climb=climb, work=work)
                rows.append((graph, k, test, bool(reduce), climb, b.min_cost, b.lower_edges, b.refuted, b.status, time.monotonic() - t))
            yield pd.DataFrame(rows, columns=["graph", "k", "test", "reduce", "climb", "min_cost", "lower_edges", "refuted", "status", "seconds"])

    jobs = [(k, test, reduce, climb) for k in ks if k <= inst.n for test in ("none", "eg", "graph_eg") for reduce, climb in ((False, "jump"), (False, "step"), (True, "step"))]
    df = spark.createDataFrame(jobs, "k int, test string, reduce boolean, climb string").repartition(len(jobs), "k", "test", "reduce", "climb")
    return df.mapInPandas(run, "graph string, k int, test string, reduce boolean, climb string, min_cost long, lower_edges long, refuted long, status string, seconds double")


def gain_of_test(ablation: DataFrame) -> DataFrame:
    """(graph, k, gain): edges by which the graph-aware test raises the bound over the plain one."""
    full = ablation.filter("not reduce and climb = 'jump'")
    of = lambda t: F.max(F.when(F.col("test") == t, F.col("lower_edges")))
    return full.groupBy("graph", "k").agg((of("graph_eg") - of("eg")).alias("gain"))


def ablation_dp(spark: SparkSession, sf: str, graph: str = "parts", ks=(2, 3, 5, 10, 20, 50)) -> DataFrame:
    """Section, block and segmented programs and the pattern rule: costs, cells they visit, seconds."""
    from crowding.operators import graph as g

    b = collect_blocks(g.block_sequence(g.degrees(GRAPHS[graph](spark, sf))))[graph]
    d = [i for i, n in enumerate(b) for _ in range(int(n))]
    rows = []
    for k in ks:
        width = int(min(2 * k, b.sum() + 1))
        sections = sum(min(j - k, k - 1) + 1 for j in range(k, len(d) + 1))
        left, x, _ = reduce_pattern(b, k)
        # of a reduced sequence only stretches with blocks that are neither empty nor full need the program again
        live = sum(1 for n in left if 0 < n < k)
        for name, f, cells in (
            ("sections", lambda: section_cost(d, k), sections), ("blocks", lambda: min_cost(b, k), len(b) * width),
            ("segments", lambda: min_cost_by_segments(b, k), len(b) * width), ("rule", lambda: min_cost(left, k) + int(x.sum()), live * width),
        ):
            t = time.monotonic()
            cost = f()
            rows.append((graph, k, name, int(cost), cells, time.monotonic() - t))
    return spark.createDataFrame(rows, "graph string, k int, method string, cost_deg long, cells long, seconds double")


def speed_up(ablation: DataFrame) -> DataFrame:
    """(graph, k, by_cells, by_time): the section program over the block program."""
    of = lambda m, c: F.max(F.when(F.col("method") == m, F.col(c)))
    return ablation.groupBy("graph", "k").agg((of("sections", "cells") / of("blocks", "cells")).alias("by_cells"), (of("sections", "seconds") / F.greatest(of("blocks", "seconds"), F.lit(1e-6))).alias("by_time"))


def phase2_success(spark: SparkSession, sf: str, graph: str = "users_minute", ks=(2, 3, 5, 10), work: float = 300) -> DataFrame:
    """How often each mapping variant realizes a passing lift of least cost; of all of them, or as many as the work allows."""
    inst = instance(graph_of(spark, sf, graph), graph, max(ks), whole=True)
    shared = spark.sparkContext.broadcast(inst)  # candidates, and edges or groups of these

    def run(parts):
        for part in parts:
            for k in part["k"]:
                inst, meter = shared.value, sv.Meter(work)
                c = min_cost(inst.blocks, int(k))
                c += c % 2
                rows = {v: [0, 0] for v in VARIANTS}
                for x in enumerate_lifts(inst.blocks, int(k), c):
                    if not meter.spend():
                        break
                    if passing(x, inst.blocks):
                        for v in VARIANTS:
                            meter.spend(1 + c / 50)
                            rows[v][0] += 1
                            rows[v][1] += realize(inst, x.x, [v]) is not None
                yield pd.DataFrame([(graph, int(k), "+".join(v), n, hit) for v, (n, hit) in rows.items()], columns=["graph", "k", "variant", "lifts", "realized"])

    return spark.createDataFrame([(k,) for k in ks], "k int").repartition(len(ks), "k").mapInPandas(run, "graph string, k int, variant string, lifts long, realized long")


def baselines(spark: SparkSession, sf: str, kind: str, graphs=TABLE, ks=GRID) -> DataFrame:
    """(graph, k, edges) of a baseline, cluster or two_phase; edges is null where it gets stuck."""
    from crowding.plans.solver import instances, settle

    ready = Prepared({n: GRAPHS[n](spark, sf) for n in graphs}, max(ks))
    f = sv.cluster_baseline if kind == "cluster" else sv.two_phase_baseline

    def run(parts):
        for name, k, inst in instances(parts):
            got = f(inst, k)
            yield pd.DataFrame({"graph": [name], "k": [k], "edges": [None if got is None else [{"u": a, "v": b} for a, b in sorted(got)]]})

    jobs = [(name, k) for name, r in sorted(ready.sizes.items()) for k in ks if k <= r["n"]]
    plan = spark.createDataFrame(jobs, "graph string, k int")
    rows = settle(ready.packed([n for n in ready.sizes if ready.fits(n)]), "graph-packed").join(F.broadcast(plan), "graph").repartition(len(jobs), "graph", "k")
    return rows.mapInPandas(run, "graph string, k int, edges array<struct<u: long, v: long>>")
