"""Distributed rounds for what does not fit one task: component labels, and realization of many demands."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from crowding.core.realization import local_exchange
from crowding.sources.store import settle


def min_labels(edges: DataFrame) -> DataFrame:
    """(graph, v, label): the smallest vertex of each component; labels and their labels are taken by turns."""
    both = settle(edges.select("graph", "u", "v").unionByName(edges.select("graph", F.col("v").alias("u"), F.col("u").alias("v"))), "arcs")
    lab = settle(both.groupBy("graph", F.col("u").alias("v")).agg(F.least(F.min("v"), F.first("u")).alias("label")), "labels")
    while True:
        near = both.join(lab.select("graph", F.col("v"), "label"), ["graph", "v"]).groupBy("graph", F.col("u").alias("v")).agg(F.min("label").alias("near"))
        new = lab.join(near, ["graph", "v"]).select("graph", "v", F.least("label", "near").alias("label"))
        jump = new.select("graph", F.col("v").alias("label"), F.col("label").alias("far"))
        new = settle(new.join(jump, ["graph", "label"]).select("graph", "v", F.least("label", "far").alias("label")), "labels")
        moved = new.agg(F.sum("label")).first()[0] != lab.agg(F.sum("label")).first()[0]
        lab = new
        if not moved:
            return lab


def exchange_rounds(edges: DataFrame, demands: DataFrame, seed: int = 1, rounds: int = 60) -> tuple[DataFrame, DataFrame]:
    """(inserts(u, v), left(v, demand)): demands met by rounds of random pairing, stuck ones by exchanges.

    A round lines up the open units of all vertices in a hash order within buckets, proposes neighbours in that
    line, drops loops, old edges and repeats, and keeps as many of each vertex's proposals as it has units, on
    both ends. When pairing stands still, each stuck pair (u, w) takes an inserted edge {a, b} with {u, a} and
    {w, b} free in its place, an edge and a pair at most once a round.
    """
    spark = demands.sparkSession
    left = settle(demands.filter("demand > 0").select("v", F.col("demand").cast("int").alias("demand")), "demands")
    # only demanders are ever paired, also by exchanges, so the graph is looked through once
    ends = left.select(F.col("v").alias("u"))
    old = settle(edges.select("u", "v").join(ends, "u", "left_semi").join(left.select("v"), "v", "left_semi").select("u", "v"), "old")
    done = spark.createDataFrame([], "u long, v long")
    still = 0
    for r in range(rounds):
        total = left.agg(F.coalesce(F.sum("demand"), F.lit(0))).first()[0]
        if not total:
            break
        if still < 2:
            new = settle(_propose(left, old, done, seed + r), "pairs")
            gone = None
        else:
            new, gone = _swap(left, old, done, seed + r)
        n = new.count()
        if not n:
            still += 1
            if still > 6:
                break
            continue
        still = 0 if gone is None else 2
        kept = done if gone is None else done.join(gone, ["u", "v"], "left_anti")
        done = settle(kept.unionByName(new), "inserts")
        used = new.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("used"))
        if gone is not None:
            back = gone.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg((-F.count(F.lit(1))).alias("used"))
            used = used.unionByName(back).groupBy("v").agg(F.sum("used").alias("used"))
        left = settle(left.join(used, "v", "left").select("v", (F.col("demand") - F.coalesce("used", F.lit(0))).cast("int").alias("demand")).filter("demand > 0"), "demands")
    return done, left


def met_in_one_task(edges: DataFrame, demands: DataFrame) -> DataFrame:
    """inserts(u, v) that meet the demands, by local exchange on the demanders and the edges among them, which is all that
    takes part; empty if it does not succeed. Both are counted by the caller."""
    spark = demands.sparkSession
    ends = demands.select(F.col("v").alias("u"))
    inner = edges.select("u", "v").join(ends, "u", "left_semi").join(demands.select("v"), "v", "left_semi")
    asked = demands.agg(F.sort_array(F.collect_list(F.struct("v", "demand"))).alias("asked"))
    there = inner.agg(F.sort_array(F.collect_list(F.struct("u", "v"))).alias("there"))

    def run(parts):
        for part in parts:
            for asked, there in zip(part["asked"], part["there"]):
                dem = {int(r["v"]): int(r["demand"]) for r in asked}
                adjacent: dict[int, set[int]] = {v: set() for v in dem}
                for r in there:
                    adjacent[r["u"]].add(r["v"])
                    adjacent[r["v"]].add(r["u"])
                yield pd.DataFrame(sorted(local_exchange(dem, adjacent) or ()), columns=["u", "v"]).astype("int64")

    return settle(asked.crossJoin(there).mapInPandas(run, "u long, v long"), "inserts") if demands.limit(1).count() else spark.createDataFrame([], "u long, v long")


def realize_demands(edges: DataFrame, demands: DataFrame, most: int = 1_000_000) -> DataFrame | None:
    """inserts(u, v) that meet the demands exactly, or None: in one task if demanders and edges among them are no more
    than `most`, by exchange_rounds() otherwise or if that fails."""
    demands = settle(demands.filter("demand > 0"), "demands")
    total = demands.agg(F.coalesce(F.sum("demand"), F.lit(0))).first()[0]
    if total % 2:
        return None
    ends = demands.select(F.col("v").alias("u"))
    if total <= most and edges.select("u", "v").join(ends, "u", "left_semi").join(demands.select("v"), "v", "left_semi").limit(most + 1).count() <= most:
        done = met_in_one_task(edges, demands)
        if 2 * done.count() == total:
            return done
    done, left = exchange_rounds(edges, demands)
    return done if left.limit(1).count() == 0 else None


def _fresh(pairs: DataFrame, old: DataFrame, done: DataFrame) -> DataFrame:
    pairs = pairs.filter("u < v")
    return pairs.join(old, ["u", "v"], "left_anti").join(done, ["u", "v"], "left_anti")


def _quota(pairs: DataFrame, left: DataFrame, seed: int) -> DataFrame:
    """As many pairs as both ends have units for, in a hash order."""
    h = F.xxhash64(F.lit(seed), "u", "v")
    ends = pairs.select("u", "v", F.explode(F.array("u", "v")).alias("end"))
    ranked = ends.join(left.select(F.col("v").alias("end"), "demand"), "end").withColumn("r", F.row_number().over(W.partitionBy("end").orderBy(h, "u", "v")))
    return ranked.filter(F.col("r") <= F.col("demand")).groupBy("u", "v").count().filter("count = 2").select("u", "v")


def _propose(left: DataFrame, old: DataFrame, done: DataFrame, seed: int) -> DataFrame:
    units = left.withColumn("i", F.explode(F.sequence(F.lit(1), F.col("demand"))))
    buckets = max(1, int(left.agg(F.sum("demand")).first()[0]) // 200_000)
    line = units.withColumn("bucket", F.pmod(F.xxhash64(F.lit(seed), "v"), F.lit(buckets))).withColumn("h", F.xxhash64(F.lit(seed + 77), "v", "i"))
    w = W.partitionBy("bucket").orderBy("h", "v")
    nexts = F.array(*[F.lead("v", j).over(w) for j in range(1, 7)])
    pairs = line.select("v", nexts.alias("nexts")).select("v", F.explode("nexts").alias("next")).filter("next is not null and next <> v")
    pairs = pairs.select(F.least("v", "next").alias("u"), F.greatest("v", "next").alias("v")).distinct()
    return _quota(_fresh(pairs, old, done), left, seed)


def _swap(left: DataFrame, old: DataFrame, done: DataFrame, seed: int) -> tuple[DataFrame, DataFrame]:
    """(added, removed): stuck units pair up in a hash order within buckets, and each pair meets some inserted edges, as
    many as share its slot."""
    total, many = left.agg(F.sum("demand")).first()[0], done.count()
    units = left.withColumn("i", F.explode(F.sequence(F.lit(1), F.col("demand"))))
    units = units.withColumn("bucket", F.pmod(F.xxhash64(F.lit(seed), "v", "i"), F.lit(max(1, int(total) // 50_000))))
    one = W.partitionBy("bucket").orderBy(F.xxhash64(F.lit(seed + 5), "v", "i"), "v", "i")
    pairs = units.withColumn("n", F.row_number().over(one) - 1).groupBy("bucket", F.floor(F.col("n") / 2).alias("pair"))
    stuck = pairs.agg(F.min("v").alias("p"), F.max("v").alias("q"), F.count(F.lit(1)).alias("c")).filter("c = 2").withColumn("pair", F.xxhash64("bucket", "pair")).drop("bucket")
    slots = F.lit(max(1, many // 64))
    edges = done.withColumn("slot", F.pmod(F.xxhash64(F.lit(seed), "u", "v"), slots))
    met = stuck.withColumn("slot", F.pmod(F.xxhash64(F.lit(seed + 9), "pair"), slots)).join(edges, "slot")
    turn = met.select("pair", "p", "q", F.col("u").alias("a"), F.col("v").alias("b")).unionByName(met.select("pair", "p", "q", F.col("v").alias("a"), F.col("u").alias("b")))
    turn = turn.filter("p <> a and q <> b and p <> b and q <> a")
    for x, y in (("p", "a"), ("q", "b")):
        for e in (old, done):
            taken = e.select(F.col("u").alias("eu"), F.col("v").alias("ev"))
            turn = turn.join(taken, (F.least(x, y) == F.col("eu")) & (F.greatest(x, y) == F.col("ev")), "left_anti")
    lo, hi = F.least("a", "b"), F.greatest("a", "b")
    # one exchange a pair, an edge and a vertex, so that exchanges of a round don't touch each other
    turn = turn.withColumn("h", F.xxhash64(F.lit(seed), "pair", "a", "b"))
    turn = turn.withColumn("r", F.row_number().over(W.partitionBy("pair").orderBy("h"))).filter("r = 1").drop("r")
    turn = settle(turn, "exchanges")
    ends = turn.select("pair", "h", F.explode(F.array("p", "q", "a", "b")).alias("x")).distinct()
    first = ends.groupBy("x").agg(F.min(F.struct("h", "pair")).alias("m"))
    calm = ends.join(first, "x").groupBy("pair").agg(F.bool_and(F.col("m")["pair"] == F.col("pair")).alias("calm")).filter("calm").select("pair")
    turn = settle(turn.join(calm, "pair", "left_semi"), "exchanges")
    added = turn.select(F.inline(F.array(F.struct(F.least("p", "a").alias("u"), F.greatest("p", "a").alias("v")), F.struct(F.least("q", "b").alias("u"), F.greatest("q", "b").alias("v")))))
    return settle(added, "pairs"), turn.select(lo.alias("u"), hi.alias("v"))
