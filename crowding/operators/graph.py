"""Graph and block primitives over edges(graph, u, v), u < v, as DataFrame plans."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from crowding.sources.store import settle


def canonical_edges(pairs: DataFrame, src: str = "u", dst: str = "v", graph: str | Column = "g") -> DataFrame:
    """Any pair list as a simple undirected graph: no loops, nulls or repeats, ends in order."""
    name = F.lit(graph) if isinstance(graph, str) else graph
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    return pairs.select(name.alias("graph"), F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).filter((a.isNotNull()) & (b.isNotNull()) & (F.col("u") < F.col("v"))).distinct()


def degrees(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(graph, v, degree) in one scan; with vertices(graph, v), isolated ones have degree 0."""
    ends = edges.select("graph", F.explode(F.array("u", "v")).alias("v"))
    deg = ends.groupBy("graph", "v").agg(F.count(F.lit(1)).cast("int").alias("degree"))
    if vertices is None:
        return deg
    return vertices.select("graph", "v").distinct().join(deg, ["graph", "v"], "left").fillna({"degree": 0})


def block_sequence(deg: DataFrame) -> DataFrame:
    """(graph, degree, size), non-empty blocks only."""
    return deg.groupBy("graph", "degree").agg(F.count(F.lit(1)).alias("size"))


def dense_blocks(blocks: DataFrame) -> DataFrame:
    """Blocks 0 to the maximum degree, empty ones included."""
    grid = blocks.groupBy("graph").agg(F.max("degree").alias("top")).select("graph", F.explode(F.sequence(F.lit(0), F.col("top"))).alias("degree"))
    return grid.join(blocks, ["graph", "degree"], "left").fillna({"size": 0})


def graph_summary(deg: DataFrame) -> DataFrame:
    """graph, n, m, max_degree, n_per_degree, density, distinct_degrees."""
    n, total = F.count(F.lit(1)), F.sum("degree")
    return deg.groupBy("graph").agg(
        n.alias("n"), (total / 2).cast("long").alias("m"), F.max("degree").alias("max_degree"), F.round(n / F.max("degree"), 6).alias("n_per_degree"),
        F.round(total / (n * (n - 1)), 9).alias("density"), F.count_distinct("degree").alias("distinct_degrees"),
    )


def crowd_level(blocks: DataFrame) -> DataFrame:
    """(graph, level): the largest k for which the graph is crowded."""
    return blocks.filter("size > 0").groupBy("graph").agg(F.min("size").alias("level"))


def is_crowded(blocks: DataFrame, k: int) -> DataFrame:
    return blocks.filter("size > 0").groupBy("graph").agg(F.bool_and(F.col("size") >= k).alias("crowded"))


def violations(blocks: DataFrame, k: int) -> DataFrame:
    """Blocks that are neither empty nor large enough."""
    return blocks.filter((F.col("size") > 0) & (F.col("size") < k))


def exposed_vertices(deg: DataFrame, k: int) -> DataFrame:
    """Vertices in such blocks. At most k - 1 of each degree: the block list is small, and broadcast by Spark if so."""
    return deg.join(violations(block_sequence(deg), k), ["graph", "degree"], "left_semi")


def add_edges(edges: DataFrame, inserts: DataFrame) -> DataFrame:
    """G + S; ValueError if S has a loop, a repeat or an edge of G."""
    bad = inserts.filter("u >= v").limit(1).count() + inserts.groupBy("graph", "u", "v").count().filter("count > 1").limit(1).count()
    bad += inserts.join(edges, ["graph", "u", "v"], "left_semi").limit(1).count()
    if bad:
        raise ValueError("the insertions hold a loop, a repeat or an existing edge")
    return edges.select("graph", "u", "v").unionByName(inserts.select("graph", "u", "v"))


def crossings(before: DataFrame, after: DataFrame) -> DataFrame:
    """(graph, degree, b_before, x, b_after) on the degrees of either: x counts positions that move above the degree."""
    both = before.withColumnRenamed("size", "b_before").join(after.withColumnRenamed("size", "b_after"), ["graph", "degree"], "full").fillna(0, ["b_before", "b_after"])
    above = W.partitionBy("graph").orderBy(F.desc("degree")).rowsBetween(W.unboundedPreceding, -1)
    x = F.coalesce(F.sum(F.col("b_after") - F.col("b_before")).over(above), F.lit(0))
    return both.select("graph", "degree", "b_before", x.cast("long").alias("x"), "b_after")


def dominance(cross: DataFrame) -> DataFrame:
    """(graph, dominates, cost_deg): the cost takes each crossing times the gap to the next degree listed."""
    gap = F.lead("degree").over(W.partitionBy("graph").orderBy("degree")) - F.col("degree")
    return cross.withColumn("gap", F.coalesce(gap, F.lit(0))).groupBy("graph").agg(F.bool_and((F.col("x") >= 0)).alias("dominates"), F.sum(F.col("x") * F.col("gap")).alias("cost_deg"))


def sorted_demands(before: DataFrame, after: DataFrame) -> DataFrame:
    """(graph, demand, n) of the matching in sorted order: runs of equal degree are cut at each other's ends.

    Ends of both runs, in falling order, each see the last run begun on either side, so a window over the blocks
    does what a join of intervals would.
    """

    def ends(b: DataFrame, mine: str, other: str) -> DataFrame:
        end = F.sum("size").over(W.partitionBy("graph").orderBy("degree").rowsBetween(W.unboundedPreceding, 0))
        return b.filter("size > 0").select("graph", end.alias("at"), F.col("degree").alias(mine), F.lit(None).cast("int").alias(other))

    both = ends(before, "low", "high").unionByName(ends(after, "high", "low"))
    cuts = both.groupBy("graph", "at").agg(F.max("low").alias("low"), F.max("high").alias("high"))
    down = W.partitionBy("graph").orderBy(F.desc("at"))
    seen = down.rowsBetween(W.unboundedPreceding, 0)
    run = cuts.select(
        "graph", F.last("low", ignorenulls=True).over(seen).alias("low"), F.last("high", ignorenulls=True).over(seen).alias("high"),
        (F.col("at") - F.coalesce(F.lead("at").over(down), F.lit(0))).alias("n"),
    )
    return run.groupBy("graph", (F.col("high") - F.col("low")).alias("demand")).agg(F.sum("n").cast("long").alias("n"))


def _eg_rows(hist: DataFrame, keys: list[str]) -> DataFrame:
    """keys, r, asked, rest of hist(keys, demand, n, r, asked), r being the number of vertices up to the row: the rest can
    give min(r, demand) each. Demands and the r asked for are sorted together, so one window has, for every r, how
    many demand r or more, and how much."""
    data = hist.select(*keys, F.col("demand").cast("long").alias("at"), F.lit(0).alias("kind"), F.col("n").cast("long").alias("n"), F.lit(None).cast("long").alias("r"), F.lit(None).cast("long").alias("asked"))
    asks = hist.select(*keys, F.col("r").cast("long").alias("at"), F.lit(1).alias("kind"), F.lit(0).cast("long").alias("n"), F.col("r").cast("long").alias("r"), F.col("asked").cast("long").alias("asked"))
    w = W.partitionBy(*keys).orderBy(F.desc("at"), "kind").rowsBetween(W.unboundedPreceding, 0)
    seen = data.unionByName(asks).select("*", F.sum("n").over(w).alias("many"), F.sum(F.col("n") * F.col("at")).over(w).alias("much"))
    total = hist.groupBy(*keys).agg(F.sum(F.col("demand") * F.col("n")).cast("long").alias("total"))
    rows = seen.filter("kind = 1").join(total, keys)
    rest = F.when(F.col("many") > F.col("r"), F.col("r") * (F.col("many") - F.col("r")) + F.col("total") - F.col("much")).otherwise(F.col("total") - F.col("asked"))
    return rows.select(*keys, "r", "asked", rest.alias("rest"))


def eg_positions(demands: DataFrame) -> DataFrame:
    """Per case and prefix length r: what the r largest demands ask and may get. demands(case_id, demand)."""
    by = W.partitionBy("case_id").orderBy(F.desc("demand"))
    pos = demands.filter("demand > 0").select("case_id", "demand", F.lit(1).alias("n"), F.row_number().over(by).alias("r"))
    pos = pos.withColumn("asked", F.sum("demand").over(W.partitionBy("case_id").orderBy("r").rowsBetween(W.unboundedPreceding, 0)))
    room = (F.col("r") * (F.col("r") - 1) + F.col("rest")).cast("long")
    return _eg_rows(pos, ["case_id"]).select("case_id", F.col("r").cast("int").alias("r"), "asked", room.alias("room"), (F.col("asked") <= room).alias("ok"))


def eg_verdict(demands: DataFrame) -> DataFrame:
    """(case_id, realizable) of demands(case_id, demand)."""
    even = demands.groupBy("case_id").agg((F.coalesce(F.sum("demand"), F.lit(0)) % 2 == 0).alias("even"))
    ok = eg_positions(demands).groupBy("case_id").agg(F.bool_and("ok").alias("ok"))
    return even.join(ok, "case_id", "left").select("case_id", (F.col("even") & F.coalesce("ok", F.lit(True))).alias("realizable"))


def eg_blocks(hist: DataFrame) -> DataFrame:
    """One check a distinct demand of hist(graph, demand, n): graph, demand, r, asked, room, ok."""
    by = W.partitionBy("graph").orderBy(F.desc("demand")).rowsBetween(W.unboundedPreceding, 0)
    h = hist.filter("demand > 0").select("graph", "demand", "n", F.sum("n").over(by).alias("r"), F.sum(F.col("demand") * F.col("n")).over(by).alias("asked"))
    room = (F.col("r") * (F.col("r") - 1) + F.col("rest")).cast("long")
    out = _eg_rows(h, ["graph"]).join(h.select("graph", "demand", "r"), ["graph", "r"])
    return out.select("graph", "demand", F.col("r").cast("long").alias("r"), "asked", room.alias("room"), (F.col("asked") <= room).alias("ok"))


def seq_to_blocks(sequences: DataFrame) -> DataFrame:
    """(graph, degree, size) of sequences(graph, degrees array)."""
    return block_sequence(sequences.select("graph", F.explode("degrees").alias("degree")))


def blocks_to_seq(blocks: DataFrame, most: int = 10_000_000) -> DataFrame:
    """(graph, degrees): the sorted sequence as an array; ValueError beyond `most` vertices, for which degrees() is the form."""
    if blocks.groupBy("graph").agg(F.sum("size").alias("n")).filter(F.col("n") > most).limit(1).count():
        raise ValueError(f"a sequence has more than {most} members")
    runs = F.sort_array(F.collect_list(F.struct("degree", "size")))
    return blocks.groupBy("graph").agg(F.flatten(F.transform(runs, lambda r: F.array_repeat(r["degree"], r["size"].cast("int")))).alias("degrees"))


def representatives(deg: DataFrame, most: int) -> DataFrame:
    """The first vertices of every block, by id: a constant rank bound, so Spark limits each group before its shuffle."""
    w = W.partitionBy("graph", "degree").orderBy("v")
    return deg.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= F.lit(most))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among the vertices: two semi-joins, edges scanned once and shuffled only if need be."""
    left = vertices.select("graph", F.col("v").alias("u"))
    return edges.join(left, ["graph", "u"], "left_semi").join(vertices.select("graph", "v"), ["graph", "v"], "left_semi").select("graph", "u", "v")


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))


def dense_for_products(edges: DataFrame | Groups) -> bool:
    """Whether products of blocks of the adjacency matrix take less than walking all paths of two edges; about 1,000 of a
    product's steps take as long as one row of a join, and 7,000 of a pass over a graph's groups, of which 64 vertices share one."""
    if isinstance(edges, Groups):
        met = edges.lists.select(F.explode("ms").alias("m"), (F.size("ms") - 1).alias("n")).groupBy("m").agg(F.count(F.lit(1)).alias("own"), F.sum("n").cast("double").alias("met"))
        n, rows, paths = met.agg(F.count(F.lit(1)), F.coalesce(F.sum("own"), F.lit(0)), F.coalesce(F.sum(F.col("met") * F.col("met")), F.lit(0.0))).first()
        return float(n) * rows <= 7000 * paths
    n, paths = degrees(edges.select(F.lit("g").alias("graph"), "u", "v")).agg(F.count(F.lit(1)), F.coalesce(F.sum(F.col("degree").cast("double") * F.col("degree")), F.lit(0.0))).first()
    return float(n) ** 3 < 1000 * paths


def neighbour_products(edges: DataFrame | Groups, pick, schema: str, block: int = 1024, columns: int = 4096, first: int | None = None) -> DataFrame:
    """What pick(u, v, shared, linked) gives for all pairs of vertices with common neighbours, u < v, each once: arrays of
    the pairs of two blocks of vertices, how many neighbours they share, and whether they are joined themselves. A task holds
    two blocks with their neighbours, and multiplies them over some columns at a time; counts are whole below 2^24.

    Of a graph told by groups pick gets only what is asked for: the `first` pairs of each task by (shared falling, u, v), or,
    without a number, those that are not joined, uncounted (shared is None)."""
    if isinstance(edges, Groups):
        return edges.far(pick, schema) if first is None else edges.most_shared(pick, schema, first)
    lists = both_ways(edges).distinct().groupBy("u").agg(F.collect_list("v").alias("vs"))
    many = max(1, -(-edges.select(F.explode(F.array("u", "v")).alias("v")).distinct().count() // block))
    own = lists.withColumn("own", F.pmod(F.xxhash64("u"), F.lit(many)).cast("int"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(many - 1)))).withColumn("p", F.least("own", "other")).withColumn("q", F.greatest("own", "other"))

    def matrix(rows: np.ndarray, at: np.ndarray, n: int, low: int) -> np.ndarray:
        out = np.zeros((n, columns), np.float32)
        here = (at >= low) & (at < low + columns)
        out[rows[here], at[here] - low] = 1
        return out

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        p, q = int(pdf["p"].iloc[0]), int(pdf["q"].iloc[0])
        sides = [pdf[pdf["own"] == b] for b in (p, q)]
        ids = [s["u"].to_numpy(np.int64) for s in sides]
        if not len(ids[0]) or not len(ids[1]):
            return pick(*[np.zeros(0, t) for t in (np.int64, np.int64, np.int64, bool)])
        flat = [np.concatenate(s["vs"].to_list()).astype(np.int64) for s in sides]
        rows = [np.repeat(np.arange(len(s)), s["vs"].map(len).to_numpy()) for s in sides]
        there = np.intersect1d(*flat)
        cells = []
        for r, f in zip(rows, flat):
            at = np.searchsorted(there, f)
            ok = at < len(there)
            ok[ok] = there[at[ok]] == f[ok]
            cells.append((r[ok], at[ok]))
        shared = np.zeros((len(ids[0]), len(ids[1])), np.float32)
        for low in range(0, len(there), columns):
            a = matrix(*cells[0], len(ids[0]), low)
            shared += a @ (a if p == q else matrix(*cells[1], len(ids[1]), low)).T
        i, j = np.nonzero(shared)
        u, v, n = ids[0][i], ids[1][j], shared[i, j].astype(np.int64)
        if p == q:
            keep = u < v
            i, j, u, v, n = i[keep], j[keep], u[keep], v[keep], n[keep]
        # which of the second block are neighbours of the first
        order = np.argsort(ids[1])
        at = np.minimum(np.searchsorted(ids[1][order], flat[0]), len(order) - 1)
        hit = ids[1][order][at] == flat[0]
        linked = np.zeros(shared.shape, bool)
        linked[rows[0][hit], order[at[hit]]] = True
        return pick(np.minimum(u, v), np.maximum(u, v), n, linked[i, j])

    return dealt.groupBy("p", "q").applyInPandas(run, schema)


class Groups:
    """A graph told by groups, whose members are all joined, without its edges written down: rows(graph, part, grp, m).

    Groups of different parts share no member. A task gets all lists of a part and looks at some of its members, so that
    lists travel once for each task of a part, and pairs never do.
    """

    def __init__(self, rows: DataFrame):
        lists = rows.groupBy("graph", "part", "grp").agg(F.collect_list("m").alias("ms")).filter(F.size("ms") > 1)
        self.lists = settle(lists, "group-lists")
        self.rows = self.lists.select("graph", "part", "grp", F.explode("ms").alias("m"))

    def only(self, vertices: DataFrame) -> Groups:
        """The graph induced by vertices(graph, v)."""
        return Groups(self.rows.join(vertices.select("graph", F.col("v").alias("m")), ["graph", "m"], "left_semi"))

    def edges(self) -> DataFrame:
        a, b = self.rows.withColumnRenamed("m", "u"), self.rows.withColumnRenamed("m", "v")
        return a.join(b, ["graph", "part", "grp"]).filter("u < v").select("graph", "u", "v").distinct()

    def degrees(self, most: int = 250_000) -> DataFrame:
        """degrees() of its edges. most: rows of a part for each of its tasks."""

        def count(near: _Near, mine: np.ndarray) -> dict:
            return {"v": near.ids[mine], "degree": np.array([np.count_nonzero(near.of(i)) for i in mine], np.int32)}

        return self._dealt(count, "v long, degree int", most)

    def triangles(self, most: int = 60_000, held: int = 1 << 31) -> DataFrame:
        """(graph, n) for some vertices each, to be added up. held: bits of the adjacency matrix in a task at once."""

        def count(near: _Near, mine: np.ndarray) -> dict:
            n, total = len(near.ids), 0
            width = max(64, held // n // 64 * 64)
            for low in range(0, n, width):
                high = min(n, low + width)
                words = -(-(high - low) // 64)
                later = np.zeros((high, words), np.uint64)  # who of this stretch is a neighbour and comes later
                for i in range(high):
                    row = np.zeros(words * 64, bool)
                    row[: high - low] = near.of(i)[low:high]
                    row[: max(0, i + 1 - low)] = False
                    later[i] = np.packbits(row, bitorder="little").view(np.uint64)
                for i in mine[mine < high]:
                    to = i + 1 + np.flatnonzero(near.of(i)[i + 1 : high])
                    at = max(0, i - low) // 64
                    total += int(np.bitwise_count(later[to, at:] & later[i, at:]).sum())
            return {"n": np.array([total], np.int64)}

        return self._dealt(count, "n long", most)

    def far(self, pick, schema: str, most: int = 250_000) -> DataFrame:
        """neighbour_products() of pairs that are not joined. Of 64 vertices at a time, a bit each tells who meets them, which
        groups hold any of these, and whom these groups hold, in three passes over the lists."""

        def run(near: _Near, mine: np.ndarray) -> Iterator[pd.DataFrame]:
            flat, starts, which, at = near.rows()
            for low in range(0, len(mine), 64):
                some = mine[low : low + 64]
                own = np.zeros(len(starts), np.uint64)
                for j, i in enumerate(some):
                    own[which[at[i] : at[i + 1]]] |= np.uint64(1 << j)
                met = np.bitwise_or.reduceat(own.take(which), at[:-1])
                theirs = np.bitwise_or.reduceat(met.take(flat), starts)
                new = np.bitwise_or.reduceat(theirs.take(which), at[:-1]) & ~met
                us, vs = [], []
                for j, i in enumerate(some):
                    v = near.ids[i + 1 :][(new[i + 1 :] & np.uint64(1 << j)) != 0]
                    us.append(np.full(len(v), near.ids[i]))
                    vs.append(v)
                u, v = np.concatenate(us), np.concatenate(vs)
                yield pick(u, v, None, np.zeros(len(u), bool))

        return self._told(run, schema, most)

    def most_shared(self, pick, schema: str, first: int, most: int = 250_000) -> DataFrame:
        """neighbour_products() of the pairs that share most, of every task. Vertices come in falling order of their meetings,
        which, like their degrees, bound what they share. Who a vertex's neighbours meet, all meetings counted, is a closer
        bound, summed for some vertices at once; neighbours are told one by one only where it reaches the pairs found so far."""

        def run(near: _Near, mine: np.ndarray) -> Iterator[pd.DataFrame]:
            sizes = np.array([len(x) for x in near.lists], np.int64)
            _, starts, which, at = near.rows()
            meetings = np.add.reduceat(sizes[which], at[:-1]) - np.diff(at)
            order = np.argsort(-meetings, kind="stable")  # by rank from here on
            rank = np.empty(len(order), np.int64)
            rank[order] = np.arange(len(order))
            near = _Near.of_places(near.ids[order], [rank[x] for x in near.lists])
            flat, starts, which, at = near.rows()
            meetings, groups = meetings[order], np.diff(at)
            bits = int(meetings[0] + groups.max()).bit_length()
            many, mask = 64 // bits, np.uint64((1 << bits) - 1)
            best: list[tuple[int, int, int, bool]] = []  # -shared, u, v, linked

            def least() -> int:
                return -best[-1][0] if len(best) == first else 1

            def look(some: list[tuple[int, np.ndarray, int]]) -> None:
                nonlocal best
                marks = np.zeros(len(near.ids), np.uint64)
                for j, (_, mates, _) in enumerate(some):
                    marks |= mates.astype(np.uint64) << np.uint64(bits * j)
                held = np.add.reduceat(marks.take(flat), starts)
                low = some[0][0] + 1
                high = int(np.searchsorted(-meetings, -least(), side="right"))
                if low >= high:
                    return
                sums = np.add.reduceat(held.take(which[at[low] : at[high]]), at[low:high] - at[low])
                for j, (i, mates, degree) in enumerate(some):
                    v = np.arange(i + 1, high)
                    bound = (sums[i + 1 - low :] >> np.uint64(bits * j) & mask).astype(np.int64) - mates[i + 1 : high] * groups[i + 1 : high]
                    bound = np.minimum(np.minimum(bound, meetings[i + 1 : high]), degree)
                    v = v[bound >= least()]
                    bound = bound[v - i - 1]
                    for k in np.argsort(-bound, kind="stable"):
                        if bound[k] < least():
                            break
                        n = int(np.count_nonzero(mates & near.of(v[k])))
                        if n >= least():
                            a, b = sorted((int(near.ids[i]), int(near.ids[v[k]])))
                            best = sorted([*best, (-n, a, b, bool(mates[v[k]]))])[:first]

            some: list[tuple[int, np.ndarray, int]] = []
            for i in np.sort(rank[mine]).tolist():
                if meetings[i] < least():
                    break
                mates = near.of(i)
                degree = int(np.count_nonzero(mates))
                if degree >= least():
                    some.append((i, mates, degree))
                if len(some) == many:
                    look(some)
                    some = []
            if some:
                look(some)
            n, u, v, linked = (np.array([x[c] for x in best], t) for c, t in enumerate((np.int64, np.int64, np.int64, bool)))
            yield pick(u, v, -n, linked)

        return self._told(run, schema, most)

    def _dealt(self, count, schema: str, most: int) -> DataFrame:
        def run(near: _Near, mine: np.ndarray, name: str) -> Iterator[pd.DataFrame]:
            out = pd.DataFrame(count(near, mine))
            out.insert(0, "graph", name)
            yield out

        return self._told(run, f"graph string, {schema}", most, True)

    def _told(self, run_one, schema: str, most: int, named: bool = False) -> DataFrame:
        """What run_one(near, vertices) gives for the vertices of each task, a frame after the other."""
        parts = self.lists.groupBy("graph", "part").agg(F.sum(F.size("ms")).alias("n"))
        n, largest = parts.agg(F.count(F.lit(1)), F.coalesce(F.max("n"), F.lit(0))).first()
        many = max(1, -(-largest // most))
        dealt = self.lists.select("graph", "part", "ms", F.explode(F.sequence(F.lit(0), F.lit(many - 1))).alias("task"))

        def run(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            lists = []
            for pdf in pdfs:
                lists += pdf["ms"].to_list()
                name, task = pdf["graph"].iloc[0], int(pdf["task"].iloc[0])
            near = _Near(lists)
            place = (near.ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(many)
            yield from run_one(near, np.flatnonzero(place == task), *([name] if named else []))

        tasks = max(1, min(n * many, 4096))
        return dealt.repartition(tasks, "graph", "part", "task").groupBy("graph", "part", "task").applyInPandas(run, schema)


class _Near:
    """Neighbours of the members of lists, by their place among ids."""

    def __init__(self, lists: list):
        sizes = np.array([len(x) for x in lists])
        self.ids, flat = np.unique(np.concatenate(lists).astype(np.int64), return_inverse=True)
        self._place(flat, sizes)

    @classmethod
    def of_places(cls, ids: np.ndarray, lists: list) -> _Near:
        """Of ids in any order, and lists of their places."""
        out = cls.__new__(cls)
        out.ids = ids
        out._place(np.concatenate(lists), np.array([len(x) for x in lists]))
        return out

    def _place(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        ends = np.cumsum(sizes)
        self.flat, self.starts = flat, ends - sizes
        self.lists = [flat[e - n : e] for e, n in zip(ends, sizes)]
        self.which = np.repeat(np.arange(len(sizes)), sizes)[np.argsort(flat, kind="stable")]
        self.at = np.concatenate([[0], np.cumsum(np.bincount(flat, minlength=len(self.ids)))])

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Members list by list with where lists begin, and lists member by member with where members begin."""
        return self.flat, self.starts, self.which, self.at

    def of(self, i: int) -> np.ndarray:
        out = np.zeros(len(self.ids), bool)
        for j in self.which[self.at[i] : self.at[i + 1]]:
            out[self.lists[j]] = True
        out[i] = False
        return out


def degrees_of(graph: DataFrame | Groups) -> DataFrame:
    return graph.degrees() if isinstance(graph, Groups) else degrees(graph)


def among(graph: DataFrame | Groups, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among vertices(graph, v)."""
    return graph.only(vertices).edges() if isinstance(graph, Groups) else induced(graph, vertices)
