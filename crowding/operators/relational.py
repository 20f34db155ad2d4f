"""Relational queries around the methods: sources, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from crowding.operators import graph as g
from crowding.plans.registry import query
from crowding.plans.workloads import GRAPHS, SQL, cust_day_groups, graph_of, read, with_graph
from crowding.sources import edges as src


def _edges(spark, sf, name="parts") -> DataFrame:
    return GRAPHS[name](spark, sf).select("u", "v")


def _deg(spark, sf, name="parts") -> DataFrame:
    return g.degrees(GRAPHS[name](spark, sf))


def _blk(spark, sf, name="parts") -> DataFrame:
    return g.block_sequence(_deg(spark, sf, name))


@query("scan_edges", "SELECT DISTINCT l_orderkey, l_partkey FROM lineitem")
def scan_edges(spark, sf):
    return read(spark, sf, "lineitem", "l_orderkey", "l_partkey").distinct()


@query("src_csv_roundtrip", f"SELECT * FROM ({SQL['cust_day']})")
def src_csv_roundtrip(spark, sf):
    return src.read_csv(spark, src.write_csv(_edges(spark, sf, "cust_day")))


@query("src_adjacency_roundtrip", with_graph("doc_lines", "SELECT u, v FROM g"))
def src_adjacency_roundtrip(spark, sf):
    return src.read_adjacency(spark, src.write_adjacency(_edges(spark, sf, "doc_lines")))


@query("src_edgelist_datasource", with_graph("users_minute", "SELECT u, v FROM g"))
def src_edgelist_datasource(spark, sf):
    spark.dataSource.register(src.EdgeListSource)
    return spark.read.format("edgelist").option("path", src.write_csv(_edges(spark, sf, "users_minute"))).load()


@query("src_parquet_partitioned", with_graph("users_minute", "SELECT 'users_minute' AS graph, u, v FROM g"))
def src_parquet_partitioned(spark, sf):
    return src.read_parquet(spark, src.write_parquet(GRAPHS["users_minute"](spark, sf)))


@query("touched_blocks", with_graph("parts", "SELECT degree, size FROM blk WHERE size < 5"))
def touched_blocks(spark, sf):
    return g.violations(_blk(spark, sf), 5).select("degree", "size")


@query("exposed_vertices_k", with_graph("parts", "SELECT v, degree FROM deg WHERE degree IN (SELECT degree FROM blk WHERE size < 5)"))
def exposed_vertices_k(spark, sf):
    return g.exposed_vertices(_deg(spark, sf), 5).select("v", "degree")


@query("vertex_block_size", with_graph("parts", "SELECT v, deg.degree, size FROM deg JOIN blk ON deg.degree = blk.degree"))
def vertex_block_size(spark, sf):
    d = _deg(spark, sf)
    return d.join(g.block_sequence(d), ["graph", "degree"]).select("v", "degree", "size")


def _degree_pairs(spark, sf):
    e = GRAPHS["parts"](spark, sf)
    d = g.degrees(e)
    a, b = d.select(F.col("v").alias("u"), F.col("degree").alias("deg_u")), d.select("v", F.col("degree").alias("deg_v"))
    return e.join(a, "u").join(b, "v")


_PAIRS = "SELECT a.degree AS deg_u, b.degree AS deg_v FROM g JOIN deg a ON g.u = a.v JOIN deg b ON g.v = b.v"


@query("edge_degree_pairs", with_graph("parts", f"SELECT deg_u, deg_v, count(*) AS n FROM ({_PAIRS}) GROUP BY 1, 2"))
def edge_degree_pairs(spark, sf):
    return _degree_pairs(spark, sf).groupBy("deg_u", "deg_v").agg(F.count(F.lit(1)).alias("n"))


@query("degree_assortativity", with_graph("parts", f"SELECT round(corr(x, y), 6) AS r FROM (SELECT deg_u AS x, deg_v AS y FROM ({_PAIRS}) UNION ALL SELECT deg_v, deg_u FROM ({_PAIRS}))"))
def degree_assortativity(spark, sf):
    p = _degree_pairs(spark, sf).select(F.inline(F.array(F.struct(F.col("deg_u").alias("x"), F.col("deg_v").alias("y")), F.struct(F.col("deg_v").alias("x"), F.col("deg_u").alias("y")))))
    return p.agg(F.round(F.corr("x", "y"), 6).alias("r"))


def _halves(spark, sf):
    li = read(spark, sf, "lineitem", "l_orderkey", "l_partkey")
    from crowding.plans.workloads import together

    both = [together(li.filter(c), ["l_orderkey"], "l_partkey", "h").select("u", "v") for c in ("l_orderkey % 2 = 0", "l_orderkey % 2 = 1")]
    return both


_HALVES = "WITH " + ", ".join(
    f"h{i} AS (SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey WHERE a.l_orderkey % 2 = {i})"
    for i in (0, 1)
)


@query("common_edges", f"{_HALVES} SELECT u, v FROM h0 INTERSECT SELECT u, v FROM h1")
def common_edges(spark, sf):
    a, b = _halves(spark, sf)
    return a.intersect(b)


@query("new_edges", f"{_HALVES} SELECT u, v FROM h1 EXCEPT SELECT u, v FROM h0")
def new_edges(spark, sf):
    a, b = _halves(spark, sf)
    return b.exceptAll(a)


@query("edges_only_in", f"{_HALVES} SELECT u, v FROM h0 EXCEPT SELECT u, v FROM h1")
def edges_only_in(spark, sf):
    a, b = _halves(spark, sf)
    return a.join(b, ["u", "v"], "left_anti")


@query("union_graphs", f"{_HALVES} SELECT u, v FROM h0 UNION SELECT u, v FROM h1")
def union_graphs(spark, sf):
    a, b = _halves(spark, sf)
    return a.unionByName(b).distinct()


_TOP = "top AS (SELECT v FROM deg ORDER BY degree DESC, v LIMIT 50)"


@query("missing_pairs", with_graph("parts", f", {_TOP} SELECT a.v AS u, b.v AS v FROM top a JOIN top b ON a.v < b.v ANTI JOIN g ON g.u = a.v AND g.v = b.v"))
def missing_pairs(spark, sf):
    """Non-adjacent pairs among 50 hubs: a pair list of a constant size, anti-joined."""
    e = GRAPHS["parts"](spark, sf)
    top = g.degrees(e).orderBy(F.desc("degree"), "v").limit(50).select("v")
    pairs = top.select(F.col("v").alias("u")).join(top, F.col("u") < F.col("v"))
    return pairs.join(e.select("u", "v"), ["u", "v"], "left_anti")


@query("demander_edges", with_graph("parts", "SELECT u, v FROM g WHERE u IN (SELECT v FROM deg WHERE degree IN (SELECT degree FROM blk WHERE size < 5)) AND v IN (SELECT v FROM deg WHERE degree IN (SELECT degree FROM blk WHERE size < 5))"))
def demander_edges(spark, sf):
    e = GRAPHS["parts"](spark, sf)
    return g.induced(e, g.exposed_vertices(g.degrees(e), 5)).select("u", "v")


def _raised(blocks: DataFrame, most: int = 3) -> DataFrame:
    """A lift of a fixed kind for the queries below: members of blocks under a size go to the next occupied degree."""
    up = F.lead("degree").over(W.partitionBy("graph").orderBy("degree"))
    moved = blocks.withColumn("up", up).withColumn("to", F.when((F.col("size") < most) & F.col("up").isNotNull(), F.col("up")).otherwise(F.col("degree")))
    return moved.groupBy("graph", F.col("to").alias("degree")).agg(F.sum("size").alias("size"))


_LIFT = "nxt AS (SELECT degree, size, lead(degree) OVER (ORDER BY degree) AS up FROM blk), aft AS (SELECT CASE WHEN size < 3 AND up IS NOT NULL THEN up ELSE degree END AS degree, CAST(sum(size) AS BIGINT) AS size FROM nxt GROUP BY 1)"
_CROSS = (
    "cr AS (SELECT coalesce(b.degree, a.degree) AS degree, coalesce(b.size, 0) AS b_before, coalesce(a.size, 0) AS b_after FROM blk b FULL JOIN aft a ON a.degree = b.degree), "
    "cx AS (SELECT degree, b_before, CAST(coalesce(sum(b_after - b_before) OVER (ORDER BY degree DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS x, b_after FROM cr)"
)


@query("crossings", with_graph("parts", f", {_LIFT}, {_CROSS} SELECT * FROM cx"))
def crossings(spark, sf):
    b = _blk(spark, sf)
    return g.crossings(b, _raised(b)).drop("graph")


@query("dominance", with_graph("parts", f", {_LIFT}, {_CROSS} SELECT bool_and(x >= 0) AS dominates, CAST(sum(x * gap) AS BIGINT) AS cost_deg FROM (SELECT x, coalesce(lead(degree) OVER (ORDER BY degree) - degree, 0) AS gap FROM cx)"))
def dominance(spark, sf):
    b = _blk(spark, sf)
    return g.dominance(g.crossings(b, _raised(b))).drop("graph")


_RUNS = ", ".join(f"{t}r AS (SELECT degree, sum(size) OVER (ORDER BY degree) - size AS lo, sum(size) OVER (ORDER BY degree) AS hi FROM {s})" for t, s in (("a", "blk"), ("z", "aft")))
_HIST = "hist AS (SELECT CAST(z.degree - a.degree AS INT) AS demand, CAST(sum(least(a.hi, z.hi) - greatest(a.lo, z.lo)) AS BIGINT) AS n FROM ar a JOIN zr z ON a.lo < z.hi AND z.lo < a.hi GROUP BY 1)"


@query("sorted_demands", with_graph("parts", f", {_LIFT}, {_RUNS}, {_HIST} SELECT * FROM hist"))
def sorted_demands(spark, sf):
    b = _blk(spark, sf)
    return g.sorted_demands(b, _raised(b)).drop("graph")


@query("eg_theta", with_graph("parts", f""", {_LIFT}, {_RUNS}, {_HIST}, h AS (SELECT demand, n, sum(n) OVER (ORDER BY demand DESC) AS r, sum(demand * n) OVER (ORDER BY demand DESC) AS asked FROM hist WHERE demand > 0)
SELECT demand, CAST(r AS BIGINT) AS r, CAST(asked AS BIGINT) AS asked, CAST(r * (r - 1) + coalesce((SELECT sum(least(l.demand, h.r) * l.n) FROM h l WHERE l.demand < h.demand), 0) AS BIGINT) AS room FROM h"""))
def eg_theta(spark, sf):
    b = _blk(spark, sf)
    return g.eg_blocks(g.sorted_demands(b, _raised(b))).select("demand", "r", "asked", "room")


@query(
    "asof_last_order",
    """SELECT event_id, user_id, max(o_orderkey) AS last_order FROM (
         SELECT e.event_id, e.user_id, o.o_orderkey, o.o_orderdate, max(o.o_orderdate) OVER (PARTITION BY e.event_id) AS latest
         FROM events e LEFT JOIN orders o ON o.o_custkey = e.user_id AND o.o_orderdate + INTERVAL 24 YEAR <= e.ts)
       WHERE o_orderdate IS NOT DISTINCT FROM latest GROUP BY 1, 2""",
)
def asof_last_order(spark, sf):
    """Latest order at or before each event, 24 years apart: one sorted pass over the union of both."""
    ev = read(spark, sf, "events", "event_id", "user_id", "ts").select(F.col("user_id").alias("who"), "ts", F.lit(1).alias("kind"), "event_id", F.lit(None).cast("long").alias("okey"))
    orders = read(spark, sf, "orders", "o_orderkey", "o_custkey", "o_orderdate").select(
        F.col("o_custkey").alias("who"), (F.col("o_orderdate") + F.expr("INTERVAL 24 YEAR")).cast("timestamp").alias("ts"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderkey").alias("okey"))
    w = W.partitionBy("who").orderBy("ts", "kind", "okey").rowsBetween(W.unboundedPreceding, 0)
    both = orders.unionByName(ev.select("who", "ts", "kind", "event_id", "okey"))
    return both.withColumn("last_order", F.last("okey", ignorenulls=True).over(w)).filter("kind = 1").select("event_id", F.col("who").alias("user_id"), "last_order")


@query(
    "event_session_interval",
    """WITH s AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
       n AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM s)
       SELECT user_id, CAST(session AS BIGINT) AS session, count(*) AS n_events, min(event_id) AS first_event FROM n GROUP BY 1, 2""",
)
def event_session_interval(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    ev = read(spark, sf, "events", "event_id", "user_id", "ts")
    gap = (F.col("ts") - F.lag("ts").over(w)) > F.expr("INTERVAL 30 MINUTE")
    ev = ev.withColumn("session", F.sum(F.when(F.coalesce(gap, F.lit(True)), 1).otherwise(0)).over(w))
    return ev.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n_events"), F.min("event_id").alias("first_event"))


@query("block_cumulative", with_graph("parts", "SELECT degree, size, CAST(sum(size) OVER (ORDER BY degree) AS BIGINT) AS upto, CAST(sum(size) OVER (ORDER BY degree DESC) AS BIGINT) AS from_here FROM blk"))
def block_cumulative(spark, sf):
    w = W.partitionBy("graph")
    return _blk(spark, sf).select("degree", "size", F.sum("size").over(w.orderBy("degree")).alias("upto"), F.sum("size").over(w.orderBy(F.desc("degree"))).alias("from_here"))


@query("degree_gap", with_graph("parts", "SELECT degree, lead(degree) OVER (ORDER BY degree) - degree AS gap FROM blk"))
def degree_gap(spark, sf):
    return _blk(spark, sf).select("degree", (F.lead("degree").over(W.partitionBy("graph").orderBy("degree")) - F.col("degree")).alias("gap"))


@query("near_degree_range", with_graph("parts", "SELECT v, count(*) OVER (ORDER BY degree RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS near FROM deg"))
def near_degree_range(spark, sf):
    """Vertices within one degree: windows over block sums, not over all vertices of a graph."""
    d = _deg(spark, sf)
    near = g.block_sequence(d).withColumn("near", F.sum("size").over(W.partitionBy("graph").orderBy("degree").rangeBetween(-1, 1)))
    return d.join(near.select("graph", "degree", "near"), ["graph", "degree"]).select("v", "near")


@query("degree_ranks", with_graph("users_minute", "SELECT v, row_number() OVER w AS rn, rank() OVER d AS rk, dense_rank() OVER d AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER d, 9) AS pr, round(cume_dist() OVER d, 9) AS cd FROM deg WINDOW w AS (ORDER BY degree DESC, v), d AS (ORDER BY degree DESC)"))
def degree_ranks(spark, sf):
    return ranks(_deg(spark, sf, "users_minute"), 4).drop("graph")


def ranks(deg, tiles: int):
    """(graph, v, rn, rk, dr, nt, pr, cd) of degrees in falling order, ties by v.

    Ranks of a degree come from the blocks, a row per degree; only places within a block need its vertices in
    order, so no task gets a whole graph.
    """
    lng = lambda c: c.cast("long")
    blocks = g.block_sequence(deg)
    down = W.partitionBy("graph").orderBy(F.desc("degree"))
    above = F.coalesce(F.sum("size").over(down.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    total = F.sum("size").over(W.partitionBy("graph"))
    place = blocks.select("graph", "degree", "size", above.alias("above"), F.row_number().over(down).alias("dr"), total.alias("total"))
    rows = deg.join(place, ["graph", "degree"]).withColumn("rn", F.col("above") + F.row_number().over(W.partitionBy("graph", "degree").orderBy("v")))
    small, more = F.floor(F.col("total") / tiles), F.col("total") % tiles  # the first tiles have one more
    edge = more * (small + 1)
    nt = F.when(F.col("rn") <= edge, F.floor((F.col("rn") - 1) / (small + 1)) + 1).otherwise(more + F.floor((F.col("rn") - 1 - edge) / F.greatest(small, F.lit(1))) + 1)
    pr = F.when(F.col("total") > 1, F.col("above") / (F.col("total") - 1)).otherwise(F.lit(0.0))
    return rows.select("graph", "v", lng(F.col("rn")).alias("rn"), lng(F.col("above") + 1).alias("rk"), lng(F.col("dr")).alias("dr"), lng(nt).alias("nt"), F.round(pr, 9).alias("pr"), F.round((F.col("above") + F.col("size")) / F.col("total"), 9).alias("cd"))


@query("block_representatives", with_graph("parts", "SELECT degree, v, rank FROM (SELECT degree, v, CAST(row_number() OVER (PARTITION BY degree ORDER BY v) AS INT) AS rank FROM deg) WHERE rank <= 9"))
def block_representatives(spark, sf):
    return g.representatives(_deg(spark, sf), 9).select("degree", "v", "rank")


@query("top_hubs", with_graph("parts", "SELECT v, degree FROM deg ORDER BY degree DESC, v LIMIT 20"))
def top_hubs(spark, sf):
    return _deg(spark, sf).orderBy(F.desc("degree"), "v").limit(20).select("v", "degree")


@query("degree_stats", with_graph("parts", "SELECT min(degree) AS lo, max(degree) AS hi, round(avg(degree), 6) AS mean, round(stddev_samp(degree), 6) AS sd, round(quantile_cont(degree, 0.5), 6) AS median, round(quantile_cont(degree, 0.9), 6) AS p90 FROM deg"))
def degree_stats(spark, sf):
    return _deg(spark, sf).agg(
        F.min("degree").alias("lo"), F.max("degree").alias("hi"), F.round(F.avg("degree"), 6).alias("mean"), F.round(F.stddev_samp("degree"), 6).alias("sd"),
        F.round(F.percentile("degree", 0.5), 6).alias("median"), F.round(F.percentile("degree", 0.9), 6).alias("p90"))


@query("distinct_counts", with_graph("parts", "SELECT count(DISTINCT u) AS n_u, count(DISTINCT v) AS n_v FROM g"))
def distinct_counts(spark, sf):
    return _edges(spark, sf).agg(F.count_distinct("u").alias("n_u"), F.count_distinct("v").alias("n_v"))


@query("distinct_counts_approx", with_graph("parts", "SELECT count(DISTINCT u) AS n_u, count(DISTINCT v) AS n_v, true AS near_u, true AS near_v FROM g"))
def distinct_counts_approx(spark, sf):
    """Exact distinct ends beside sketches of 2 % standard error, and whether those are within 8 %."""
    e = _edges(spark, sf)
    n = e.agg(F.count_distinct("u").alias("n_u"), F.count_distinct("v").alias("n_v"), F.approx_count_distinct("u", 0.02).alias("a_u"), F.approx_count_distinct("v", 0.02).alias("a_v"))
    near = lambda a, b: F.abs(F.col(a) - F.col(b)) <= 0.08 * F.col(b)
    return n.select("n_u", "n_v", near("a_u", "n_u").alias("near_u"), near("a_v", "n_v").alias("near_v"))


@query("degree_cube", with_graph("parts", "SELECT p_brand, p_type, round(avg(degree), 6) AS mean, count(*) AS n FROM deg JOIN part ON v = p_partkey GROUP BY CUBE (p_brand, p_type)"))
def degree_cube(spark, sf):
    d = _deg(spark, sf).join(read(spark, sf, "part", "p_partkey", "p_brand", "p_type"), F.col("v") == F.col("p_partkey"))
    return d.cube("p_brand", "p_type").agg(F.round(F.avg("degree"), 6).alias("mean"), F.count(F.lit(1)).alias("n"))


_CUST = "FROM deg JOIN customer ON v = 2 * c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _customers(spark, sf):
    c = read(spark, sf, "customer", "c_custkey", "c_nationkey", "c_mktsegment").join(read(spark, sf, "nation", "n_nationkey", "n_name", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
    c = c.join(read(spark, sf, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    return _deg(spark, sf, "cust_supp").join(c, F.col("v") == F.col("c_custkey") * 2)


@query("region_rollup", with_graph("cust_supp", f"SELECT r_name, n_name, round(avg(degree), 6) AS mean, count(*) AS n {_CUST} GROUP BY ROLLUP (r_name, n_name)"))
def region_rollup(spark, sf):
    return _customers(spark, sf).rollup("r_name", "n_name").agg(F.round(F.avg("degree"), 6).alias("mean"), F.count(F.lit(1)).alias("n"))


@query("segment_grouping_sets", with_graph("cust_supp", f"SELECT c_mktsegment, n_name, round(avg(degree), 6) AS mean {_CUST} GROUP BY GROUPING SETS ((c_mktsegment), (n_name), ())"))
def segment_grouping_sets(spark, sf):
    return spark.sql("SELECT c_mktsegment, n_name, round(avg(degree), 6) AS mean FROM {d} GROUP BY GROUPING SETS ((c_mktsegment), (n_name), ())", d=_customers(spark, sf))


_FOUR = ("parts", "cust_supp", "users_minute", "cust_day")


@query("blocks_pivot", "SELECT bucket, " + ", ".join(f"CAST(sum(CASE WHEN graph = '{n}' THEN 1 END) AS BIGINT) AS {n}" for n in _FOUR) + " FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS graph, CAST(floor(log2(degree)) AS BIGINT) AS bucket FROM ({with_graph(n, 'SELECT degree FROM deg')})" for n in _FOUR) + ") GROUP BY bucket")
def blocks_pivot(spark, sf):
    rows = None
    for n in _FOUR:
        d = _deg(spark, sf, n).select(F.lit(n).alias("graph"), F.floor(F.log2("degree")).alias("bucket"))
        rows = d if rows is None else rows.unionByName(d)
    return rows.groupBy("bucket").pivot("graph", list(_FOUR)).agg(F.count(F.lit(1)))


@query("triangles", with_graph("cust_day", "SELECT count(*) AS n FROM g a JOIN g b ON a.v = b.u JOIN g c ON c.u = a.u AND c.v = b.v"))
def triangles(spark, sf):
    """From rows of the adjacency matrix, nation by nation, so that neither paths nor edges are written down."""
    return cust_day_groups(spark, sf).triangles().agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def _both(e):
    return e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))


_BOTH = "b AS (SELECT u, v FROM g UNION ALL SELECT v, u FROM g)"


@query("two_hop", with_graph("users_minute", f", {_BOTH} SELECT DISTINCT x.u, y.v FROM b x JOIN b y ON x.v = y.u AND x.u < y.v ANTI JOIN g ON g.u = x.u AND g.v = y.v"))
def two_hop(spark, sf):
    import pandas as pd

    e = graph_of(spark, sf, "users_minute")
    if g.dense_for_products(e):
        return g.neighbour_products(e, lambda u, v, n, linked: pd.DataFrame({"u": u[~linked], "v": v[~linked]}), "u long, v long")
    e = e.edges().select("u", "v")
    b = _both(e)
    far = b.select("u", F.col("v").alias("m")).join(b.select(F.col("u").alias("m"), "v"), "m").filter("u < v").select("u", "v").distinct()
    return far.join(e, ["u", "v"], "left_anti")


@query("common_neighbours_top", with_graph("users_minute", f", {_BOTH} SELECT x.u, y.v, count(*) AS shared FROM b x JOIN b y ON x.v = y.u AND x.u < y.v GROUP BY 1, 2 ORDER BY shared DESC, x.u, y.v LIMIT 25"))
def common_neighbours_top(spark, sf):
    import numpy as np
    import pandas as pd

    e = graph_of(spark, sf, "users_minute")
    if g.dense_for_products(e):

        def first(u, v, n, linked):
            at = np.lexsort((v, u, -n))[:25]  # the first of all are among those of the tasks
            return pd.DataFrame({"u": u[at], "v": v[at], "shared": n[at]})

        return g.neighbour_products(e, first, "u long, v long, shared long", first=25).orderBy(F.desc("shared"), "u", "v").limit(25)
    b = _both(e.edges().select("u", "v"))
    p = b.select("u", F.col("v").alias("m")).join(b.select(F.col("u").alias("m"), "v"), "m").filter("u < v")
    return p.groupBy("u", "v").agg(F.count(F.lit(1)).alias("shared")).orderBy(F.desc("shared"), "u", "v").limit(25)


@query("components", with_graph("cust_day", f", {_BOTH}, w(u, r) AS (SELECT v, v FROM deg UNION SELECT b.v, w.r FROM w JOIN b ON b.u = w.u AND w.r < b.v) SELECT n_vertices, count(*) AS n_components FROM (SELECT r, count(*) AS n_vertices FROM (SELECT u, min(r) AS r FROM w GROUP BY u) GROUP BY r) GROUP BY 1", recursive=True))
def components(spark, sf):
    from crowding.operators.rounds import min_labels

    lab = min_labels(GRAPHS["cust_day"](spark, sf))
    return lab.groupBy("label").agg(F.count(F.lit(1)).alias("n_vertices")).groupBy("n_vertices").agg(F.count(F.lit(1)).alias("n_components"))


@query("weighted_degree", "SELECT a.l_partkey AS v, round(sum(b.l_quantity), 4) AS weight FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey GROUP BY 1")
def weighted_degree(spark, sf):
    li = read(spark, sf, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    o = li.select("l_orderkey", F.col("l_partkey").alias("other"), "l_quantity")
    return li.select("l_orderkey", "l_partkey").join(o, "l_orderkey").filter("l_partkey <> other").groupBy(F.col("l_partkey").alias("v")).agg(F.round(F.sum("l_quantity"), 4).alias("weight"))


@query("json_props_blocks", "SELECT degree, count(*) AS size FROM (SELECT user_id, count(DISTINCT CAST(json_extract_string(props, '$.k') AS INT)) AS degree FROM events GROUP BY 1) GROUP BY 1")
def json_props_blocks(spark, sf):
    ev = read(spark, sf, "events", "user_id", "props").select("user_id", F.from_json("props", "k int")["k"].alias("k"))
    return ev.groupBy("user_id").agg(F.count_distinct("k").alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("size"))


@query("page_hosts", """SELECT regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, count(*) AS n_pages, CAST(sum(len(regexp_extract_all(html, 'href="[^"]*"'))) AS BIGINT) AS n_links FROM pages GROUP BY 1""")
def page_hosts(spark, sf):
    p = read(spark, sf, "pages", "url", "html")
    links = F.size(F.regexp_extract_all("html", F.lit('href="[^"]*"'), F.lit(0)))
    return p.groupBy(F.regexp_extract("url", "^https?://([^/?#]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("n_pages"), F.sum(links).alias("n_links"))


@query("doc_line_stats", "WITH l AS (SELECT lang, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents), c AS (SELECT lang, line, count(*) AS n FROM l WHERE length(line) > 0 GROUP BY 1, 2) SELECT lang, CAST(sum(n) AS BIGINT) AS n_lines, round(sum(CASE WHEN n > 1 THEN n ELSE 0 END) / sum(n), 9) AS repeated FROM c GROUP BY 1")
def doc_line_stats(spark, sf):
    lines = read(spark, sf, "documents", "lang", "text").select("lang", F.explode(F.split("text", "\n")).alias("line")).select("lang", F.trim("line").alias("line"))
    c = lines.filter(F.char_length("line") > 0).groupBy("lang", "line").agg(F.count(F.lit(1)).alias("n"))
    return c.groupBy("lang").agg(F.sum("n").alias("n_lines"), F.round(F.sum(F.when(F.col("n") > 1, F.col("n")).otherwise(0)) / F.sum("n"), 9).alias("repeated"))


@query("labelled_docs_semi", "SELECT doc_id, lang FROM documents SEMI JOIN labels USING (doc_id)")
def labelled_docs_semi(spark, sf):
    return read(spark, sf, "documents", "doc_id", "lang").join(read(spark, sf, "labels", "doc_id"), "doc_id", "left_semi")


@query("unlabelled_docs_anti", "SELECT doc_id, lang FROM documents ANTI JOIN labels USING (doc_id)")
def unlabelled_docs_anti(spark, sf):
    return read(spark, sf, "documents", "doc_id", "lang").join(read(spark, sf, "labels", "doc_id"), "doc_id", "left_anti")


@query("turn_windows", "SELECT conv_id, turn, lag(role) OVER w AS before, CAST(sum(length(text)) OVER w AS BIGINT) AS chars_so_far FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def turn_windows(spark, sf):
    w = W.partitionBy("conv_id").orderBy("turn")
    return read(spark, sf, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.sum(F.char_length("text")).over(w).alias("chars_so_far"))


@query("date_functions", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, CAST(dayofweek(o_orderdate) + 1 AS INT) AS weekday, count(*) AS n, CAST(max(date_diff('day', (SELECT min(o_orderdate) FROM orders), o_orderdate)) AS INT) AS last_day FROM orders GROUP BY 1, 2")
def date_functions(spark, sf):
    o = read(spark, sf, "orders", "o_orderdate")
    first = o.agg(F.min("o_orderdate")).first()[0]
    return o.groupBy(F.date_trunc("month", "o_orderdate").alias("month"), F.dayofweek("o_orderdate").alias("weekday")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("o_orderdate", F.lit(first))).alias("last_day"))


@query("math_functions", with_graph("parts", "SELECT degree, CAST(ceil(size / 7.0) AS BIGINT) AS c, CAST(floor(size / 7.0) AS BIGINT) AS f, round(ln(size), 9) AS l, round(pow(size, 1.5), 6) AS p, size % 7 AS m, greatest(size, 5) AS hi, least(size, 5) AS lo FROM blk"))
def math_functions(spark, sf):
    s = F.col("size")
    return _blk(spark, sf).select(
        "degree", F.ceil(s / 7.0).alias("c"), F.floor(s / 7.0).alias("f"), F.round(F.log(s), 9).alias("l"), F.round(F.pow(s, F.lit(1.5)), 6).alias("p"), F.pmod(s, F.lit(7)).cast("long").alias("m"),
        F.greatest(s, F.lit(5)).cast("long").alias("hi"), F.least(s, F.lit(5)).cast("long").alias("lo"))


@query("array_functions", with_graph("users_minute", f", {_BOTH}, a AS (SELECT u, list(v ORDER BY v) AS n FROM b GROUP BY u) SELECT u, n[1:3] AS first_three, len(list_filter(n, lambda x: x > u)) AS larger, CAST(list_sum(n) AS BIGINT) AS total, CAST(list_sum(list_transform(range(2, len(n) + 1), lambda i: n[i] - n[i - 1])) AS BIGINT) AS width FROM a"))
def array_functions(spark, sf):
    a = _both(_edges(spark, sf, "users_minute")).groupBy("u").agg(F.sort_array(F.collect_list("v")).alias("n"))
    steps = F.zip_with(F.slice("n", F.lit(2), F.size("n")), F.slice("n", F.lit(1), F.size("n") - 1), lambda x, y: x - y)
    total = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda s, x: s + x)
    return a.select("u", F.slice("n", 1, 3).alias("first_three"), F.size(F.filter("n", lambda x: x > F.col("u"))).cast("long").alias("larger"), total(F.col("n")).alias("total"), F.when(F.size("n") > 1, total(steps)).alias("width"))


@query("map_functions", with_graph("parts", "SELECT degree, size * 2 AS doubled FROM blk"))
def map_functions(spark, sf):
    m = _blk(spark, sf).groupBy("graph").agg(F.map_from_entries(F.collect_list(F.struct("degree", "size"))).alias("m"))
    return m.select(F.explode(F.transform_values("m", lambda k, v: v * 2)).alias("degree", "doubled"))


@query("string_functions", "SELECT c_custkey, concat_ws('/', lower(c_mktsegment), substring(c_name, 1, 8)) AS tag, CAST(levenshtein(c_mktsegment, 'BUILDING') AS INT) AS distance, length(c_name) AS n FROM customer WHERE c_name LIKE 'Customer%' AND c_acctbal BETWEEN 0 AND 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY', 'FURNITURE')")
def string_functions(spark, sf):
    c = read(spark, sf, "customer", "c_custkey", "c_name", "c_acctbal", "c_mktsegment")
    c = c.filter(F.col("c_name").like("Customer%") & F.col("c_acctbal").between(0, 5000) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY", "FURNITURE"))
    return c.select("c_custkey", F.concat_ws("/", F.lower("c_mktsegment"), F.substring("c_name", 1, 8)).alias("tag"), F.levenshtein("c_mktsegment", F.lit("BUILDING")).alias("distance"), F.char_length("c_name").cast("long").alias("n"))


@query("vector_cosine", "WITH z AS (SELECT embedding AS e0 FROM embeddings WHERE vec_id = 0) SELECT vec_id, round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), CAST(e0 AS DOUBLE[])), 6) AS cos FROM embeddings, z")
def vector_cosine(spark, sf):
    """Cosine with vector 0, whose value is brought down as one literal row."""
    vec = read(spark, sf, "embeddings", "vec_id", "embedding")
    zero = vec.filter("vec_id = 0").first()["embedding"]
    other = F.array(*[F.lit(float(x)) for x in zero])
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    e = F.col("embedding")
    return vec.select("vec_id", F.round(dot(e, other) / F.sqrt(dot(e, e) * dot(other, other)), 6).alias("cos"))


@query("publish_graph", with_graph("users_minute", "SELECT degree, size, true AS fresh FROM blk"))
def publish_graph(spark, sf):
    """Blocks of the published graph, and whether its ids are 1 to n."""
    out = publish(GRAPHS["users_minute"](spark, sf), seed=11)
    deg = g.degrees(out)
    ids = deg.groupBy("graph").agg(((F.min("v") == 1) & (F.max("v") == F.count(F.lit(1)))).alias("fresh"))
    return g.block_sequence(deg).join(ids, "graph").select("degree", "size", "fresh")


def publish(edges: DataFrame, seed: int, buckets: int = 256) -> DataFrame:
    """The graph under fresh ids in a hash order of the old ones; degrees stay, ids don't leak.

    Places are counted within ranges of the hash and added to what the ranges before hold (a row per range).
    """
    h = F.xxhash64(F.lit(seed), "v")
    ids = g.degrees(edges).select("graph", "v", h.alias("h"), F.shiftrightunsigned(h, 64 - (buckets - 1).bit_length()).alias("bucket"))
    held = ids.groupBy("graph", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(W.partitionBy("graph").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    offsets = held.select("graph", "bucket", before.alias("before"))
    place = F.row_number().over(W.partitionBy("graph", "bucket").orderBy("h", "v"))
    fresh = ids.withColumn("place", place).join(F.broadcast(offsets), ["graph", "bucket"]).select("graph", "v", (F.col("before") + F.col("place")).cast("long").alias("id"))
    a, b = fresh.select("graph", F.col("v").alias("u"), F.col("id").alias("a")), fresh.select("graph", "v", F.col("id").alias("b"))
    return edges.join(a, ["graph", "u"]).join(b, ["graph", "v"]).select("graph", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))
