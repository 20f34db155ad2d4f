"""The graphs of the experiments, from the given tables, each with the same definition in portable SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.operators.graph import Groups, canonical_edges


def read(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def together(rows: DataFrame, group: list[str], member: str, name: str) -> DataFrame:
    """Pairs of distinct members of a group; the pair's order is part of the join, so loops never arise."""
    one = rows.select(*group, F.col(member).cast("long").alias("m")).dropna().distinct()
    a, b = one.withColumnRenamed("m", "u"), one.withColumnRenamed("m", "v")
    return a.join(b, group).filter("u < v").select(F.lit(name).alias("graph"), "u", "v").distinct()


def together_in_few(rows: DataFrame, group: str, member: str, name: str) -> DataFrame:
    """together() for groups that are small by nature: members travel once, and pairs are made where a group's members are."""
    ms = rows.select(group, F.col(member).cast("long").alias("m")).dropna().groupBy(group).agg(F.collect_set("m").alias("ms"))
    firsts = ms.filter(F.size("ms") > 1).select("ms", F.explode("ms").alias("u"))
    pairs = firsts.select("u", F.explode(F.filter("ms", lambda m: m > F.col("u"))).alias("v"))
    return pairs.distinct().select(F.lit(name).alias("graph"), "u", "v")


def two_sided(rows: DataFrame, left, right, name: str) -> DataFrame:
    """Bipartite pairs; sides as even and odd ids."""
    return canonical_edges(rows.select((left * 2).alias("a"), (right * 2 + 1).alias("b")), "a", "b", name)


def parts_together(spark: SparkSession, sf: str) -> DataFrame:
    return together_in_few(read(spark, sf, "lineitem", "l_orderkey", "l_partkey"), "l_orderkey", "l_partkey", "parts")


def cust_supp(spark: SparkSession, sf: str) -> DataFrame:
    o, li = read(spark, sf, "orders", "o_orderkey", "o_custkey"), read(spark, sf, "lineitem", "l_orderkey", "l_suppkey")
    return two_sided(li.join(o, F.col("l_orderkey") == F.col("o_orderkey")), F.col("o_custkey"), F.col("l_suppkey"), "cust_supp")


def part_supp(spark: SparkSession, sf: str) -> DataFrame:
    return two_sided(read(spark, sf, "lineitem", "l_partkey", "l_suppkey"), F.col("l_partkey"), F.col("l_suppkey"), "part_supp")


def users_minute(spark: SparkSession, sf: str) -> DataFrame:
    ev = read(spark, sf, "events", "ts", "user_id").select(F.date_trunc("minute", "ts").alias("at"), "user_id")
    return together(ev, ["at"], "user_id", "users_minute")


def doc_lines(spark: SparkSession, sf: str) -> DataFrame:
    """Documents that share a line of 20 or more characters found in 2 to 50 documents."""
    lines = read(spark, sf, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    lines = lines.select("doc_id", F.trim("line").alias("line")).filter(F.char_length("line") >= 20).distinct()
    rare = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).filter("n between 2 and 50").select("line")
    return together(lines.join(rare, "line"), ["line"], "doc_id", "doc_lines")


def page_links(spark: SparkSession, sf: str) -> DataFrame:
    """Pages and their link targets; a target's id comes from its hash, so that no global ranking is needed."""
    href = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    links = read(spark, sf, "pages", "page_id", "html").select("page_id", href.alias("target"))
    return two_sided(links.select("page_id", F.conv(F.substring(F.md5("target"), 1, 15), 16, 10).cast("long").alias("t")), F.col("page_id"), F.col("t"), "page_links")


def cust_day(spark: SparkSession, sf: str) -> DataFrame:
    o = read(spark, sf, "orders", "o_custkey", "o_orderdate").join(read(spark, sf, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return together(o, ["o_orderdate", "c_nationkey"], "o_custkey", "cust_day")


def supps_together(spark: SparkSession, sf: str) -> DataFrame:
    return together(read(spark, sf, "lineitem", "l_orderkey", "l_suppkey"), ["l_orderkey"], "l_suppkey", "supps")


def vec_neighbors(spark: SparkSession, sf: str, most: int = 5, block: int = 1024) -> DataFrame:
    """Nearest neighbours by cosine, to 9 digits, ties by id: blocks of vectors against blocks, the best of every row kept.

    Every vector meets every other one, as exact search in all directions does; this graph is an oracle for small
    collections, not a way for large ones.
    """
    vec = read(spark, sf, "embeddings", "vec_id", "embedding")
    n_blocks = max(1, -(-vec.count() // block))
    packed = vec.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks))).groupBy("b").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("rows"))
    sides = packed.select(F.col("b").alias("x"), F.col("rows").alias("p")).join(packed.select(F.col("b").alias("y"), F.col("rows").alias("q")))

    def run(batches):
        for b in batches:
            out = []
            for p, q in zip(b.column("p").to_pylist(), b.column("q").to_pylist()):
                ip, iq = np.array([r["vec_id"] for r in p]), np.array([r["vec_id"] for r in q])
                vp, vq = (np.array([r["embedding"] for r in s], dtype=np.float64) for s in (p, q))
                vp, vq = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12) for v in (vp, vq))
                sim = np.round(vp @ vq.T, 9)
                sim[ip[:, None] == iq[None, :]] = -2
                for i, row in enumerate(sim):
                    best = np.lexsort((iq, -row))[:most]
                    out += [(int(ip[i]), int(iq[j]), float(row[j])) for j in best if row[j] > -2]
            cols = list(zip(*out)) if out else [[], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()))], names=["a", "b", "sim"])

    from pyspark.sql import Window as W

    near = sides.select("p", "q").mapInArrow(run, "a long, b long, sim double")
    near = near.withColumn("r", F.row_number().over(W.partitionBy("a").orderBy(F.desc("sim"), "b"))).filter(F.col("r") <= most)
    return canonical_edges(near, "a", "b", "vec")


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "parts": parts_together, "cust_supp": cust_supp, "part_supp": part_supp, "users_minute": users_minute,
    "doc_lines": doc_lines, "page_links": page_links, "cust_day": cust_day, "supps": supps_together,
}



def users_minute_groups(spark: SparkSession, sf: str) -> Groups:
    ev = read(spark, sf, "events", "ts", "user_id").select(F.lit("users_minute").alias("graph"), F.lit(0).cast("long").alias("part"), F.date_trunc("minute", "ts").alias("grp"), F.col("user_id").cast("long").alias("m"))
    return Groups(ev.dropna().distinct())


def cust_day_groups(spark: SparkSession, sf: str) -> Groups:
    """Customers of a nation are a part of their own."""
    o = read(spark, sf, "orders", "o_custkey", "o_orderdate").join(read(spark, sf, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return Groups(o.select(F.lit("cust_day").alias("graph"), F.col("c_nationkey").cast("long").alias("part"), F.col("o_orderdate").alias("grp"), F.col("o_custkey").cast("long").alias("m")).dropna().distinct())


#: Graphs whose groups grow with the tables, so that their edges are better not written down.
GROUPED = {"users_minute": users_minute_groups, "cust_day": cust_day_groups}


def graph_of(spark: SparkSession, sf: str, name: str) -> DataFrame | Groups:
    return GROUPED.get(name, GRAPHS.get(name))(spark, sf)


SQL: dict[str, str] = {
    "parts": "SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "supps": "SELECT DISTINCT a.l_suppkey AS u, b.l_suppkey AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey",
    "cust_supp": "SELECT DISTINCT least(2 * o_custkey, 2 * l_suppkey + 1) AS u, greatest(2 * o_custkey, 2 * l_suppkey + 1) AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "part_supp": "SELECT DISTINCT least(2 * l_partkey, 2 * l_suppkey + 1) AS u, greatest(2 * l_partkey, 2 * l_suppkey + 1) AS v FROM lineitem",
    "users_minute": "SELECT DISTINCT a.user_id AS u, b.user_id AS v FROM events a JOIN events b ON date_trunc('minute', a.ts) = date_trunc('minute', b.ts) AND a.user_id < b.user_id",
    "doc_lines": (
        "SELECT DISTINCT a.doc_id AS u, b.doc_id AS v FROM (SELECT * FROM dl WHERE line IN (SELECT line FROM dl GROUP BY line HAVING count(*) BETWEEN 2 AND 50)) a "
        "JOIN dl b ON a.line = b.line AND a.doc_id < b.doc_id"
    ),
    "page_links": (
        "SELECT DISTINCT least(2 * page_id, t) AS u, greatest(2 * page_id, t) AS v FROM (SELECT page_id, 2 * CAST('0x' || substr(md5(h), 1, 15) AS BIGINT) + 1 AS t "
        "FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages))"
    ),
    "cust_day": (
        "SELECT DISTINCT a.o_custkey AS u, b.o_custkey AS v FROM (SELECT o_custkey, o_orderdate, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey) a "
        "JOIN (SELECT o_custkey, o_orderdate, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey) b "
        "ON a.o_orderdate = b.o_orderdate AND a.c_nationkey = b.c_nationkey AND a.o_custkey < b.o_custkey"
    ),
}
_LINES = "dl AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents) WHERE length(line) >= 20), "


def with_graph(name: str, rest: str, recursive: bool = False) -> str:
    """SQL that begins with g (edges), deg and blk (degree, size) of a graph."""
    return (
        f"WITH {'RECURSIVE ' if recursive else ''}{_LINES if name == 'doc_lines' else ''}g AS ({SQL[name]}), "
        "deg AS (SELECT x AS v, CAST(count(*) AS INT) AS degree FROM (SELECT u AS x FROM g UNION ALL SELECT v FROM g) GROUP BY x), "
        f"blk AS (SELECT degree, count(*) AS size FROM deg GROUP BY degree) {rest}"
    )


def grow_family(spark: SparkSession, specs: list[tuple[int, int]], seed: int = 7) -> DataFrame:
    """edges(graph, u, v) of preferential-attachment graphs, one per (m0, t): vertex m0 + s joins m0 distinct earlier ones.

    No state is shared. Draw slots are numbered; a slot's two ends are its step's new vertex and the vertex it drew, and to
    draw is to take an end of an earlier slot (or a first vertex) by hash, so vertices are drawn in proportion to
    their degree; drawn ends are chased back until a fixed one. What a step has drawn twice it draws again, and
    in the end it takes first vertices. Copies refer to the first draw of a slot.
    """
    rows = spark.createDataFrame([(f"grow_m{m}_t{t}", m, t) for m, t in specs], "graph string, m0 long, t long")
    steps = rows.select("graph", "m0", F.explode(F.sequence(F.lit(0).cast("long"), F.col("t") - 1)).alias("step"))
    return attach(steps.repartition("graph", F.pmod("step", F.lit(64))), seed)


def attach(steps: DataFrame, seed: int = 7) -> DataFrame:
    """edges(graph, u, v) of the steps(graph, m0, step) of such graphs."""
    m0 = F.col("m0")
    whole = lambda c: F.floor(c).cast("long")

    def chase(j):
        begin = F.struct((F.col("step") * m0 + j % m0).alias("slot"), whole(j / m0).alias("again"), (F.col("step") * m0 * 2).alias("limit"), F.lit(None).cast("long").alias("done"))

        def back(s, _):
            # in an array, lest the hash is taken for every use of the place
            number = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), s["slot"].cast("string"), s["again"].cast("string"))), 1, 15), 16, 10).cast("long")

            def moved(p):
                place = p - m0
                slot = whole(place / 2)
                fixed = F.when(p < m0, p).when(place % 2 == 0, whole(slot / m0) + m0)
                return F.struct(slot.alias("slot"), F.lit(0).cast("long").alias("again"), (whole(slot / m0) * m0 * 2).alias("limit"), fixed.cast("long").alias("done"))

            step = F.get(F.transform(F.array(number % (s["limit"] + m0)), moved), F.lit(0))
            return F.when(s["done"].isNotNull(), s).otherwise(step)

        return F.aggregate(F.sequence(F.lit(1), F.lit(64)), begin, back, lambda s: s["done"])

    drawn = F.transform(F.sequence(F.lit(0).cast("long"), 4 * m0 - 1), chase)
    ends = F.slice(F.array_distinct(F.concat(drawn, F.sequence(F.lit(0).cast("long"), m0 - 1))), F.lit(1), m0.cast("int"))
    return steps.select("graph", F.explode(ends).alias("u"), (F.col("step") + m0).alias("v"))


def grow_customers(spark: SparkSession, sf: str, m0: int = 3) -> DataFrame:
    """The generator with a step for every customer, in the order of their keys."""
    return attach(read(spark, sf, "customer", "c_custkey").select(F.lit("customers").alias("graph"), F.lit(m0).cast("long").alias("m0"), F.col("c_custkey").cast("long").alias("step")))


def grow(spark: SparkSession, m0: int, t: int, seed: int = 7) -> DataFrame:
    return grow_family(spark, [(m0, t)], seed)


def grow_sql(m0: int, t: int | str, rest: str, seed: int = 7) -> str:
    """The same in SQL: g (edges), deg and blk, then the rest. t: the number of steps, or a query for them."""
    steps = f"range({t})" if isinstance(t, int) else f"({t})"
    return f"""WITH RECURSIVE r(st, j, slot, again, lim, done) AS (
  SELECT CAST(st AS BIGINT), CAST(j AS BIGINT), CAST(st * {m0} + j % {m0} AS BIGINT), CAST(j // {m0} AS BIGINT), CAST(st * {m0} * 2 AS BIGINT), CAST(NULL AS BIGINT)
  FROM {steps} a(st), range({4 * m0}) b(j)
  UNION ALL
  SELECT st, j, (p - {m0}) // 2, CAST(0 AS BIGINT), ((p - {m0}) // 2 // {m0}) * {m0} * 2, CASE WHEN p < {m0} THEN p WHEN (p - {m0}) % 2 = 0 THEN (p - {m0}) // 2 // {m0} + {m0} END
  FROM (SELECT *, CAST('0x' || substr(md5('{seed}:' || slot || ':' || again), 1, 15) AS BIGINT) % (lim + {m0}) AS p FROM r WHERE done IS NULL)),
c AS (SELECT st, j, done FROM r WHERE done IS NOT NULL UNION ALL SELECT st, {4 * m0} + i, i FROM {steps} a(st), range({m0}) b(i)),
f AS (SELECT st, done, min(j) AS j FROM c GROUP BY 1, 2),
g AS (SELECT done AS u, st + {m0} AS v FROM (SELECT *, row_number() OVER (PARTITION BY st ORDER BY j) AS rn FROM f) WHERE rn <= {m0}),
deg AS (SELECT x AS v, CAST(count(*) AS INT) AS degree FROM (SELECT u AS x FROM g UNION ALL SELECT v FROM g) GROUP BY x),
blk AS (SELECT degree, count(*) AS size FROM deg GROUP BY degree) {rest}"""
