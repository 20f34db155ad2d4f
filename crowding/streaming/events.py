"""Structured streaming over events: graphs of windows, sessions, late rows, repeats, and running degrees."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from crowding.operators import graph as g
from crowding.plans.workloads import read, together
from crowding.sources.store import scratch

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def as_files(events: DataFrame, files: int = 4) -> str:
    """Events as files in order of time, written one after another, as a stream reads files by their age."""
    path = scratch(events.sparkSession, "event-files")
    rows = events.select("event_id", "ts", "user_id", "event_type", "value", "props").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("at", F.unix_micros("ts"))
    cuts = rows.agg(F.percentile_approx("at", [i / files for i in range(1, files)], 10_000)).first()[0] or []
    edges = [None, *cuts, None]
    for low, high in zip(edges, edges[1:]):
        part = rows if low is None else rows.filter(F.col("at") >= low)
        part = part if high is None else part.filter(F.col("at") < high)
        part.drop("at").coalesce(1).write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(path)


def run_to_table(df: DataFrame, mode: str = "append", each=None) -> DataFrame:
    """Run what is there through the stream, and return what it wrote."""
    spark = df.sparkSession
    out, mark = scratch(spark, "stream-out"), scratch(spark, "stream-mark")
    if each is not None or mode != "append":

        def put(batch: DataFrame, i: int) -> None:
            # a batch that is run again replaces its own folder
            (each(batch, i) if each is not None else batch).write.mode("overwrite").parquet(f"{out}/batch={i}")

        q = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", mark).trigger(availableNow=True).start()
    else:
        q = df.writeStream.outputMode(mode).format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)


def minute_users(events: DataFrame, width: str = "1 minute", late: str = "10 minutes") -> DataFrame:
    """Users of every window once."""
    counted = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("at"), "user_id", "n")


def stream_minute_blocks(spark: SparkSession, sf: str) -> DataFrame:
    """Blocks of the users-in-one-minute graph, from what the stream has closed."""
    users = run_to_table(minute_users(stream(spark, as_files(read(spark, sf, "events")))))
    edges = together(users, ["at"], "user_id", "stream")
    return g.block_sequence(g.degrees(edges)).select("degree", "size")


def stream_session_users(spark: SparkSession, sf: str) -> DataFrame:
    """Sessions of a user, ended by 30 minutes of silence: how many, and events in them (complete mode: last batch counts)."""
    ev = stream(spark, as_files(read(spark, sf, "events")))
    s = ev.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    out = run_to_table(s.select(F.col("w.start").alias("start"), "user_id", "n"), "complete")
    last = out.agg(F.max("batch")).first()[0]
    return out.filter(F.col("batch") == last).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n_events"))


def stream_late_dropped(spark: SparkSession, sf: str) -> DataFrame:
    """Rows two hours late, in a file of their own at the end, leave no trace; (rows sent late, windows they are in)."""
    ev = read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = as_files(ev)
    top = ev.agg(F.max("ts")).first()[0]
    late = ev.orderBy(F.desc("ts")).limit(20).withColumn("event_id", F.col("event_id") + 10**9).withColumn("ts", (F.lit(top) - F.expr("INTERVAL 2 HOURS")).cast("timestamp"))
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    # rows are held against the watermark of the batch before last: one more row lets the last file count
    beat = ev.orderBy(F.desc("ts")).limit(1).withColumn("event_id", F.col("event_id") + 2 * 10**9)
    for rows in (beat, late):
        rows.select(*names).coalesce(1).write.mode("append").parquet(path)
    s = stream(spark, path).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.sum(F.col("event_id").between(10**9, 2 * 10**9 - 1).cast("long")).alias("late"))
    out = run_to_table(s.select(F.col("w.start").alias("at"), "late"))
    return out.agg(F.sum("late").alias("late_counted"))


def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    """Every event sent twice, counted once by type."""
    ev = read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = as_files(ev)
    ev.select(*[c.split()[0] for c in SCHEMA.split(", ")]).repartitionByRange(4, "ts").write.mode("append").parquet(path)
    once = spark.readStream.schema(SCHEMA).parquet(path).withWatermark("ts", "1 hour").dropDuplicates(["event_id", "ts"])
    return run_to_table(once.select("event_id", "event_type")).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def stream_running_degrees(spark: SparkSession, sf: str) -> DataFrame:
    """Distinct event types of every user by a stateful function; the last state of each user."""

    def keep(key, parts, state: GroupState):
        seen, n = set(state.get[0].split(",")) - {""} if state.exists else set(), state.get[1] if state.exists else 0
        for p in parts:
            seen |= set(p["event_type"].dropna())
            n += len(p)
        state.update((",".join(sorted(seen)), n))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [len(seen)], "n_events": [n]})

    ev = stream(spark, as_files(read(spark, sf, "events")))
    s = ev.groupBy("user_id").applyInPandasWithState(keep, "user_id long, degree long, n_events long", "types string, n long", "update", GroupStateTimeout.NoTimeout)
    out = run_to_table(s, "update")
    return out.groupBy("user_id").agg(F.max("degree").alias("degree"), F.max("n_events").alias("n_events"))


def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    """Events joined with customers of the same id as they come, counted by segment."""
    cust = read(spark, sf, "customer", "c_custkey", "c_mktsegment")
    ev = stream(spark, as_files(read(spark, sf, "events"))).select("event_id", "user_id")
    return run_to_table(ev.join(cust, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


def stream_exposed(spark: SparkSession, sf: str) -> DataFrame:
    """foreachBatch: every batch's user graph by minute, with the block sizes of its users. (users seen, whether every
    user of a batch stands in one block of it, whether blocks add up)"""

    def each(batch: DataFrame, i: int) -> DataFrame:
        users = batch.select(F.lit("b").alias("graph"), F.col("user_id").cast("long").alias("v")).distinct()
        edges = together(batch.select(F.date_trunc("minute", "ts").alias("at"), "user_id"), ["at"], "user_id", "b")
        deg = g.degrees(edges, users)
        return deg.join(g.block_sequence(deg), ["graph", "degree"]).join(g.exposed_vertices(deg, 3).select("v", F.lit(True).alias("exposed")), "v", "left").select("v", "degree", "size", F.coalesce("exposed", F.lit(False)).alias("exposed"))

    out = run_to_table(stream(spark, as_files(read(spark, sf, "events"))), "append", each)
    blocks = out.groupBy("batch", "degree").agg(F.count(F.lit(1)).alias("n"), F.max("size").alias("size"), F.bool_and(F.col("exposed") == (F.col("size") < 3)).alias("told"))
    seen = out.agg(F.count_distinct("v").alias("n_users"))
    return seen.crossJoin(blocks.agg(F.bool_and(F.col("n") == F.col("size")).alias("blocks_add_up"), F.bool_and("told").alias("exposed_told")))  # a row each
