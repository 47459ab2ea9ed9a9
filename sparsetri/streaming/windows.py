"""Windowed operators on the event stream.  Every run is AvailableNow over files and appends to Parquet in the shared folder."""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import coin52
from ..plans.store import folder, stored
from ..sources.edges import half_edges

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf: str, delay: str | None = "1 hour") -> DataFrame:
    """Watermarks need an instant, so local times are read as the session's."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(f"{sf}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))
    return s.withWatermark("ts", delay) if delay else s


def run_to_table(stream: DataFrame, what: str, mode: str = "append") -> DataFrame:
    """Runs a query over all that is available and returns its sink as a table."""
    spark = stream.sparkSession
    out = folder(spark, what)
    query = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{out}-log").format("parquet").option("path", out).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def run_by_batches(stream: DataFrame, write, what: str, mode: str = "append") -> None:
    """foreachBatch with AvailableNow; write(batch, id) must overwrite what it wrote for the same id, so replays do no harm."""
    query = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", folder(stream.sparkSession, f"{what}-log")).foreachBatch(write).start()
    query.awaitTermination()


def tumbling_users(stream: DataFrame, length: str = "1 hour") -> DataFrame:
    out = stream.groupBy(F.window("ts", length).alias("w")).agg(F.count(F.lit(1)).alias("n_events"), F.sum(F.col("event_type").isin("purchase").cast("long")).alias("n_purchases"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n_events", "n_purchases")


def window_members(stream: DataFrame, length: str = "1 hour", step: str | None = None) -> DataFrame:
    """(start, event_type, user_id), each once, of windows that the watermark has closed: users that share a type in a window are joined by an edge.
    State is a row for each member of an open window; pairs are made of closed windows only."""
    out = stream.groupBy(F.window("ts", length, step or length).alias("w"), "event_type", "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "user_id")


def window_edges(members: DataFrame) -> DataFrame:
    """(start, u, v): the distinct edges of each window."""
    a, b = members.withColumnRenamed("user_id", "u"), members.withColumnRenamed("user_id", "v")
    return a.join(b, ["start", "event_type"]).where("u < v").select("start", "u", "v").distinct()


def window_edge_counts(members: DataFrame) -> DataFrame:
    """(start, m): how many distinct edges each window has, without making them: users of the very same types are one row with their number, and rows
    whose types overlap are joined."""
    own = members.where("user_id is not null and event_type is not null")
    types = sorted(r[0] for r in own.select("event_type").distinct().limit(64).collect())
    if len(types) < 64:  # a set of types is a number
        place = F.array_position(F.array(*map(F.lit, types)), F.col("event_type")) if types else F.lit(1)
        kind, overlap = F.bit_or(F.expr("shiftleft(1L, place - 1)")), F.expr("kind & kind2") != 0
        own = own.withColumn("place", place.cast("int"))
    else:
        kind, overlap = F.array_sort(F.collect_set("event_type")), F.arrays_overlap("kind", "kind2")
    own = own.groupBy("start", "user_id").agg(kind.alias("kind"))
    kinds = stored(own.groupBy("start", "kind").agg(F.count(F.lit(1)).alias("n")), "window-kinds")
    pairs = kinds.join(kinds.select("start", F.col("kind").alias("kind2"), F.col("n").alias("n2")), "start").where((F.col("kind") <= F.col("kind2")) & overlap)
    pairs = pairs.select("start", F.when(F.col("kind") == F.col("kind2"), F.expr("n * (n - 1) div 2")).otherwise(F.col("n") * F.col("n2")).alias("m"))
    return pairs.groupBy("start").agg(F.sum("m").alias("m")).where("m > 0")


def sliding_members(panes: DataFrame, step_minutes: int = 15, length_minutes: int = 60) -> DataFrame:
    """Members of windows that slide by whole panes, from those of the panes: a stream's state then has a member once, not once for each window around it."""
    back = F.explode(F.sequence(F.lit(0), F.lit(length_minutes - step_minutes), F.lit(step_minutes)))
    return panes.select(back.alias("back"), "start", "event_type", "user_id").select((F.col("start") - F.expr("make_dt_interval(0, 0, back)")).alias("start"), "event_type", "user_id")


def window_triangles(edges: DataFrame, colours: int = 2, seed: int = 3) -> DataFrame:
    """(start, m, t, t_est): edges and triangles of each window, and the estimate from edges whose ends have one colour."""

    def count(e: DataFrame, name: str) -> DataFrame:
        ab, ac, bc = (e.select("start", F.col("u").alias(x), F.col("v").alias(y)) for x, y in ("ab", "ac", "bc"))
        return ab.join(bc, ["start", "b"]).join(ac, ["start", "a", "c"]).groupBy("start").agg(F.count(F.lit(1)).alias(name))

    one = lambda c: coin52(seed, F.lit("colour"), c) % colours
    out = edges.groupBy("start").agg(F.count(F.lit(1)).alias("m")).join(count(edges, "t"), "start", "left").join(count(edges.where(one("u") == one("v")), "kept"), "start", "left")
    return out.select("start", "m", F.coalesce("t", F.lit(0)).alias("t"), (F.coalesce("kept", F.lit(0)) * colours**2).alias("t_est"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions of a user; n_edges: the types that the session joins its user to."""
    out = stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n_events"), F.size(F.collect_set("event_type")).cast("long").alias("n_edges"))
    return out.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), "n_events", "n_edges")


def dedupe(stream: DataFrame) -> DataFrame:
    """Edges (user, type) of an hour, each once: the methods assume each edge once.  The state of an edge goes when the watermark has passed it."""
    keyed = stream.withColumn("hour", F.date_trunc("hour", "ts"))
    return keyed.dropDuplicatesWithinWatermark(["user_id", "event_type", "hour"]).select("user_id", "event_type", F.col("hour").cast("timestamp_ntz").alias("hour"))


def late_counts(spark: SparkSession, batches: list[DataFrame], length: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """(start, n_counted, n_late): what a windowed count sees of batches that arrive one after the other, and what came after its window was closed."""
    path = folder(spark, "late")
    for k, b in enumerate(batches):
        b.select(F.col("ts").cast("timestamp").alias("ts"), F.lit(k).alias("batch")).coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)  # files arrive in the order of their times, which some file systems keep by the second
    every = spark.read.schema("ts timestamp, batch int").parquet(path)
    stream = spark.readStream.schema(every.schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", delay)
    counted = run_to_table(stream.groupBy(F.window("ts", length).alias("w")).agg(F.count(F.lit(1)).alias("n_counted")).select(F.col("w.start").alias("start"), "n_counted"), "late-counts")
    whole = every.groupBy(F.window("ts", length).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")
    return whole.join(counted, "start").select(F.col("start").cast("timestamp_ntz").alias("start"), "n_counted", (F.col("n") - F.col("n_counted")).alias("n_late"))


def running_degrees(edges: DataFrame) -> DataFrame:
    """(x, d) by a stateful operator: a counter for each vertex of a stream of edges, updated batch by batch; the last update is the degree."""

    def count(key: tuple, rows, state: GroupState):
        d = (state.get[0] if state.exists else 0) + sum(len(r) for r in rows)
        state.update((d,))
        yield pd.DataFrame({"x": [key[0]], "d": [d]})

    counted = half_edges(edges).groupBy("x").applyInPandasWithState(count, "x long, d long", "d long", "update", GroupStateTimeout.NoTimeout)
    out = folder(edges.sparkSession, "running-degrees")
    run_by_batches(counted, lambda b, i: b.write.mode("overwrite").parquet(f"{out}/batch={i}"), "running-degrees", "update")
    return edges.sparkSession.read.schema("x long, d long").parquet(f"{out}/*").groupBy("x").agg(F.max("d").alias("d"))


def co_activity(left: DataFrame, right: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream interval join: different users, same type, at most `minutes` apart."""
    a = left.select(F.col("event_id").alias("a"), F.col("ts").alias("ts_a"), F.col("user_id").alias("user_a"), F.col("event_type").alias("type_a"))
    b = right.select(F.col("event_id").alias("b"), F.col("ts").alias("ts_b"), F.col("user_id").alias("user_b"), F.col("event_type").alias("type_b"))
    near = F.expr(f"type_a = type_b AND user_a < user_b AND ts_b >= ts_a - interval {minutes} minutes AND ts_b <= ts_a + interval {minutes} minutes")
    return a.join(b, near).select("a", "b", "user_a", "user_b")
