"""Streams of events as streams of edges: windows, sessions, repeats, state, and warm starts of unseen nodes."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from datetime import datetime

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, sf_dir: str, late: str = "1 hour", close: str | None = None) -> DataFrame:
    """The events table as a stream with a watermark; close: a folder of rows that follow the events."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    raw = raw if close is None else raw.unionAll(spark.readStream.schema(EVENTS).parquet(close))
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def tumbling(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def users_by_hour(events: DataFrame) -> DataFrame:
    """(start, users): the distinct users of each hour, the rows of which coactive edges are made."""
    return events.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.array_sort(F.collect_set("user_id")).alias("users")).select(F.col("w.start").alias("start"), "users")


def part_traffic(events: DataFrame, parts: DataFrame) -> DataFrame:
    """Events by part and hour: a stream-static join with parts(node, part)."""
    return events.join(parts, events["user_id"] == parts["node"]).groupBy(F.window("ts", "1 hour").alias("w"), "part").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "part", "n")


def unique_events(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def followed(left: DataFrame, right: DataFrame, minutes: int = 10) -> DataFrame:
    """Pairs of one user's events, the second within so many minutes: a stream-stream interval join."""
    a = left.select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("e1"))
    b = right.select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("e2"))
    return a.join(b, F.expr(f"u = user_id and t2 > t1 and t2 <= t1 + interval {minutes} minutes")).select("user_id", "e1", "e2", "t1", "t2")


def running_mean(events: DataFrame) -> DataFrame:
    """Each user's running count and mean, in keyed state."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: object) -> Iterator[pd.DataFrame]:
        n, s = state.get if state.exists else (0, 0.0)
        for b in batches:
            n, s = n + len(b), s + float(b["value"].sum())
        state.update((n, s))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [s / max(n, 1)]})

    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, mean double", "n long, s double", "update", "NoTimeout")


def run_to_table(stream: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Run a bounded stream to its end into an in-memory table."""
    w = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    w = w.option("checkpointLocation", checkpoint) if checkpoint else w
    q = w.start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def run_to_parquet(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Run a bounded append stream to its end into Parquet: nothing passes through the driver."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def run_to_close(make: Callable[[DataFrame], DataFrame], spark: SparkSession, sf_dir: str, path: str, checkpoint: str, close: str) -> DataFrame:
    """Run a windowed append stream of the events to its end into Parquet, open windows included.

    Only when all events are read, one row of a far time follows them from
    the folder `close`: it moves the watermark past every window but its own.
    """
    row = lambda ts: spark.createDataFrame(ts, "ts timestamp_ntz").selectExpr("null event_id", "ts", "null user_id", "null event_type", "null value", "null props").selectExpr(*(f"cast({c.split()[0]} as {c.split()[1]}) {c.split()[0]}" for c in EVENTS.split(", ")))
    row([]).write.parquet(close)
    for ts in ([], [(datetime(9000, 1, 1),)]):
        if ts:
            row(ts).write.mode("append").parquet(close)
        out = run_to_parquet(make(source(spark, sf_dir, close=close)), path, checkpoint)
    return out


def warm_start(emb: DataFrame, new_edges: DataFrame) -> DataFrame:
    """(node, vec) of nodes that emb lacks: the mean of their known neighbours."""
    from ..functions.vec import sum_vectors
    from ..operators.graph import arcs

    unseen = arcs(new_edges.select("src", "dst")).join(emb.select(F.col("node").alias("src")), "src", "left_anti")
    s = sum_vectors(unseen.join(emb.select(F.col("node").alias("dst"), "vec"), "dst").select(F.col("src").alias("node"), "vec"))
    return s.select("node", F.transform("vec", lambda x: x / F.col("n")).alias("vec"))


def maintain(stream: DataFrame, parts: DataFrame, path: str, checkpoint: str) -> None:
    """foreachBatch: append each batch's abstract-edge counts to a table keyed by batch, so a replayed batch overwrites itself."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        from ..operators.abstract import abstract_edges

        abstract_edges(batch.select("src", "dst"), parts).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
