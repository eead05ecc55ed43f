"""Queries that run a bounded stream to its end; their oracles are batch SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..plans.storage import stash, stash_path
from ..streaming import edges as st

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _run(stream: DataFrame, mode: str = "complete") -> DataFrame:
    spark = stream.sparkSession
    return st.run_to_table(stream, f"s{uuid.uuid4().hex}", mode, stash_path(spark, "stream"))


def _add(name: str, sql: str | None, f) -> None:  # noqa: ANN001
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


_add("stream_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2",
     lambda s, sf: _run(st.tumbling(st.source(s, sf))).withColumn("start", F.col("start").cast("timestamp_ntz")))
_add("stream_sliding", "SELECT CAST(h AS TIMESTAMP) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT event_type, value, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY 1, 2",
     lambda s, sf: _run(st.tumbling(st.source(s, sf), "2 hours", "1 hour")).withColumn("start", F.col("start").cast("timestamp_ntz")))
_add("stream_session", "SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n FROM (SELECT user_id, ts, sum(k) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS k FROM events)) GROUP BY user_id, g",
     lambda s, sf: st.run_to_close(st.sessions, s, sf, stash_path(s, "sessions"), stash_path(s, "stream"), stash_path(s, "close")).withColumn("start", F.col("start").cast("timestamp_ntz")).withColumn("end", F.col("end").cast("timestamp_ntz")))
_add("stream_abstract_edges", "SELECT CAST(a.user_id % 7 AS INTEGER) AS src, CAST(b.user_id % 7 AS INTEGER) AS dst, count(*) AS w FROM (SELECT DISTINCT date_trunc('hour', ts) AS h, user_id FROM events) a JOIN (SELECT DISTINCT date_trunc('hour', ts) AS h, user_id FROM events) b ON a.h = b.h AND a.user_id % 7 < b.user_id % 7 GROUP BY 1, 2",
     lambda s, sf: _abstract(s, sf))
_add("stream_part_traffic", "SELECT date_trunc('hour', ts) AS start, CAST(user_id % 7 AS INTEGER) AS part, count(*) AS n FROM events GROUP BY 1, 2",
     lambda s, sf: _run(st.part_traffic(st.source(s, sf), _parts(s, sf))).withColumn("start", F.col("start").cast("timestamp_ntz")))
_add("stream_unique", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1",
     lambda s, sf: st.run_to_parquet(st.unique_events(st.source(s, sf)), stash_path(s, "unique"), stash_path(s, "stream")).groupBy("event_type").agg(F.count("*").alias("n")))
_add("asof_latest_order", "SELECT event_id, max(o_orderkey) AS o_orderkey FROM (SELECT e.event_id, o.o_orderkey, rank() OVER (PARTITION BY e.event_id ORDER BY o.o_orderdate DESC) AS r FROM events e JOIN orders o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts) WHERE r = 1 GROUP BY 1", lambda s, sf: _asof(s, sf))


def _parts(s: SparkSession, sf: str) -> DataFrame:
    return s.read.parquet(f"{sf}/events.parquet").select("user_id").distinct().select(F.col("user_id").alias("node"), (F.col("user_id") % 7).cast("int").alias("part"))


def _abstract(s: SparkSession, sf: str) -> DataFrame:
    """Hourly users come from the stream; counts of parts per hour make the pairs, so no pair of users is formed."""
    hours = _run(st.users_by_hour(st.source(s, sf)))
    n = hours.select("start", F.explode("users").alias("u")).groupBy("start", (F.col("u") % 7).cast("int").alias("part")).agg(F.count("*").alias("n"))
    n = stash(n, "hours")
    both = n.join(n.select("start", F.col("part").alias("dst"), F.col("n").alias("m")), "start").where("part < dst")
    return both.groupBy(F.col("part").alias("src"), "dst").agg(F.sum(F.col("n") * F.col("m")).alias("w"))


def _asof(s: SparkSession, sf: str) -> DataFrame:
    """As-of join: events and orders in one timeline per customer, the last order carried forward."""
    from pyspark.sql import Window

    e = s.read.parquet(f"{sf}/events.parquet").select(F.col("user_id").alias("k"), "ts", "event_id", F.lit(None).cast("long").alias("o"))
    o = s.read.parquet(f"{sf}/orders.parquet").groupBy("o_custkey", "o_orderdate").agg(F.max("o_orderkey").alias("o"))
    line = e.unionAll(o.select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), "o"))
    w = Window.partitionBy("k").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return line.withColumn("o_orderkey", F.last("o", ignorenulls=True).over(w)).where("event_id is not null and o_orderkey is not null").select("event_id", "o_orderkey")
