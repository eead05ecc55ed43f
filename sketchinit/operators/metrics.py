"""What the experiments measure: loss, cut, balance, gains, repeated runs, and the cost in Spark."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.vec import dot, euclid


def reconstruction(edges: DataFrame, emb: DataFrame, theta: str = "dot") -> float:
    """Sum over all ordered pairs of (A - theta)^2, from one pass over the edges and one over the vectors.

    edges(src, dst[, w]); theta: dot, cosine, euclid_distance or neg_distance. The diagonal counts with A = 0.
    """
    w = F.col("w") if "w" in edges.columns else F.lit(1.0)
    if theta == "cosine":
        emb = emb.select("node", F.transform("vec", lambda x: x / F.greatest(F.sqrt(dot(F.col("vec"), F.col("vec"))), F.lit(1e-12))).alias("vec"))
    e = edges.join(emb.select(F.col("node").alias("src"), F.col("vec").alias("x")), "src").join(emb.select(F.col("node").alias("dst"), F.col("vec").alias("y")), "dst")
    sign = -1.0 if theta == "neg_distance" else 1.0
    t = dot(F.col("x"), F.col("y")) if theta in ("dot", "cosine") else euclid(F.col("x"), F.col("y")) * sign
    r = e.agg(F.sum(w * w), F.sum(w * t)).first()
    on = 2 * float(r[0] or 0) - 4 * float(r[1] or 0)
    if theta in ("dot", "cosine"):
        return on + _gram(emb)
    n = emb.count()
    sums = emb.select(F.posexplode("vec").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("s"), F.sum(F.col("v") * F.col("v")).alias("q")).agg(F.sum("q"), F.sum(F.col("s") * F.col("s"))).first()
    return on + 2 * n * float(sums[0] or 0) - 2 * float(sums[1] or 0)


def _gram(emb: DataFrame) -> float:
    """Sum of the squares of the vectors' product matrix: each task adds up its own d x d sums, the driver sees nothing but the total."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: np.ndarray | None = None
        for b in batches:
            if b.num_rows:
                x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
                total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size)), pa.array(total.ravel())], names=["at", "s"])

    cells = emb.select(F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "at long, s double").groupBy("at").agg(F.sum("s").alias("s"))
    return float(cells.agg(F.sum(F.col("s") * F.col("s"))).first()[0] or 0)


def gain(a: float, b: float) -> float:
    """How much a is better than b, relative to b."""
    return (a - b) / b


def repeat(fn: Callable[[int], float], n: int = 10) -> dict[str, float]:
    """Mean, deviation and standard error over n seeds."""
    v = [fn(seed) for seed in range(n)]
    dev = statistics.stdev(v) if n > 1 else 0.0
    return {"mean": statistics.fmean(v), "stddev": dev, "stderr": dev / n**0.5, "runs": n}


def timed(fn: Callable[[], DataFrame]) -> float:
    """Seconds until the whole result was produced (written to the noop sink)."""
    t = time.time()
    fn().write.format("noop").mode("overwrite").save()
    return time.time() - t


def spark_cost(spark: SparkSession, fn: Callable[[], object]) -> dict[str, float]:
    """Jobs, stages, tasks, seconds, and records and bytes shuffled or spilled that fn used, from the status store."""
    tracker = spark.sparkContext.statusTracker()
    group = f"cost-{time.time_ns()}"
    spark.sparkContext.setJobGroup(group, "measured")
    t = time.time()
    fn()
    took = time.time() - t
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    store = spark.sparkContext._jsc.sc().statusStore()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs for s in (tracker.getJobInfo(j).stageIds if tracker.getJobInfo(j) else [])}
    out = {"seconds": took, "jobs": len(jobs), "stages": 0, "tasks": 0, "shuffle_bytes": 0, "shuffle_records": 0, "spilled_bytes": 0}
    for s in stages:
        info = store.lastStageAttempt(s)
        if info.numCompleteTasks():
            out["stages"] += 1
            out["tasks"] += info.numCompleteTasks()
            out["shuffle_bytes"] += info.shuffleWriteBytes()
            out["shuffle_records"] += info.shuffleWriteRecords()
            out["spilled_bytes"] += info.diskBytesSpilled()
    return out


QUERY_BLOCK = 2_000  # queries that one group compares with a batch of vectors


def nearest(emb: DataFrame, query: DataFrame, k: int = 10, sim: str = "cosine", digits: int = 6) -> DataFrame:
    """(query, node, rank, value): for each row of query(node, vec) the k most similar other rows of emb.

    Queries and vectors meet in pairs of blocks, each as one product of
    matrices; every pair of blocks keeps its best k, and those are ranked.
    Values are rounded to `digits`; ties go to the smaller node.
    """
    q = query.select(F.col("node").cast("long").alias("query"), F.col("vec").cast("array<double>").alias("qv"))
    e = emb.select(F.col("node").cast("long").alias("node"), F.col("vec").cast("array<double>").alias("vec"))
    cols, rows = (max(1, -(-df.count() // QUERY_BLOCK)) for df in (q, e))
    q = q.withColumn("i", F.pmod(F.xxhash64("query"), F.lit(cols)).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))))
    e = e.withColumn("j", F.pmod(F.xxhash64("node"), F.lit(rows)).cast("int")).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))))
    kind = "query long, node long, value double"

    def best(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({c: pa.array([], t) for c, t in (("query", pa.int64()), ("node", pa.int64()), ("value", pa.float64()))})
        b = b.sort_by("node")
        x, y = (t.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1) for t, c in ((a, "qv"), (b, "vec")))
        xs, ys = (x * x).sum(axis=1), (y * y).sum(axis=1)
        if sim == "cosine":
            with np.errstate(divide="ignore", invalid="ignore"):
                value = np.round(x @ y.T / np.sqrt(xs[:, None] * ys[None]), digits)
            order = np.where(np.isnan(value), np.inf, -value)
        else:
            value = np.round(np.sqrt(np.maximum(xs[:, None] + ys[None] - 2 * (x @ y.T), 0)), digits)
            order = value.copy()
        ids, qs = b.column("node").to_numpy(), a.column("query").to_numpy()
        order[qs[:, None] == ids[None]] = np.inf
        top = np.argsort(order, axis=1, kind="stable")[:, :k]
        r = np.repeat(np.arange(len(qs)), top.shape[1])
        c = top.ravel()
        some = np.isfinite(order[r, c])
        return pa.table({"query": pa.array(qs[r[some]]), "node": pa.array(ids[c[some]]), "value": pa.array(value[r[some], c[some]])})

    some = q.groupBy("i", "j").cogroup(e.groupBy("i", "j")).applyInArrow(best, kind)
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("value") if sim == "cosine" else F.asc("value"), "node"))
    return some.withColumn("rank", rank).where(F.col("rank") <= k).select("query", "node", "rank", "value")
