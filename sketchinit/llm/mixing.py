"""Mixing sources to target weights by balanced sampling (the cube method).

Sources share the words of the whole table by weight; a source's target stops
at `most` times its own words and the excess goes to the others by weight. A
source with ratio r = target / words takes every document floor(r) times and
a sample with inclusion probability frac(r) once more. The sample is drawn by
the flight phase of the cube method: probabilities move along the null space
of the balancing constraints (documents, words) until each is 0 or 1. It runs
in salted blocks of bounded size; what stays fractional in a block (fewer
units than constraints plus one) flies again with the leftovers of other
blocks, level by level, until one block for each source lands.

Edge cases: null text has size 0; a null source is a source of its own, last
in order; an empty table gives no rows; a table without words takes nothing;
repeated rows are separate units; the order of hashes breaks ties, so reruns
agree; only the named columns are read.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.storage import stash
from .memory import release_driver

BLOCK = 4000  # documents of one block of the flight phase
FAN = 500  # blocks whose leftovers fly together at the next level
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """Words of the whole text (null: 0): each word becomes one letter, so no array of words is held."""
    letters = F.translate(F.regexp_replace(text, WORD, "x"), " \t\n\x0b\f\r", "")
    return F.coalesce(F.char_length(letters), F.lit(0)).cast("long")


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, size): size counts the words of the whole text."""
    size = word_count(F.col(text_col))
    return docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"))


def targets(units: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = 3) -> DataFrame:
    """(source, source_size, target): one row for each source; only scalars reach the driver."""
    by = units.groupBy("source").agg(F.sum("size").alias("source_size"))
    nth = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1  # one row a source
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (nth % len(weights) + 1).cast("int"))
    by = stash(by.withColumn("weight", weight.cast("double")), "mix")
    total = float(by.agg(F.sum("source_size")).first()[0] or 0)
    cap, level, closed = F.col("source_size") * most, 0.0, -1
    while total:  # each round closes at least one more source, or ends
        full = cap < F.lit(level) * F.col("weight")
        r = by.agg(F.sum(F.when(full, cap)), F.sum(F.when(~full, F.col("weight"))), F.count_if(full)).first()
        if r[2] == closed or not r[1]:
            break
        closed, level = r[2], (total - float(r[0] or 0)) / r[1]
    return by.select("source", "source_size", F.least(cap.cast("double"), F.lit(level) * F.col("weight")).alias("target"))


def flight(p: np.ndarray, x: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Move the probabilities p until fewer than two constraints allow are fractional.

    x: one balancing variable; the other one is 1. Balance is kept on
    sum(p) and sum(p * x). u: one uniform number for each unit, that decides
    its step. Works on the three first fractional units at a time.
    """
    p, eps = p.astype(float).copy(), 1e-9
    held: list[int] = []
    for nxt in np.flatnonzero((p > eps) & (p < 1 - eps)).tolist():
        held.append(nxt)
        if len(held) < 3:
            continue
        a, b, c = (float(x[i]) for i in held)
        v = np.array([b - c, c - a, a - b])  # sums to 0, and weighted by x too
        if not v.any():
            v = np.array([1.0, -1.0, 0.0])
        q = p[held]
        with np.errstate(divide="ignore", invalid="ignore"):
            up = np.where(v > 0, (1 - q) / v, np.where(v < 0, -q / v, np.inf)).min()
            down = np.where(v > 0, q / v, np.where(v < 0, (q - 1) / v, np.inf)).min()
        q = q + up * v if u[nxt] * (up + down) < down else q - down * v
        p[held] = np.clip(q, 0, 1)
        held = [i for i in held if eps < p[i] < 1 - eps]
    return np.where(p < eps, 0, np.where(p > 1 - eps, 1, p))


def land(p: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Round the few fractional units so that the words, then the number of units, are closest to balance."""
    p = p.copy()
    open_ = np.flatnonzero((p > 0) & (p < 1))
    if len(open_):
        best = min(itertools.product((0, 1), repeat=len(open_)), key=lambda s: (abs(float(((np.array(s) - p[open_]) * x[open_]).sum())), abs(float((np.array(s) - p[open_]).sum())), s))
        p[open_] = best
    return p


def sample(units: DataFrame, block: int = BLOCK, fan: int = FAN, seed: int = 5) -> DataFrame:
    """units(source, size, p, key, ...) with p moved to 0 or 1 for every row. key: a long that orders and draws."""
    schema = units.schema
    names = list(schema.names)

    def fly(last: bool):  # noqa: ANN202
        def run(t: pa.Table) -> pa.Table:
            key, size = t.column("key").to_numpy().astype(np.int64), t.column("size").to_numpy()
            order = np.lexsort((size, key))
            t, key, size = t.take(pa.array(order)), key[order], size[order].astype(float)
            u = (((key.view(np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(11)).astype(float) / 2.0**53
            p = flight(t.column("p").to_numpy(), size, u)
            return t.set_column(t.column_names.index("p"), "p", pa.array(land(p, size) if last else p)).select(names if last else [*names, "_block"])

        return run

    counts = units.groupBy("source").agg(F.count("*").alias("_n"))
    blocks = F.ceil(F.col("_n") / block).cast("long")
    most = counts.agg(F.max(blocks)).first()[0] or 0
    if not most:
        return units
    joined = units.join(F.broadcast(counts) if counts.count() < 10_000 else counts, units["source"].eqNullSafe(counts["source"])).drop(counts["source"])
    dealt = joined.withColumn("_block", F.pmod(F.xxhash64(F.lit(seed), "key"), blocks)).drop("_n")
    if most == 1:
        return dealt.groupBy("source").applyInArrow(fly(True), schema)
    with_block = dealt.select(*schema.names, "_block").schema

    def level(df: DataFrame) -> DataFrame:
        return df.groupBy("source", "_block").applyInArrow(fly(False), with_block)

    done, state = [], stash(level(dealt), "fly")
    while True:
        done.append(state.where("p = 0 or p = 1").select(*schema.names))
        left = state.where("p > 0 and p < 1").withColumn("_block", (F.col("_block") / fan).cast("long"))
        most = -(-most // fan)
        if most <= 1:
            done.append(left.groupBy("source").applyInArrow(fly(True), schema))
            break
        state = stash(level(left), "fly")
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def plan(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, nth): one row for each row of docs.

    taken: words the mix takes of the document, repeats counted. nth numbers
    rows of one doc_id, source and size.
    """
    nth = F.row_number().over(Window.partitionBy("doc_id", "source", "size").orderBy("size"))
    units = stash(sized(docs, id_col, text_col, source_col).withColumn("nth", nth), "mix")
    goal = targets(units, weights, most)
    goal = stash(goal, "mix")  # one row a source
    release_driver(docs.sparkSession)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    r = F.when(ratio > most - 1e-9, F.lit(float(most))).otherwise(ratio)
    with_goal = units.withColumnRenamed("source", "_s").join(goal, F.col("_s").eqNullSafe(F.col("source"))).drop("_s")
    ready = with_goal.withColumn("base", F.floor(r)).withColumn("p", r - F.floor(r)).withColumn("key", F.xxhash64("doc_id", "nth", "source"))
    drawn = sample(ready.where("size > 0")).unionByName(ready.where("size = 0").withColumn("p", F.lit(0.0)))
    return drawn.select("doc_id", "source", "size", "source_size", "target", (F.col("size") * (F.col("base") + F.col("p")).cast("long")).alias("taken"), "nth")


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of docs, each as often as the plan takes it (documents without words stay once); all columns pass through."""
    size = word_count(F.col(text_col))
    chosen = plan(docs, weights, most, id_col, text_col, source_col).withColumn("_times", F.when(F.col("size") > 0, F.col("taken") / F.col("size")).otherwise(1).cast("int"))
    chosen = chosen.where("_times > 0").select(F.col("doc_id").alias("_d"), F.col("source").alias("_s"), F.col("size").alias("_z"), F.col("nth").alias("_n"), "_times")
    numbered = docs.withColumn("_size", size).withColumn("_nth", F.row_number().over(Window.partitionBy(id_col, source_col, "_size").orderBy("_size")))
    on = F.col(id_col).eqNullSafe(F.col("_d")) & F.col(source_col).eqNullSafe(F.col("_s")) & (F.col("_size") == F.col("_z")) & (F.col("_nth") == F.col("_n"))
    return numbered.join(chosen, on).withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*docs.columns)
