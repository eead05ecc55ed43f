"""Embedding propagation: inherit the part's vector, then average with the neighbours until the mean move is small."""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.vec import euclid, sum_vectors
from ..plans.storage import drop_stash, stash
from . import local
from .graph import Graph, arcs
from .local import Csr


def inherit(parts: DataFrame, f_a: DataFrame) -> DataFrame:
    """(node, vec) from parts(node, part) and f_a(part, vec)."""
    return parts.join(f_a, "part").select("node", "vec")


def neighbor_mean(edges: DataFrame, emb: DataFrame) -> DataFrame:
    """(node, mean): plain mean of the neighbours' vectors; nodes without neighbours are absent."""
    sent = arcs(edges.select("src", "dst")).join(emb.select(F.col("node").alias("dst"), "vec"), "dst").select(F.col("src").alias("node"), "vec")
    return sum_vectors(sent).select("node", F.transform("vec", lambda x: x / F.col("n")).alias("mean"))


def step(edges: DataFrame, emb: DataFrame, self_weight: float = 0.5) -> DataFrame:
    """One synchronous update; an isolated node keeps its vector."""
    return fused(emb, neighbor_mean(edges, emb), self_weight)


def fused(emb: DataFrame, mean: DataFrame, self_weight: float = 0.5) -> DataFrame:
    m = emb.join(mean, "node", "left")
    mixed = F.zip_with("vec", "mean", lambda a, b: a * self_weight + b * (1 - self_weight))
    return m.select("node", F.when(F.col("mean").isNull(), F.col("vec")).otherwise(mixed).alias("vec"))


def displacement(before: DataFrame, after: DataFrame) -> float:
    """Mean Euclidean move over all nodes."""
    both = before.join(after.select("node", F.col("vec").alias("new")), "node")
    return float(both.agg(F.avg(euclid(F.col("vec"), F.col("new")))).first()[0] or 0.0)


def spread(emb: DataFrame) -> float:
    """Mean squared distance to the mean vector: 0 means that all vectors have become one."""
    r = emb.select(F.posexplode("vec").alias("k", "v")).groupBy("k").agg(F.var_pop("v").alias("s")).agg(F.sum("s")).first()[0]
    return float(r or 0.0)


LOCAL_EDGES, LOCAL_BYTES = 8_000_000, 256 << 20  # a graph and its vectors up to these sizes propagate in one task
BLOCK_BYTES, BLOCK_ARCS = 64 << 20, 4_000_000  # vectors and arcs of one block beyond


def run(g: Graph, parts: DataFrame, f_a: DataFrame, delta: float | None = None, max_iter: int = 200, delta_c: float = 1.0, blocks: int | None = None) -> tuple[DataFrame, list[dict]]:
    """(emb, trace). At least one step unless max_iter is 0; delta defaults to delta_c / nodes.

    blocks=0 runs all steps in one task (the default for a small graph);
    otherwise each step is a round of joins between so many blocks.
    """
    emb = stash(inherit(parts, f_a).select("node", F.col("vec").cast("array<double>").alias("vec")), "emb")
    if max_iter == 0:
        return emb, []
    n, m = emb.count(), g.edges.count()
    delta = delta_c / max(1, n) if delta is None else delta
    first = emb.select(F.size("vec")).first()
    size = n * (first[0] if first else 0) * 8
    if blocks is None:
        blocks = 0 if m <= LOCAL_EDGES and size <= LOCAL_BYTES else max(2, math.ceil(size / BLOCK_BYTES), math.ceil(math.sqrt(2 * m / BLOCK_ARCS)))
    if not blocks:
        return _in_task(g.edges, emb, delta, max_iter)
    ship = _Blocks(g.edges, blocks)
    trace: list[dict] = []
    for i in range(max_iter):
        t = time.time()
        after = stash(ship.step(emb), "emb")
        move = displacement(emb, after)
        trace.append({"iter": i + 1, "delta": move, "seconds": time.time() - t, "converged": move <= delta})
        drop_stash(emb)
        emb = after
        if move <= delta:
            break
    return emb, trace


def _in_task(edges: DataFrame, emb: DataFrame, delta: float, max_iter: int) -> tuple[DataFrame, list[dict]]:
    def run_all(p: pa.Table, e: pa.Table) -> pa.Table:
        p = p.sort_by("node")
        ids = p.column("node").to_numpy()
        flat = p.column("vec").combine_chunks()
        x = flat.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        csr = Csr(len(ids), *(np.searchsorted(ids, e.column(c).to_numpy()) for c in ("src", "dst")), ids=ids)
        x, trace = local.propagate(csr, x, delta, max_iter)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, max(1, x.shape[1])), pa.int32()), pa.array(x.ravel()))
        rows = pa.table({"node": pa.array(ids), "vec": lists, "iter": pa.nulls(len(ids), pa.int32()), "delta": pa.nulls(len(ids), pa.float64()), "seconds": pa.nulls(len(ids), pa.float64())})
        steps = pa.table({"node": pa.nulls(len(trace), pa.int64()), "vec": pa.nulls(len(trace), lists.type), "iter": pa.array(range(1, len(trace) + 1), pa.int32()), "delta": pa.array([t[0] for t in trace], pa.float64()), "seconds": pa.array([t[1] for t in trace], pa.float64())})
        return pa.concat_tables([rows, steps])

    one = F.lit(1).alias("one")
    both = emb.select(one, "node", "vec").groupBy("one").cogroup(edges.select(one, "src", "dst").groupBy("one"))
    out = stash(both.applyInArrow(run_all, "node long, vec array<double>, iter int, delta double, seconds double"), "emb")
    trace = [{"iter": r["iter"], "delta": r["delta"], "seconds": r["seconds"], "converged": r["delta"] <= delta} for r in out.where("iter is not null").orderBy("iter").collect()]  # one row a step
    return out.where("iter is null").select("node", "vec"), trace


class _Blocks:
    """Steps over hash blocks of nodes: a vector is sent once to each block that has a neighbour of its node, where the sums of one pair of blocks are made.

    A hub's arcs lie in many pairs of blocks, so no task holds them all.
    """

    def __init__(self, edges: DataFrame, blocks: int) -> None:
        self.of = lambda c: F.pmod(F.xxhash64(F.lit(11), c), F.lit(blocks)).cast("int")
        a = arcs(edges.select("src", "dst")).select(self.of(F.col("src")).alias("i"), self.of(F.col("dst")).alias("j"), "src", "dst")
        self.arcs = stash(a, "arcs")
        self.routes = stash(self.arcs.select(F.col("dst").alias("node"), "i").distinct(), "routes")

    def step(self, emb: DataFrame) -> DataFrame:
        def sums(a: pa.Table, v: pa.Table) -> pa.Table:
            a, v = a.sort_by("src"), v.sort_by("node")
            src = a.column("src").to_numpy()
            flat = v.column("vec").combine_chunks()
            x = flat.flatten().to_numpy(zero_copy_only=False).reshape(v.num_rows, -1)
            at = np.searchsorted(v.column("node").to_numpy(), a.column("dst").to_numpy())
            head = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]]))
            out, rows = [], max(1, (1 << 22) // max(1, x.shape[1]))
            for lo in range(0, len(src), rows):  # a node over a border gives two partial sums
                here = head[(head >= lo) & (head < lo + rows)]
                begin = np.unique(np.concatenate([[lo], here]))
                total = np.add.reduceat(x[at[lo : lo + rows]], begin - lo, axis=0)
                count = np.diff(np.append(begin, min(lo + rows, len(src))))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, total.size + 1, max(1, total.shape[1])), pa.int32()), pa.array(total.ravel()))
                out.append(pa.table({"node": pa.array(src[begin]), "vec": lists, "n": pa.array(count)}))
            return pa.concat_tables(out)

        sent = emb.join(self.routes, "node").select("i", self.of(F.col("node")).alias("j"), "node", "vec")
        part = self.arcs.groupBy("i", "j").cogroup(sent.groupBy("i", "j")).applyInArrow(sums, "node long, vec array<double>, n long")
        mean = sum_vectors(part, counts="n").select("node", F.transform("vec", lambda x: x / F.col("n")).alias("mean"))
        return fused(emb, mean)


def fixed(edges: DataFrame, emb: DataFrame, steps: int) -> DataFrame:
    """A given number of steps, as one plan."""
    for _ in range(steps):
        emb = step(edges, emb)
    return emb


def membership(edges: DataFrame, parts: DataFrame, steps: int) -> DataFrame:
    """(node, part, weight) after so many steps: propagation is linear, so the vectors are these rows times f_a."""
    m = parts.select("node", "part", F.lit(1.0).alias("weight"))
    a = arcs(edges.select("src", "dst"))
    share = a.join(a.groupBy("src").agg(F.count("*").alias("deg")), "src")
    alone = parts.join(share.select(F.col("src").alias("node")).distinct(), "node", "left_anti").select("node", "part", F.lit(1.0).alias("weight"))
    for _ in range(steps):
        near = share.join(m.withColumnRenamed("node", "dst"), "dst").select(F.col("src").alias("node"), "part", (F.col("weight") / F.col("deg") * 0.5).alias("weight"))
        own = m.join(alone.select("node"), "node", "left_anti").select("node", "part", (F.col("weight") * 0.5).alias("weight"))
        m = near.unionAll(own).groupBy("node", "part").agg(F.sum("weight").alias("weight")).unionAll(alone)
    return m


def from_membership(m: DataFrame, f_a: DataFrame) -> DataFrame:
    """(node, vec): memberships times the abstract vectors."""
    w = m.join(f_a, "part").select("node", F.transform("vec", lambda x: x * F.col("weight")).alias("vec"))
    return sum_vectors(w).select("node", "vec")


def long_form(emb: DataFrame) -> DataFrame:
    return emb.select("node", F.posexplode("vec").alias("dim", "val"))
