"""The three embedding algorithms that are given a start."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.rng import u01
from ..plans.storage import stash
from . import sgns, walks
from .graph import Graph, arcs, degrees
from .local import Csr, biased_walks, count_pairs
from .local import walks as local_walks

LOCAL_EDGES, LOCAL_STEPS = 8_000_000, 40_000_000  # up to so many edges and walk steps one task walks; the walks are the same either way


def walk_pairs(g: Graph, r: int, length: int, window: int, seed: int = 1, biased: tuple[float, float] | None = None, local: bool | None = None) -> DataFrame:
    """(center, context, n) of r walks from each node; steps have equal (or edge-weight) odds, or those of second order for biased = (p, q).

    A small graph is walked in one task, a large one by joins, from the same draws.
    """
    if local is None:
        local = g.edges.count() <= LOCAL_EDGES and g.nodes.count() * r * length <= LOCAL_STEPS
    if local:
        return _local_pairs(g, r, length, window, seed, biased)
    if biased:
        w = walks.biased(g.edges, g.nodes, r, length, *biased, seed)
    elif "w" in g.edges.columns:
        t = stash(walks.transitions(g.edges), "trans")
        if (degrees(g.edges).agg(F.max("degree")).first()[0] or 0) > walks.BLOCK:  # hubs: no task holds a whole neighbourhood
            w = walks.weighted_blocked(*(stash(x, "alias") for x in walks.alias_blocks(t)), g.nodes, r, length, seed)
        else:
            w = walks.weighted(stash(walks.alias_tables(t), "alias"), g.nodes, r, length, seed, "bulk")
    else:
        w = walks.uniform(g.edges, g.nodes, r, length, seed, "bulk")
    return walks.context_pairs(w, window)


def _local_pairs(g: Graph, r: int, length: int, window: int, seed: int, biased: tuple[float, float] | None) -> DataFrame:
    one = F.lit(1).alias("one")
    w = ["w"] if "w" in g.edges.columns else []

    def run(p: pa.Table, e: pa.Table) -> pa.Table:
        ids = np.sort(p.column("node").to_numpy())
        csr = Csr(len(ids), *(np.searchsorted(ids, e.column(c).to_numpy()) for c in ("src", "dst")), e.column("w").to_numpy() if w else None, ids)
        paths = local_walks(csr, r, length, seed) if biased is None else biased_walks(csr, r, length, *biased, seed)
        c, o, n = count_pairs(paths, window, len(ids))
        return pa.table({"center": pa.array(ids[c]), "context": pa.array(ids[o]), "n": pa.array(n)})

    left, right = g.nodes.select(one, F.col("node").cast("long").alias("node")), g.edges.select(one, F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), *(F.col(c).cast("double").alias(c) for c in w))
    return left.groupBy("one").cogroup(right.groupBy("one")).applyInArrow(run, "center long, context long, n long")


def uniform_walk(g: Graph, d: int = 128, r: int = 80, length: int = 40, window: int = 10, epochs: int = 1, rate: float = 0.025, init: DataFrame | None = None, seed: int = 1, local: bool | None = None) -> DataFrame:
    """(node, vec): walks with equal (or edge-weight) odds, then skip-gram from init."""
    return sgns.fit(walk_pairs(g, r, length, window, seed, None, local), g.nodes, d, init, epochs, rate=rate, seed=seed)


def biased_walk(g: Graph, d: int = 128, p: float = 1.0, q: float = 1.0, r: int = 10, length: int = 80, window: int = 10, epochs: int = 1, rate: float = 0.025, init: DataFrame | None = None, seed: int = 1, local: bool | None = None) -> DataFrame:
    """(node, vec): second-order walks, then skip-gram from init."""
    return sgns.fit(walk_pairs(g, r, length, window, seed, (p, q), local), g.nodes, d, init, epochs, rate=rate, seed=seed)


def edge_samples(edges: DataFrame, rounds: int, share: float = 1.0, seed: int = 1) -> DataFrame:
    """(center, context, n): each arc is drawn about share times in each round, both ways, by weight where there is one."""
    w = F.col("w") if "w" in edges.columns else F.lit(1)
    a = arcs(edges)
    times = F.floor(w * share * rounds + u01("edge", seed, F.col("src"), F.col("dst")))
    return a.select(F.col("src").alias("center"), F.col("dst").alias("context"), times.cast("long").alias("n")).where("n > 0")


def edge_prox(g: Graph, d: int = 128, order: int | str = 1, rounds: int = 20, negatives: int = 5, rate: float = 0.025, init: DataFrame | None = None, seed: int = 1) -> DataFrame:
    """(node, vec). order 1: both ends share one table; 2: separate context vectors; 'both': halves side by side."""
    if order == "both":
        cut = (lambda lo: None) if init is None else (lambda lo: init.select("node", F.slice("vec", lo, d // 2).alias("vec")))
        one = edge_prox(g, d // 2, 1, rounds, negatives, rate, cut(1), seed)
        two = edge_prox(g, d - d // 2, 2, rounds, negatives, rate, cut(d // 2 + 1) if d % 2 == 0 else None, seed + 1)
        return one.join(two.withColumnRenamed("vec", "two"), "node").select("node", F.concat("vec", "two").alias("vec"))
    return sgns.fit(edge_samples(g.edges, rounds, 1.0, seed), g.nodes, d, init, 1, negatives, rate, seed, tie=order == 1)


TARGETS = {"uniform-walk": uniform_walk, "biased-walk": biased_walk, "edge-proximity": edge_prox}
