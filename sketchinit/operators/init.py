"""The initializers: sketch (partition, abstract graph, embedding, propagation), random, hierarchical."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, functions as F

from ..plans.storage import stash
from . import abstract, coarsen, hyper, partition, propagate, sgns, target
from .abstract import AbstractGraph
from .graph import Graph
from .metrics import reconstruction


@dataclass
class InitResult:
    emb: DataFrame
    parts: DataFrame | None = None
    sketch: AbstractGraph | None = None
    trace: list[dict] = field(default_factory=list)
    timings: dict[str, float] = field(default_factory=dict)
    hyper: tuple[int, int] | None = None


PARTITIONERS = {"multilevel": partition.multilevel, "label_prop": partition.label_prop}


def embed_abstract(ag: AbstractGraph, n_walks: int, length: int, d: int, seed: int = 1, window: int = 5, epochs: int = 1, rate: float = 0.05, local: bool | None = None) -> DataFrame:
    """(part, vec): weighted walks on the abstract graph, then skip-gram."""
    g = Graph(ag.nodes.select(F.col("part").cast("long").alias("node")), ag.edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w"))
    emb = target.uniform_walk(g, d, n_walks, length, window, epochs, rate, None, seed, local)
    return emb.select(F.col("node").cast("int").alias("part"), "vec")


def pick(ag: AbstractGraph, how: str | tuple[int, int], w: np.ndarray | None, select: str, d: int, seed: int) -> tuple[int, int]:
    """The walk hyperparameters: a given pair, 'learned' (the model w, or the shipped one), 'learned-crossed' (the shipped model that depends on the graph), 'random', or 'grid' (every pair is tried; the least loss wins).

    select reads the model's score literally ('highest' wins) or as the loss it is ('lowest').
    """
    if isinstance(how, tuple):
        return how
    if how == "random":
        rng = np.random.default_rng(seed)
        return int(rng.choice(hyper.WALKS)), int(rng.choice(hyper.LENGTHS))
    if how in ("learned", "learned-crossed"):
        return hyper.choose(hyper.stats(ag), hyper.default_model(how != "learned") if w is None else w, select=select)
    if how != "grid":
        raise ValueError(f"unknown way to pick hyperparameters: {how}")
    losses = grid_losses(ag, d, seed)
    return min(sorted(losses), key=losses.get)


def grid_losses(ag: AbstractGraph, d: int, seed: int = 1, n_walks: tuple[int, ...] = hyper.WALKS, lengths: tuple[int, ...] = hyper.LENGTHS) -> dict[tuple[int, int], float]:
    """The loss of the abstract graph's embedding under every combination; the embeddings are independent jobs, run side by side."""
    def one(combo: tuple[int, int]) -> float:
        emb = embed_abstract(ag, *combo, d, seed)
        return reconstruction(ag.edges, emb.withColumnRenamed("part", "node"), "euclid_distance")

    combos = [(a, b) for a in n_walks for b in lengths]
    with ThreadPoolExecutor(4) as pool:
        return dict(zip(combos, pool.map(one, combos)))


def sketch(g: Graph, d: int = 128, k: int | None = None, eps: float = 0.03, delta: float | None = None, max_iter: int = 200, how: str | tuple[int, int] = "learned", w: np.ndarray | None = None, select: str = "highest", partitioner: str | DataFrame = "multilevel", rule: str = "sqrt", seed: int = 1) -> InitResult:
    """The sketch initializer. max_iter=0 leaves out propagation; k, rule and partitioner are the ablations' knobs."""
    times: dict[str, float] = {}
    t = time.time()

    def lap(name: str) -> None:
        nonlocal t
        times[name], t = time.time() - t, time.time()

    n = g.nodes.count()
    k = partition.choose_k(n, "fixed" if k else rule, k)
    if isinstance(partitioner, DataFrame):
        parts = partition.from_table(partitioner, g.nodes)
    elif partitioner == "hash":
        parts = partition.hashed(g.nodes, k, seed)
    elif partitioner == "range":
        parts = partition.ranged(g.nodes, k, n)
    else:
        parts = PARTITIONERS[partitioner](g, k, eps, seed=seed)
    parts = stash(parts, "parts")
    lap("partition")
    ag = abstract.build(g, parts)
    lap("abstract")
    combo = pick(ag, how, w, select, d, seed)
    lap("hyper")
    f_a = stash(embed_abstract(ag, *combo, d, seed), "fa")
    lap("embed")
    emb, trace = propagate.run(g, parts, f_a, delta, max_iter)
    lap("propagate")
    return InitResult(emb, parts, ag, trace, times, combo)


def random(g: Graph, d: int = 128, seed: int = 1) -> InitResult:
    t = time.time()
    emb = stash(sgns.random_vectors(g.nodes, d, seed), "emb")
    return InitResult(emb, timings={"random": time.time() - t})


def hierarchical(g: Graph, d: int = 128, kind: str = "uniform-walk", min_nodes: int = 100, seed: int = 1, **options: object) -> InitResult:
    """The baseline: coarsen by stars and edges, embed the coarsest graph, hand vectors down and train again at every level but the finest."""
    t = time.time()
    levels = coarsen.hierarchy(g, min_nodes, seed=seed)
    fit = target.TARGETS[kind]
    emb = stash(fit(levels[-1][0], d, seed=seed, **options), "emb")
    for i in range(len(levels) - 2, -1, -1):
        graph, parent = levels[i]
        emb = parent.join(emb.withColumnRenamed("node", "parent"), "parent").select("node", "vec")
        if i:
            emb = fit(graph, d, init=emb, seed=seed, **options)
        emb = stash(emb, "emb")
    return InitResult(emb, timings={"hierarchical": time.time() - t, "levels": len(levels)})
