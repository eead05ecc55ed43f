"""Balanced k-way partitions with a small edge cut: multilevel, label propagation, and the plain ablations."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.rng import u32
from ..plans.storage import stash
from .graph import Graph, arcs
from .local import Csr, cut

COARSE_NODES, COARSE_EDGES = 400_000, 8_000_000  # the coarsest graph, which one task cuts, is no larger


def choose_k(n: int, rule: str = "sqrt", k: int | None = None, beta: float = 0.5) -> int:
    """Number of parts: the ceiling of the root (default), n ** beta, or a given k."""
    if rule == "fixed":
        if not k:
            raise ValueError("rule 'fixed' needs k")
        return min(k, max(n, 1))
    root = math.isqrt(n) + (math.isqrt(n) ** 2 < n) if rule == "sqrt" else math.ceil(n**beta)
    return max(1, min(root, max(n, 1)))


def capacity(n: int, k: int, eps: float) -> int:
    return max(1, math.floor((1 + eps) * -(-n // k)))


def hashed(nodes: DataFrame, k: int, seed: int = 1) -> DataFrame:
    return nodes.select("node", (u32("part", seed, F.col("node")) % k).cast("int").alias("part"))


def ranged(nodes: DataFrame, k: int, n: int | None = None) -> DataFrame:
    """Equal ranges of the id order: ranks by range partitions with offsets, no single window over all."""
    n = nodes.count() if n is None else n
    return ranked(nodes).select("node", F.floor(F.col("rank") * k / n).cast("int").alias("part"))


CHUNK = 1_000_000  # rows of one range partition that are ranked together


def numbered(rows: DataFrame, order: list[str]) -> DataFrame:
    """rows with their rank from 0 in a total order: ranks inside range partitions, then offsets. The number of partitions follows the number of rows."""
    rows = stash(rows, "rank")
    parts = max(1, -(-rows.count() // CHUNK))
    cut = rows.withColumn("chunk", F.lit(0)) if parts == 1 else stash(rows.repartitionByRange(parts, *order).withColumn("chunk", F.spark_partition_id()), "rank")
    before = Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)  # one row a chunk
    base = cut.groupBy("chunk").agg(F.count("*").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).select("chunk", "base")
    inside = Window.partitionBy("chunk").orderBy(*order)
    return cut.withColumn("rn", F.row_number().over(inside) - 1).join(F.broadcast(base), "chunk").select(*rows.columns, (F.col("rn") + F.col("base")).alias("rank"))


def ranked(nodes: DataFrame) -> DataFrame:
    """(node, rank from 0) in id order."""
    return numbered(nodes.select("node"), ["node"])


def from_table(parts: DataFrame, nodes: DataFrame) -> DataFrame:
    """A user's partition, checked: every node exactly once."""
    p = parts.select(F.col("node").cast("long"), F.col("part").cast("int"))
    n = nodes.count()
    if p.select("node").distinct().count() != p.count() or p.join(nodes, "node", "left_semi").count() != n or p.where("part is null or part < 0").count():
        raise ValueError("the parts do not cover the nodes once")
    return p


def balance(parts: DataFrame, k: int, eps: float = 0.03) -> DataFrame:
    """One row: nodes, used parts, the largest part, the cap and whether it holds."""
    sizes = parts.groupBy("part").agg(F.count("*").alias("size"))
    out = sizes.agg(F.sum("size").alias("nodes"), F.count("*").alias("parts"), F.max("size").alias("max_size"))
    cap = F.floor(F.lit(1 + eps) * F.ceil(F.col("nodes") / k))
    return out.withColumn("cap", cap.cast("long")).withColumn("ok", F.col("max_size") <= F.col("cap"))


def edge_cut(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """Edges between parts: (src, dst, part_src, part_dst)."""
    return with_parts(edges, parts).where("part_src <> part_dst")


def with_parts(edges: DataFrame, parts: DataFrame) -> DataFrame:
    p = parts.select("node", "part")
    a = edges.join(p.select(F.col("node").alias("src"), F.col("part").alias("part_src")), "src")
    return a.join(p.select(F.col("node").alias("dst"), F.col("part").alias("part_dst")), "dst").select("src", "dst", "part_src", "part_dst")


def label_round(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """One synchronous round: each node's most frequent neighbouring part, own part counting once; ties to the smaller part."""
    votes = arcs(edges).join(parts.select(F.col("node").alias("dst"), "part"), "dst").select(F.col("src").alias("node"), "part")
    n = votes.unionAll(parts.select("node", "part")).groupBy("node", "part").agg(F.count("*").alias("votes"))
    return n.groupBy("node").agg(F.min_by("part", F.struct(-F.col("votes"), F.col("part"))).cast("int").alias("part"))


def rebalance(parts: DataFrame, k: int, cap: int, seed: int = 1, fill: bool = True) -> DataFrame:
    """Every part within cap and, with fill and nodes enough, none empty: surplus nodes take free seats in order.

    Seats and movers are numbered by small per-part tables and in-part ranks;
    they meet in an equi-join.
    """
    spark = parts.sparkSession
    sizes = spark.range(k).select(F.col("id").cast("int").alias("part")).join(parts.groupBy("part").agg(F.count("*").alias("size")), "part", "left").na.fill(0)
    empties = sizes.where("size = 0").count() if fill else 0
    level = cap
    if empties:  # seats for the empty parts must be filled by someone
        most = sizes.agg(F.max("size")).first()[0] or 0
        n = parts.count()
        level = min(cap, max(1, -(-n // k))) if most > 1 else cap
    inside = Window.partitionBy("part").orderBy(u32("seat", seed, F.col("node")), "node")
    numbered = parts.withColumn("rn", F.row_number().over(inside))
    order = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a part
    over = sizes.select("part", F.greatest(F.col("size") - level, F.lit(0)).alias("extra")).withColumn("base", F.coalesce(F.sum("extra").over(order), F.lit(0)))
    movers = numbered.where(F.col("rn") > level).join(over, "part").select("node", (F.col("rn") - level + F.col("base")).alias("seat"))
    first = Window.orderBy("size", "part").rowsBetween(Window.unboundedPreceding, -1)
    free = sizes.where(F.col("size") < level).withColumn("free", F.lit(level) - F.col("size")).withColumn("base", F.coalesce(F.sum("free").over(first), F.lit(0)))
    seats = free.select("part", F.posexplode(F.sequence(F.lit(1), F.col("free")))).select("part", "col")
    seats = free.join(seats, "part").select("part", (F.col("base") + F.col("col")).alias("seat"))
    moved = movers.join(seats, "seat").select("node", "part")
    stay = numbered.where(F.col("rn") <= level).select("node", "part")
    return stay.unionAll(moved).select("node", F.col("part").cast("int"))


def label_prop(g: Graph, k: int, eps: float = 0.03, rounds: int = 4, seed: int = 1) -> DataFrame:
    """Size-capped label propagation from a hash start."""
    n = g.nodes.count()
    parts = stash(hashed(g.nodes, k, seed), "parts")
    for _ in range(rounds):
        parts = stash(rebalance(label_round(g.edges, parts), k, capacity(n, k, max(eps, 0.3)), seed), "parts")
    return stash(rebalance(parts, k, capacity(n, k, eps), seed), "parts")


# ---------------------------------------------------------------- multilevel


def match(edges: DataFrame, seed: int) -> DataFrame:
    """(node, parent): mutual proposals along heavy edges; edges(src, dst, w). Unmatched nodes are absent."""
    a = arcs(edges)
    best = a.groupBy("src").agg(F.max_by("dst", F.struct("w", u32("match", seed, F.least("src", "dst"), F.greatest("src", "dst")), F.col("dst"))).alias("to"))
    other = best.select(F.col("src").alias("to"), F.col("to").alias("back"))
    pair = best.join(other, "to").where("back = src and src < to").select("src", "to")
    return pair.select(F.explode(F.array("src", "to")).alias("node"), F.col("src").alias("parent"))


def contract(edges: DataFrame, nodes: DataFrame, parent: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(edges, nodes, full parent map) one level up; weights and sizes add."""
    whole = nodes.join(parent, "node", "left").select("node", F.coalesce("parent", "node").alias("parent"), "size")
    up = whole.groupBy("parent").agg(F.sum("size").alias("size")).withColumnRenamed("parent", "node")
    p = whole.select("node", "parent")
    e = edges.join(p.select(F.col("node").alias("src"), F.col("parent").alias("a")), "src").join(p.select(F.col("node").alias("dst"), F.col("parent").alias("b")), "dst").where("a <> b")
    e = e.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("w").alias("w"))
    return e, up, p


def refine(edges: DataFrame, nodes: DataFrame, parts: DataFrame, cap: int, turn: int) -> DataFrame:
    """One round of moves by gain: half of the nodes by hash may move, into seats that are free, best gain first."""
    p = parts.select("node", "part")
    votes = arcs(edges).join(p.select(F.col("node").alias("dst"), F.col("part").alias("to")), "dst").groupBy(F.col("src").alias("node"), "to").agg(F.sum("w").alias("w"))
    own = p.join(votes.select("node", F.col("to").alias("part"), F.col("w").alias("own")), ["node", "part"], "left").na.fill(0, ["own"])
    best = votes.join(p, "node").where("to <> part").groupBy("node").agg(F.max_by("to", F.struct("w", -F.col("to"))).alias("to"), F.max("w").alias("w"))
    gain = own.join(best, "node").where((F.col("w") > F.col("own")) & (u32("turn", turn, F.col("node")) % 2 == 0)).withColumn("gain", F.col("w") - F.col("own"))
    load = p.join(nodes, "node").groupBy("part").agg(F.sum("size").alias("load"))
    queue = Window.partitionBy("to").orderBy(F.desc("gain"), "node").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    fit = gain.join(nodes, "node").withColumn("need", F.sum("size").over(queue)).join(load.select(F.col("part").alias("to"), "load"), "to").where(F.col("load") + F.col("need") <= cap)
    return p.join(fit.select("node", "to"), "node", "left").select("node", F.coalesce("to", "part").cast("int").alias("part"))


def _cut_in_task(edges: DataFrame, nodes: DataFrame, k: int, cap: int, seed: int) -> DataFrame:
    """(node, part) of a graph of checked size: one task, nothing on the driver."""

    def run(v: pa.Table, e: pa.Table) -> pa.Table:
        v = v.sort_by("node")
        ids, size = v.column("node").to_numpy(), v.column("size").to_numpy()
        a, b = (np.searchsorted(ids, e.column(c).to_numpy()) for c in ("src", "dst"))
        part = cut(Csr(len(ids), a, b, e.column("w").to_numpy(), ids), size.copy(), k, cap, seed)
        return pa.table({"node": pa.array(ids), "part": pa.array(part.astype(np.int32))})

    one = F.lit(1).alias("one")
    left, right = nodes.select(one, "node", F.col("size").cast("long").alias("size")), edges.select(one, "src", "dst", F.col("w").cast("double").alias("w"))
    return left.groupBy("one").cogroup(right.groupBy("one")).applyInArrow(run, "node long, part int")


def multilevel(g: Graph, k: int, eps: float = 0.03, seed: int = 1, coarse_nodes: int = COARSE_NODES, coarse_edges: int = COARSE_EDGES, refine_rounds: int = 2) -> DataFrame:
    """Coarsen by heavy-edge matching until one task can hold the graph, cut it there, then project back and refine level by level.

    A graph that stops shrinking before is cut by refinement alone, which
    counts sizes and weights too: more rounds from hash parts. Nodes without
    edges take part in neither; they fill free seats at the end.
    """
    n = g.nodes.count()
    if k >= n:
        return ranked(g.nodes).select("node", F.col("rank").cast("int").alias("part"))
    cap = capacity(n, k, eps)
    edges = stash(g.edges.select("src", "dst", (F.col("w") if "w" in g.edges.columns else F.lit(1)).cast("long").alias("w")), "ml")
    nodes = stash(edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct().withColumn("size", F.lit(1).cast("long")), "ml")
    alone = g.nodes.select("node").join(nodes, "node", "left_anti")
    levels: list[tuple[DataFrame, DataFrame, DataFrame]] = []
    count, m = nodes.count(), edges.count()
    while (count > coarse_nodes or m > coarse_edges) and len(levels) < 40:
        parent = match(edges, seed + len(levels))
        small = nodes.where(F.col("size") <= max(1, cap // 3)).select("node")
        parent = parent.join(small, "node", "left_semi")
        parent = parent.join(parent.groupBy("parent").count().where("count = 2").select("parent"), "parent", "left_semi")
        e, up, p = contract(edges, nodes, stash(parent, "ml"))
        levels.append((edges, nodes, stash(p, "ml")))
        edges, nodes = stash(e, "ml"), stash(up, "ml")
        before, count, m = count, nodes.count(), edges.count()
        if count > 0.95 * before:
            break
    if count <= coarse_nodes and m <= coarse_edges:
        parts = stash(_cut_in_task(edges, nodes, k, cap, seed), "parts")
    else:
        parts = stash(hashed(nodes, k, seed), "parts")
        for turn in range(8):
            parts = stash(refine(edges, nodes, parts, cap, seed + turn), "parts")
    for e, nd, p in reversed(levels):
        down = p.join(parts.select(F.col("node").alias("parent"), "part"), "parent").select("node", "part")
        for turn in range(refine_rounds):
            down = stash(refine(e, nd, down, cap, seed + turn), "parts")
        parts = down
    return stash(rebalance(parts.unionByName(hashed(alone, k, seed)), k, cap, seed), "parts")
