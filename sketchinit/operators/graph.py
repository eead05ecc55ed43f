"""Canonical simple graphs and their adjacency."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from ..plans.storage import stash


@dataclass(frozen=True)
class Graph:
    """nodes(node), edges(src, dst) with src < dst."""

    nodes: DataFrame
    edges: DataFrame


def canonical(pairs: DataFrame, nodes: DataFrame | None = None, keep: bool = True, directed: bool = False) -> Graph:
    """Undirected simple graph of any pairs(src, dst): nulls and loops go, orientation and repeats collapse. keep: write it once."""
    if directed:
        raise ValueError("only undirected graphs are supported")
    e = pairs.select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"))
    e = e.where(F.col("src").isNotNull() & F.col("dst").isNotNull() & (F.col("src") != F.col("dst"))).distinct()
    e = stash(e, "edges") if keep else e
    n = e.select(F.explode(F.array("src", "dst")).alias("node"))
    n = (n if nodes is None else n.unionAll(nodes.select(F.col("node").cast("long")))).distinct()
    return Graph(n, e)


def arcs(edges: DataFrame) -> DataFrame:
    """Both orientations, other columns kept."""
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select("src", "dst", *rest).unionAll(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count("*").alias("degree"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("degree").agg(F.count("*").alias("nodes"))


def neighbor_lists(edges: DataFrame, max_degree: int = 1_000_000) -> DataFrame:
    """(node, neighbors): sorted ids as text; nodes over max_degree are refused, since a list is one row."""
    d = degrees(edges)
    if d.where(F.col("degree") > max_degree).limit(1).count():
        raise ValueError("a node has too many neighbours for a list; use arcs()")
    lists = arcs(edges).groupBy(F.col("src").alias("node")).agg(F.array_sort(F.collect_list("dst")).alias("n"))
    return lists.select("node", F.array_join(F.col("n").cast("array<string>"), ",").alias("neighbors"))


def summary(degree: DataFrame) -> DataFrame:
    """One row: nodes, edges, from degree(node, degree)."""
    return degree.agg(F.count("*").alias("nodes"), F.coalesce(F.expr("sum(degree) div 2"), F.lit(0)).cast("long").alias("edges"))


def common_neighbors(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(src, dst) with the number of common neighbours and their Jaccard share."""
    a = arcs(edges)
    d = degrees(edges)
    both = pairs.join(a.select("src", F.col("dst").alias("via")), "src").join(a.select(F.col("src").alias("dst"), F.col("dst").alias("via")), ["dst", "via"])
    n = both.groupBy("src", "dst").agg(F.count("*").alias("common"))
    out = pairs.join(n, ["src", "dst"], "left").join(d.select(F.col("node").alias("src"), F.col("degree").alias("x")), "src", "left").join(d.select(F.col("node").alias("dst"), F.col("degree").alias("y")), "dst", "left")
    c = F.coalesce("common", F.lit(0))
    return out.select("src", "dst", c.alias("common"), (c / (F.coalesce("x", F.lit(0)) + F.coalesce("y", F.lit(0)) - c)).alias("jaccard"))
