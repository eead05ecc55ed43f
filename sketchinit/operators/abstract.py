"""The abstract graph of a partition: one node a part, edges counted."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from ..plans.storage import stash
from .graph import Graph
from .partition import with_parts


@dataclass(frozen=True)
class AbstractGraph:
    """nodes(part, size, internal_edges), edges(src, dst, w) with src < dst."""

    nodes: DataFrame
    edges: DataFrame


def nodes(edges: DataFrame, parts: DataFrame) -> DataFrame:
    size = parts.groupBy("part").agg(F.count("*").alias("size"))
    inner = with_parts(edges, parts).where("part_src = part_dst").groupBy(F.col("part_src").alias("part")).agg(F.count("*").alias("internal_edges"))
    return size.join(inner, "part", "left").select("part", "size", F.coalesce("internal_edges", F.lit(0)).alias("internal_edges"))


def abstract_edges(edges: DataFrame, parts: DataFrame) -> DataFrame:
    cut = with_parts(edges, parts).where("part_src <> part_dst")
    return cut.groupBy(F.least("part_src", "part_dst").alias("src"), F.greatest("part_src", "part_dst").alias("dst")).agg(F.count("*").alias("w"))


def build(g: Graph, parts: DataFrame) -> AbstractGraph:
    return AbstractGraph(stash(nodes(g.edges, parts), "anodes"), stash(abstract_edges(g.edges, parts), "aedges"))
