"""Connected components by alternating large-star and small-star contractions.

Each round is two aggregations and two equi-joins; hubs are only ever keys of
an aggregation with map-side combine or of a join that AQE can split, so no
group is gathered in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..plans.storage import drop_stash, stash


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionAll(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def _lowest(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("src").agg(F.least(F.min("dst"), F.col("src")).alias("low"))


def _large_star(edges: DataFrame) -> DataFrame:
    arcs = _both(edges)
    joined = arcs.join(_lowest(arcs), "src").where(F.col("dst") > F.col("src"))
    return joined.select(F.col("dst").alias("src"), F.col("low").alias("dst")).where("src <> dst").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst"))
    low = down.groupBy("src").agg(F.min("dst").alias("low"))
    rest = down.join(low, "src").where(F.col("dst") != F.col("low"))
    linked = rest.select(F.col("dst").alias("src"), F.col("low").alias("dst"))
    return linked.unionAll(low.select("src", F.col("low").alias("dst"))).distinct()


def connected(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Label every node that has an edge with the smallest node it can reach.

    edges(src, dst): any orientation; self-loops, repeats and null ends are
    ignored. Returns (node, root); an empty input gives an empty result.
    """
    state = stash(edges.where("src <> dst").select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct(), "cc")
    mark = None
    for _ in range(max_rounds):
        after = stash(_small_star(_large_star(state)), "cc")
        drop_stash(state)
        state = after
        now = tuple(state.agg(F.count("*"), F.sum(F.xxhash64("src", "dst") % F.lit(1 << 40)), F.count_if(F.col("src") < F.col("dst"))).first())
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    roots = state.select("dst").distinct()
    return state.select(F.col("src").alias("node"), F.col("dst").alias("root")).unionAll(roots.select(F.col("dst").alias("node"), F.col("dst").alias("root")))


def largest(labels: DataFrame) -> DataFrame:
    """Nodes of the biggest component; ties go to the smallest root."""
    top = labels.groupBy("root").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "root").limit(1)
    return labels.join(F.broadcast(top.select("root")), "root", "left_semi").select("node")
