"""Link prediction: hold out edges, take the largest component, match negatives, rank, and count."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.rng import u32
from ..functions.vec import similarity
from ..plans.storage import stash
from .components import connected, largest
from .graph import arcs
from .partition import CHUNK, ranked


@dataclass(frozen=True)
class Split:
    train: DataFrame
    pos: DataFrame
    neg: DataFrame
    nodes: DataFrame
    held: int
    unmatched: int = 0  # ends of positives that no negative could take


def holdout(edges: DataFrame, alpha: float = 0.1, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """(E_s, E_r): the ceiling of alpha * m edges of least hash. A threshold cuts; only its tie class is sorted."""
    m = edges.count()
    take = math.ceil(alpha * m)
    h = edges.withColumn("h", u32("hold", seed, F.col("src"), F.col("dst")))
    if not take:
        return edges.limit(0), edges
    edge = h.agg(F.percentile_approx("h", take / m, 100_000)).first()[0]
    below = h.where(F.col("h") < edge).count()
    while below > take:  # an approximate threshold: step down by its overshoot
        edge = int(edge * (1 - max(1e-6, 1.5 * (below - take) / max(1, below))))
        below = h.where(F.col("h") < edge).count()
    rest = h.where(F.col("h") >= edge).orderBy("h", "src", "dst").limit(take - below)
    held = stash(h.where(F.col("h") < edge).unionAll(rest).select("src", "dst"), "held")
    return held, edges.join(held, ["src", "dst"], "left_anti")


def inside(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    return edges.join(nodes.withColumnRenamed("node", "src"), "src", "left_semi").join(nodes.withColumnRenamed("node", "dst"), "dst", "left_semi")


def uniform_negatives(edges: DataFrame, nodes: DataFrame, count: int, seed: int = 1, surplus: float = 1.5) -> DataFrame:
    """Up to `count` random pairs of nodes that are no edges; fewer where the graph is nearly complete."""
    order = stash(ranked(nodes), "rank")
    n = order.count()
    if n < 2 or not count:
        return edges.limit(0)
    spark = edges.sparkSession
    draw = spark.range(int(count * surplus * (1 + edges.count() / max(1, n * (n - 1) / 2))) + 20)
    i = (u32("neg_a", seed, F.col("id")) % n).alias("a")
    j = (u32("neg_b", seed, F.col("id")) % n).alias("b")
    p = draw.select("id", i, j).where("a <> b").select("id", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).groupBy("a", "b").agg(F.min("id").alias("id"))
    named = p.join(order.select(F.col("rank").alias("a"), F.col("node").alias("src")), "a").join(order.select(F.col("rank").alias("b"), F.col("node").alias("dst")), "b")
    named = named.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "id").join(edges, ["src", "dst"], "left_anti")
    return named.orderBy("id").limit(count).select("src", "dst")


REPAIR, OFFERS = 20_000, 24  # stubs that one round of swaps may hold on the driver, and swaps offered to each pair of them
BUCKET = 50_000  # stubs that are shuffled and zipped together


def matched_negatives(edges: DataFrame, pos: DataFrame, seed: int = 1, rounds: int = 12) -> tuple[DataFrame, int]:
    """(negatives, stubs left over): each node has as many negatives as positives; stubs stay only where no swap places them.

    The positives' ends, each with a number of its own, are shuffled by hash
    and zipped inside hash ranges; what is an edge, a loop or a repeat is
    shuffled again until few are left. Those swap ends with accepted pairs:
    (a, b) and (c, d) become (a, c) and (b, d) where both are free.
    """
    stubs = stash(arcs(pos).select(F.col("src").alias("node"), F.col("dst").alias("tag")), "stubs")
    left = stubs.count()
    done = stash(pos.select("src", "dst").limit(0), "neg")
    for r in range(rounds):
        if not left or (r and left <= REPAIR):
            break
        h = u32("stub", seed + r, F.col("node"), F.col("tag"))
        dealt = stubs.withColumn("h", h).withColumn("bucket", F.floor(F.col("h") * (-(-left // BUCKET)) / 2**32))
        nth = F.row_number().over(Window.partitionBy("bucket").orderBy("h", "node", "tag")) - 1
        both = dealt.withColumn("p", nth).groupBy("bucket", F.floor(F.col("p") / 2).alias("p")).agg(F.array_sort(F.collect_list(F.struct("node", "tag"))).alias("ends"))  # two rows
        a, b = F.col("ends")[0]["node"], F.get("ends", 1)["node"]
        paired = stash(both.select("bucket", "p", "ends", F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"), (F.size("ends") == 2).alias("two")), "stubs")
        first = F.row_number().over(Window.partitionBy("src", "dst").orderBy("bucket", "p"))
        ok = paired.where("two and src <> dst").withColumn("first", first).where("first = 1").join(edges, ["src", "dst"], "left_anti").join(done, ["src", "dst"], "left_anti")
        ok = stash(ok.select("src", "dst", "bucket", "p"), "neg")
        stubs = stash(paired.join(ok, ["bucket", "p"], "left_anti").select(F.explode("ends").alias("s")).select("s.node", "s.tag"), "stubs")
        done = stash(done.unionAll(ok.select("src", "dst")), "neg")
        left = stubs.count()
    if left and left <= REPAIR:
        return _swapped(edges, done, sorted(r["node"] for r in stubs.select("node").collect()), seed)
    return done, left


def _swapped(edges: DataFrame, done: DataFrame, stubs: list[int], seed: int, rounds: int = 12) -> tuple[DataFrame, int]:
    """Place the last stubs by swaps with accepted pairs. A round draws accepted pairs by hash, checks all offered pairs in one join, and takes what fits."""
    spark = edges.sparkSession
    rng = np.random.default_rng(seed)
    added: set[tuple[int, int]] = set()
    gone: set[tuple[int, int]] = set()
    pair = lambda a, b: (min(a, b), max(a, b))
    for r in range(rounds):
        order = rng.permutation(len(stubs))
        stubs = [stubs[i] for i in order]
        open_ = list(zip(stubs[::2], stubs[1::2]))
        if not open_:
            break
        drawn = done.orderBy(u32("swap", seed + r, F.col("src"), F.col("dst")), "src", "dst").limit(OFFERS * len(open_)).collect()  # at most OFFERS * REPAIR / 2 rows
        pool = [p for p in [*map(tuple, drawn), *sorted(added)] if p not in gone]
        offers, wanted = [], set()
        for k, (a, b) in enumerate(open_):
            mine = [(None, [pair(a, b)])]
            for c, d in (pool[(k * OFFERS + i) % len(pool)] for i in range(min(OFFERS, len(pool)))):
                mine += [((c, d), [pair(a, c), pair(b, d)]), ((c, d), [pair(a, d), pair(b, c)])]
            mine = [(old, new) for old, new in mine if len(set(new)) == len(new) and all(x != y for x, y in new)]
            offers.append(mine)
            wanted |= {p for _, new in mine for p in new}
        asked = spark.createDataFrame(sorted(wanted), "src long, dst long") if wanted else done.limit(0)
        known = edges.select("src", "dst").unionAll(done)
        free = {tuple(x) for x in asked.join(known, ["src", "dst"], "left_anti").collect()} | (gone & wanted)
        free -= {tuple(x) for x in asked.join(edges, ["src", "dst"], "left_semi").collect()} if gone & wanted else set()
        free -= added
        stubs = [] if len(stubs) % 2 == 0 else stubs[-1:]
        for (a, b), mine in zip(open_, offers):
            for old, new in mine:
                if all(p in free for p in new) and (old is None or (old not in gone and (old in added or old in pool))):
                    if old is not None:
                        added.discard(old) if old in added else gone.add(old)
                    for p in new:
                        free.discard(p)
                        gone.discard(p) if p in gone else added.add(p)
                    break
            else:
                stubs += [a, b]
    if gone:
        done = done.join(F.broadcast(spark.createDataFrame(sorted(gone), "src long, dst long")), ["src", "dst"], "left_anti")
    if added:
        done = done.unionAll(spark.createDataFrame(sorted(added), "src long, dst long"))
    return stash(done, "neg"), len(stubs)


def negative_degrees(pos: DataFrame, neg: DataFrame) -> DataFrame:
    """(node, positives, negatives) of every node at a test pair."""
    ends = lambda df, p: df.select(F.explode(F.array("src", "dst")).alias("node"), F.lit(p).alias("p"))
    return ends(pos, 1).unionAll(ends(neg, 0)).groupBy("node").agg(F.sum("p").alias("positives"), F.sum(1 - F.col("p")).alias("negatives"))


def split(edges: DataFrame, alpha: float = 0.1, seed: int = 1, match_degree: bool = True) -> Split:
    """The protocol's sets: training edges and positives in the largest component of what is left, and as many negatives."""
    held, rest = holdout(edges, alpha, seed)
    rest = stash(rest, "rest")
    nodes = stash(largest(connected(rest)), "lcc")
    train, pos = stash(inside(rest, nodes), "train"), stash(inside(held, nodes), "pos")
    neg, left = matched_negatives(edges, pos, seed) if match_degree else (uniform_negatives(edges, nodes, pos.count(), seed), 0)
    return Split(train, pos, stash(neg.select("src", "dst"), "neg"), nodes, held.count(), left)


def scored(pos: DataFrame, neg: DataFrame, emb: DataFrame, sim: str = "cosine") -> DataFrame:
    """(src, dst, y, s): s larger is more similar, rounded so that ties are ties everywhere."""
    test = pos.select("src", "dst", F.lit(1).alias("y")).unionAll(neg.select("src", "dst", F.lit(0).alias("y")))
    t = test.join(emb.select(F.col("node").alias("src"), F.col("vec").alias("a")), "src").join(emb.select(F.col("node").alias("dst"), F.col("vec").alias("b")), "dst")
    return t.select("src", "dst", "y", F.round(F.coalesce(similarity(F.col("a"), F.col("b"), sim), F.lit(-2.0)), 9).alias("s"))


def precision_global(test: DataFrame) -> DataFrame:
    """One row: positives, hits among as many most similar pairs, and the precision. test(src, dst, y, s).

    A threshold on s found by percentile settles all but its tie class; no
    single task sorts all pairs.
    """
    n = test.agg(F.sum("y"), F.count("*")).first()
    p = int(n[0] or 0)
    if not p:
        return test.limit(0).agg(F.lit(0).cast("long").alias("positives"), F.lit(0).cast("long").alias("hits"), F.lit(0.0).alias("precision"))
    edge = test.agg(F.percentile_approx("s", 1 - p / n[1], 100_000)).first()[0]
    above = test.where(F.col("s") > edge).count()
    while above > p:
        nxt = test.where(F.col("s") > edge).agg(F.percentile_approx("s", max(0.0, 1 - p / above), 100_000)).first()[0]
        edge = nxt if nxt > edge else test.where(F.col("s") > edge).agg(F.min("s")).first()[0]
        above = test.where(F.col("s") > edge).count()
    rest = test.where(F.col("s") <= edge).orderBy(F.desc("s"), "src", "dst").limit(p - above)
    top = test.where(F.col("s") > edge).unionAll(rest)
    return top.agg(F.lit(p).cast("long").alias("positives"), F.sum("y").cast("long").alias("hits"), F.round(F.sum("y") / p, 6).alias("precision"))


def precision_per_node(test: DataFrame) -> DataFrame:
    """One row: for each node its t most similar test partners, t its number of positives; hits over all."""
    a = test.unionAll(test.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "y", "s"))
    t = a.groupBy("src").agg(F.sum("y").alias("t"))
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))
    top = a.join(t, "src").withColumn("r", rank).where(F.col("r") <= F.col("t"))
    return top.agg(F.count("*").alias("predicted"), F.sum("y").cast("long").alias("hits"), F.round(F.sum("y") / F.count("*"), 6).alias("precision"))


def auc(test: DataFrame) -> float:
    """Chance that a positive ranks over a negative, ties by half: from counts at each distinct value."""
    by = test.groupBy("s").agg(F.sum("y").alias("p"), F.sum(1 - F.col("y")).alias("q"))
    by = stash(by, "auc")
    bucket = stash(by.repartitionByRange(max(1, -(-by.count() // CHUNK)), "s").withColumn("chunk", F.spark_partition_id()), "auc")
    total = bucket.agg(F.sum("p"), F.sum("q")).first()
    before = Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)  # one row a chunk
    base = bucket.groupBy("chunk").agg(F.sum("q").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).select("chunk", "base")
    inner = Window.partitionBy("chunk").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    x = bucket.join(base, "chunk").withColumn("less", F.col("base") + F.coalesce(F.sum("q").over(inner), F.lit(0)))
    r = x.agg(F.sum(F.col("p") * (F.col("less") + F.col("q") / 2))).first()[0] or 0
    return float(r) / max(1.0, float(total[0] or 0) * float(total[1] or 0))
