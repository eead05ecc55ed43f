"""Skip-gram with negative sampling from a given start: pairs of disjoint blocks, one block for small graphs."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..functions.rng import u01
from ..plans.storage import drop_stash, stash, stash_path, stored
from .local import train

SMALL_BYTES = 128 << 20  # parameters that one task may hold
MAX_ROWS, MAX_PAIRS = 8_000_000, 40_000_000  # distinct pairs, and pairs with repeats, of one task


def random_vectors(nodes: DataFrame, d: int, seed: int = 1) -> DataFrame:
    """(node, vec): uniform in +-0.5/d, a pure function of node and dimension."""
    v = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: (u01("init", seed, F.col("node"), i) - 0.5) / d)
    return nodes.select("node", v.alias("vec"))


def started(nodes: DataFrame, d: int, init: DataFrame | None, seed: int) -> DataFrame:
    """Every node with its initial vector; those that init lacks get random ones."""
    base = random_vectors(nodes, d, seed)
    if init is None:
        return base
    given = init.select("node", F.col("vec").cast("array<double>").alias("given"))
    return base.join(given, "node", "left").select("node", F.coalesce("given", "vec").alias("vec"))


def fit(pairs: DataFrame, nodes: DataFrame, d: int, init: DataFrame | None = None, epochs: int = 1, negatives: int = 5, rate: float = 0.025, seed: int = 1, tie: bool = False, blocks: int | None = None) -> DataFrame:
    """(node, vec). pairs(center, context, n); tie: one table for both sides.

    Nodes lie in hash blocks. A round of a tournament pairs every block with
    one other; a pair of blocks holds all parameters that its pairs touch, so
    a round's tasks run at once and only blocks move between rounds. The
    number of blocks follows from the parameters and the pairs, so that a
    task's share of both is bounded; a small input is one block, one round.
    Negatives come from the task's blocks.
    """
    start = stash(started(nodes, d, init, seed), "sgns")
    rows = pairs.select(F.col("center").cast("long").alias("center"), F.col("context").cast("long").alias("context"), F.col("n").cast("long").alias("n"))
    if blocks is None:
        rows = rows if stored(pairs) else stash(rows, "pairs")
        r = rows.agg(F.count("*"), F.sum("n")).first()
        blocks = block_count(start.count(), d, r[0], r[1] or 0)
    if blocks > 1:
        blocks += blocks % 2
    of = lambda c: F.pmod(F.xxhash64(F.lit(seed), c), F.lit(blocks)).cast("int")
    odd, half = blocks - 1, blocks // 2
    i, j = of(F.col("center")), of(F.col("context"))
    # blocks i and j meet in round (i + j) / 2 modulo the odd number; the last block meets block r in round r; a block's own pairs are spread over all rounds
    meet = F.when(i == j, F.pmod(F.xxhash64(F.lit(seed), F.col("center"), F.col("context")), F.lit(max(odd, 1)))).when(i == odd, j).when(j == odd, i).otherwise((i + j) * half % max(odd, 1))
    params = stash(start.select("node", F.col("vec").alias("x"), F.array_repeat(F.lit(0.0), d).alias("y")), "grid")
    if blocks == 1:
        dealt = rows.withColumn("round", F.lit(0))
    else:
        path = stash_path(pairs.sparkSession, "pairs")
        rows.withColumn("round", meet.cast("int")).repartition("round", i, j).write.option("compression", "zstd").partitionBy("round").parquet(path)
        dealt = pairs.sparkSession.read.schema(T.StructType([*rows.schema, T.StructField("round", T.IntegerType())])).parquet(path)
    steps = max(1, odd) * epochs
    for at in range(steps):
        r = at % max(1, odd)

        def team(c: Column) -> Column:
            """The smaller block of the pair that block c is in."""
            other = F.when(c == odd, r).when(c == r, odd).otherwise(F.pmod(2 * r - c, F.lit(max(1, odd))))
            return F.least(c, other) if blocks > 1 else F.lit(0)

        rates = rate * (1 - at / steps), max(0.05 * rate, rate * (1 - (at + 1) / steps))
        mine = params.select(team(of(F.col("node"))).alias("team"), "node", "x", "y")
        here = dealt.where(F.col("round") == r).select(team(i).alias("team"), "center", "context", "n")
        after = stash(mine.groupBy("team").cogroup(here.groupBy("team")).applyInArrow(_trainer(d, negatives, rates, seed + at, tie), "node long, x array<double>, y array<double>"), "grid")
        drop_stash(params)
        params = after
    return params.select("node", F.col("x").alias("vec"))


def block_count(n: int, d: int, rows: int, total: int) -> int:
    """Blocks such that two of them hold at most SMALL_BYTES of parameters and their pairs are bounded in rows and in number."""
    if 2 * n * d * 8 <= SMALL_BYTES and rows <= MAX_ROWS and total <= MAX_PAIRS:
        return 1
    most = max(rows / MAX_ROWS, total / MAX_PAIRS)
    return max(2, -(-4 * n * d * 8 // SMALL_BYTES), math.ceil(2 * math.sqrt(most)))


def _trainer(d: int, negatives: int, rates: tuple[float, float], seed: int, tie: bool):  # noqa: ANN202
    def table(c: pa.ChunkedArray) -> np.ndarray:
        flat = c.combine_chunks()
        return flat.flatten().to_numpy(zero_copy_only=False).reshape(-1, d).copy()

    def lists(x: np.ndarray) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, d), pa.int32()), pa.array(x.ravel()))

    def run(p: pa.Table, e: pa.Table) -> pa.Table:
        p, e = p.sort_by("node"), e.sort_by([("center", "ascending"), ("context", "ascending")])
        ids, x = p.column("node").to_numpy(), table(p.column("x"))
        y = x if tie else table(p.column("y"))
        c, o = (np.searchsorted(ids, e.column(k).to_numpy()) for k in ("center", "context"))
        train(x, y, c, o, e.column("n").to_numpy(), negatives, rates, seed)
        return pa.table({"node": pa.array(ids), "x": lists(x), "y": p.column("y") if tie else lists(y)})

    return run


def fit_mllib(walks: DataFrame, d: int, window: int = 5, epochs: int = 1, seed: int = 1) -> DataFrame:
    """The library's trainer (no initial vectors): for cross-checks of the random start."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    words = walks.select(F.col("path").cast("array<string>").alias("path"))
    m = Word2Vec(vectorSize=d, windowSize=window, maxIter=epochs, minCount=0, seed=seed, inputCol="path", outputCol="v").fit(words)
    return m.getVectors().select(F.col("word").cast("long").alias("node"), vector_to_array("vector").alias("vec"))
