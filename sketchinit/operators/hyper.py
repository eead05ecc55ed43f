"""Learning the two walk hyperparameters offline from random abstract graphs."""

from __future__ import annotations

import json
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from ..functions.rng import u01
from ..sources.tables import load_model, save_model
from .abstract import AbstractGraph
from .graph import arcs, degrees
from .local import Csr, count_pairs, diameter, random_graph, reconstruction, skip_gram, statistics, walks

FEATURES = ["n_walks", "walk_length", "n_nodes", "n_edges", "density", "diameter", "avg_degree", "max_degree", "avg_weight", "max_weight"]
WALKS, LENGTHS = (5, 10, 20, 40, 80), (5, 10, 20, 40, 80)
LOCAL_EDGES = 1_000_000  # up to so many edges each task that searches for the diameter holds the abstract graph
SOURCES = 4_096  # nodes that one task of that search starts from, about
TRAINING_TASKS = 500  # tasks that make training rows, at most
MAX_TRAINING = 1_000_000  # combinations times training graphs that the gradient fit holds
HYBRID = T.StructType([T.StructField("graph_id", T.IntegerType()), T.StructField("combo_id", T.IntegerType()), *[T.StructField(f, T.DoubleType()) for f in FEATURES], T.StructField("y", T.DoubleType())])


def grid(spark: SparkSession, n_walks: tuple[int, ...] = WALKS, lengths: tuple[int, ...] = LENGTHS) -> DataFrame:
    """(combo_id, n_walks, walk_length)."""
    rows = [(i, a, b) for i, (a, b) in enumerate((a, b) for a in n_walks for b in lengths)]
    return spark.createDataFrame(rows, "combo_id int, n_walks int, walk_length int")


def grid_of(levels: DataFrame) -> DataFrame:
    """(combo_id, n_walks, walk_length) of every two of the distinct levels(level), from 0; each level doubles the one before, 0 stands for 5."""
    v = levels.select("level").where("level is not null").distinct()
    size = lambda c: (5 * F.pow(F.lit(2), c)).cast("int")
    both = v.withColumnRenamed("level", "a").crossJoin(F.broadcast(v.withColumnRenamed("level", "b")))  # a few levels
    return both.select((F.col("a") * len(LENGTHS) + F.col("b")).alias("combo_id"), size(F.col("a")).alias("n_walks"), size(F.col("b")).alias("walk_length"))


def gnp(nodes: DataFrame, p: float, seed: int = 1) -> DataFrame:
    """(graph_id, src, dst, w): a random graph on the nodes of each graph_id, nodes(graph_id, node); weight 1 + floor(4 u)."""
    n = nodes.select("graph_id", "node").distinct()
    all_ = n.withColumnRenamed("node", "src").join(n.withColumnRenamed("node", "dst"), "graph_id").where("src < dst")
    kept = all_.where(u01("gnp", seed, F.col("graph_id"), F.col("src"), F.col("dst")) < p)
    return kept.withColumn("w", (F.floor(u01("weight", seed, F.col("graph_id"), F.col("src"), F.col("dst")) * 4) + 1).cast("long"))


def bfs_diameter(edges: DataFrame, sources: DataFrame | None = None) -> int:
    """Longest shortest path in hops from the sources (default: all nodes): one join and one anti-join a hop."""
    from ..plans.storage import stash

    a = stash(arcs(edges.select("src", "dst")), "arcs")
    s = a.select(F.col("src").alias("node")).distinct() if sources is None else sources.select("node")
    seen = stash(s.select(F.col("node").alias("source"), "node"), "seen")
    front, hops = seen, 0
    while True:
        nxt = front.join(a.withColumnRenamed("src", "node"), "node").select("source", F.col("dst").alias("node")).distinct().join(seen, ["source", "node"], "left_anti")
        front = stash(nxt, "front")
        if not front.limit(1).count():
            break
        hops += 1
        seen = stash(seen.unionAll(front), "seen")
    return hops


def double_sweep(edges: DataFrame, starts: int = 4) -> int:
    """A lower bound of the diameter: searches from a few nodes. No query uses it: stats() is exact at every size."""
    first = arcs(edges).select(F.col("src").alias("node")).distinct().orderBy(u01("sweep", 1, F.col("node")), "node").limit(starts)
    return bfs_diameter(edges, first)


def stats(ag: AbstractGraph) -> dict[str, float]:
    """The eight statistics of an abstract graph. The diameter is exact whatever the size: searches start from every node."""
    e = ag.edges
    n = ag.nodes.count()
    r = e.agg(F.count("*"), F.avg("w"), F.max("w")).first()
    m = r[0]
    top = degrees(e).agg(F.max("degree")).first()[0] or 0
    far = _diameter_in_tasks(e, n) if m <= LOCAL_EDGES else bfs_diameter(e)
    return dict(zip(FEATURES[2:], map(float, (n, m, 2 * m / (n * (n - 1)) if n > 1 else 0.0, far, 2 * m / n if n else 0.0, top, r[1] or 0.0, r[2] or 0.0))))


def _diameter_in_tasks(edges: DataFrame, n: int) -> int:
    """Each task holds the graph and starts from its share of the nodes."""
    tasks = max(1, min(-(-n // SOURCES), edges.sparkSession.sparkContext.defaultParallelism))

    def run(e: pa.Table) -> pa.Table:
        a, b = e.column("src").to_numpy(), e.column("dst").to_numpy()
        ids = np.unique(np.concatenate([a, b]))
        g = Csr(len(ids), np.searchsorted(ids, a), np.searchsorted(ids, b))
        return pa.table({"far": pa.array([diameter(g, np.arange(e.column("task")[0].as_py(), g.n, tasks))], pa.int32())})

    every = edges.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"), "src", "dst")
    return every.groupBy("task").applyInArrow(run, "far int").agg(F.max("far")).first()[0] or 0


def hybrid(combos: DataFrame, graph_stats: DataFrame) -> DataFrame:
    """One row for each combination and graph; both sides are small."""
    return F.broadcast(combos).crossJoin(graph_stats)


def score_graph(g: Csr, n_walks: int, length: int, d: int, seed: int, theta: str = "euclid_distance") -> float:
    """Loss of the weighted graph's embedding under one combination."""
    c, o, n = count_pairs(walks(g, n_walks, length, seed), 5, g.n)
    return reconstruction(g, skip_gram(g.n, c, o, n, d, epochs=1, rate=0.05, seed=seed), theta)


def training_set(spark: SparkSession, graphs: int = 20, kinds: tuple[str, ...] = ("gnp", "planted", "pref_attach"), sizes: tuple[int, int] = (10, 40), n_walks: tuple[int, ...] = WALKS, lengths: tuple[int, ...] = LENGTHS, d: int = 8, seed: int = 1, theta: str = "euclid_distance") -> DataFrame:
    """HYBRID rows: every combination on every random graph, a task for each (graph, combination) up to TRAINING_TASKS tasks. The rows are few and
    small but costly, so their number of parts is given: parts by size would put them all into one task."""
    combos = grid(spark, n_walks, lengths)
    jobs = combos.crossJoin(spark.range(graphs).select(F.col("id").cast("int").alias("graph_id")))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                gid = int(r.graph_id)
                n = sizes[0] + (gid * 7919 + seed) % (sizes[1] - sizes[0] + 1)
                g = random_graph(kinds[gid % len(kinds)], n, seed * 1000 + gid)
                y = score_graph(g, int(r.n_walks), int(r.walk_length), d, seed + gid, theta)
                row = [gid, int(r.combo_id), float(r.n_walks), float(r.walk_length), *map(float, statistics(g)), y]
                yield pd.DataFrame([row], columns=[f.name for f in HYBRID])

    parts = max(1, min(TRAINING_TASKS, graphs * len(n_walks) * len(lengths)))
    return jobs.repartition(parts).mapInPandas(run, HYBRID)


def _matrix(xy: DataFrame, interactions: bool) -> tuple[np.ndarray, np.ndarray]:
    rows = xy.select(*FEATURES, "y").limit(MAX_TRAINING + 1).collect()
    if len(rows) > MAX_TRAINING:
        raise ValueError(f"over {MAX_TRAINING} training rows: use fit_exact, which aggregates")
    a = np.array([list(r) for r in rows], float)
    x = a[:, :-1]
    return (_crossed(x) if interactions else x), a[:, -1]


def _crossed(x: np.ndarray) -> np.ndarray:
    """With the 16 products of a hyperparameter and a statistic."""
    return np.hstack([x, *[x[:, [h]] * x[:, 2:] for h in (0, 1)]])


def fit_sgd(xy: DataFrame, rate: float = 0.05, epochs: int = 3000, batch: int = 64, seed: int = 1, interactions: bool = False) -> np.ndarray:
    """Least squares by mini-batch gradients with momentum, on columns scaled by their root mean square; the scale is folded back, so y is about x.w."""
    x, y = _matrix(xy, interactions)
    scale = np.sqrt((x**2).mean(axis=0))
    scale[scale == 0] = 1
    z, big = x / scale, max(float(np.abs(y).max()), 1e-12)
    rng, w, v = np.random.default_rng(seed), np.zeros(x.shape[1]), np.zeros(x.shape[1])
    for epoch in range(epochs):
        lr = rate / (1 + 4 * epoch / epochs) / x.shape[1]
        order = rng.permutation(len(y))
        for at in range(0, len(y), batch):
            i = order[at : at + batch]
            v = 0.9 * v - lr * 2 * z[i].T @ (z[i] @ w - y[i] / big) / len(i)
            w = w + v
    return w * big / scale


def fit_exact(xy: DataFrame, interactions: bool = False) -> np.ndarray:
    """Normal equations: one aggregate of 55 + 10 sums, then a small solve with minimal norm."""
    if interactions:
        x, y = _matrix(xy, True)
        return np.linalg.pinv(x) @ y
    sums = normal_sums(xy).first()
    n = len(FEATURES)
    a = np.array([[sums[f"s_{min(i, j)}_{max(i, j)}"] for j in range(n)] for i in range(n)])
    b = np.array([sums[f"t_{i}"] for i in range(n)])
    scale = np.sqrt(np.maximum(np.diag(a), 1e-300))
    return np.linalg.pinv(a / np.outer(scale, scale), rcond=1e-12) @ (b / scale) / scale


def normal_sums(xy: DataFrame) -> DataFrame:
    f = FEATURES
    cols = [F.sum(F.col(f[i]) * F.col(f[j])).alias(f"s_{i}_{j}") for i in range(len(f)) for j in range(i, len(f))]
    return xy.agg(*cols, *[F.sum(F.col(c) * F.col("y")).alias(f"t_{i}") for i, c in enumerate(f)])


def fit_mllib(xy: DataFrame) -> np.ndarray:
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    v = VectorAssembler(inputCols=FEATURES, outputCol="x").transform(xy)
    return LinearRegression(featuresCol="x", labelCol="y", fitIntercept=False, regParam=0.0, solver="normal").fit(v).coefficients.toArray()


def sse(xy: DataFrame, w: np.ndarray) -> float:
    pred = sum((F.col(c) * float(v) for c, v in zip(FEATURES, w)), F.lit(0.0))
    return float(xy.agg(F.sum(F.pow(pred - F.col("y"), 2))).first()[0] or 0.0)


def scores(graph_stats: dict[str, float], w: np.ndarray, n_walks: tuple[int, ...] = WALKS, lengths: tuple[int, ...] = LENGTHS) -> list[tuple[int, int, float]]:
    """(walks, length, predicted score) of every combination."""
    s = [graph_stats[f] for f in FEATURES[2:]]
    combos = [(a, b) for a in n_walks for b in lengths]
    x = np.array([[a, b, *s] for a, b in combos], float)
    y = (_crossed(x) if len(w) > len(FEATURES) else x) @ w
    return [(a, b, float(v)) for (a, b), v in zip(combos, y)]


def choose(graph_stats: dict[str, float], w: np.ndarray, n_walks: tuple[int, ...] = WALKS, lengths: tuple[int, ...] = LENGTHS, select: str = "highest") -> tuple[int, int]:
    """The combination with the highest (or lowest) predicted score; ties to the smaller product, then the fewer walks."""
    sign = -1 if select == "highest" else 1
    return min(scores(graph_stats, w, n_walks, lengths), key=lambda t: (round(sign * t[2], 9), t[0] * t[1], t))[:2]


def save(spark: SparkSession, w: np.ndarray, path: str) -> None:
    save_model(spark, {"features": FEATURES, "w": list(map(float, w))}, path)


def load(spark: SparkSession, path: str) -> np.ndarray:
    return np.array(load_model(spark, path)["w"])


def default_model(interactions: bool = False) -> np.ndarray:
    """The weights that train_default() learned and that the package ships."""
    model = json.loads((Path(__file__).parent / "walk_model.json").read_text())
    return np.array(model["crossed" if interactions else "plain"])


def train_default(spark: SparkSession) -> dict[str, list[float]]:
    """The shipped model: every combination on 24 random graphs, fitted by gradients, without and with the 16 products."""
    xy = training_set(spark, graphs=24).cache()
    return {"plain": fit_sgd(xy).tolist(), "crossed": fit_sgd(xy, interactions=True).tolist()}
