"""The experiment tables: link prediction, classification, initializer times, time to a loss, ablations, convergence."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import classify, init, linkpred, metrics, partition, propagate, sgns, target
from ..operators.graph import Graph
from ..plans.storage import stash
from ..sources import graphs as g
from ..sources.tables import table
from .base import edges, nodes

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: Budgets of the registered tables; the functions take any others (the published settings are d=128, 80 walks of 40, window 10, 10 runs).
DIM, WALKS, SEEDS = 16, {"r": 8, "length": 10, "window": 4}, (1,)
RATE = 0.05
OPTIONS = {"uniform-walk": {**WALKS, "rate": RATE}, "biased-walk": {**WALKS, "p": 0.5, "q": 2.0, "rate": RATE}, "edge-proximity": {"rounds": 8, "rate": RATE}}
LINK_GRAPHS, CLASS_GRAPHS = ("wordadj", "docshare", "trade", "copurchase"), ("wordadj", "docshare")
RESULT = "workload string, dataset string, target string, init string, measure string, value double, stderr double, runs int"
JOBS = 8  # jobs of an experiment that run side by side

Row = tuple[str, str, str, str, str, float, float, int]


def query(name: str):  # noqa: ANN201
    def keep(f):  # noqa: ANN001, ANN202
        QUERIES[name] = f
        return f

    return keep


def together(*jobs: Callable[[], object]) -> list:
    with ThreadPoolExecutor(JOBS) as pool:
        return [f.result() for f in [pool.submit(j) for j in jobs]]


def _summed(found: dict[tuple, list[float]]) -> list[Row]:
    """Mean and standard error of each cell over its runs."""
    out = []
    for key, v in sorted(found.items()):
        dev = statistics.stdev(v) if len(v) > 1 else 0.0
        out.append((*key, statistics.fmean(v), dev / len(v) ** 0.5, len(v)))
    return out


def trained(gr: Graph, seed: int, targets: tuple[str, ...], d: int, options: dict[str, dict]) -> dict[tuple[str, str], DataFrame]:
    """{(target, initializer): vectors}; the three starts of a target train on the same samples."""
    spread, plain = together(lambda: stash(init.sketch(gr, d, seed=seed).emb, "start"), lambda: init.random(gr, d, seed).emb)

    def one(t: str) -> dict[tuple[str, str], DataFrame]:
        o = dict(options[t])
        rate = o["rate"]
        if t == "edge-proximity":
            pairs = target.edge_samples(gr.edges, o["rounds"], 1.0, seed)
        else:
            pairs = target.walk_pairs(gr, o["r"], o["length"], o["window"], seed, (o["p"], o["q"]) if "p" in o else None)
        pairs = stash(pairs, "pairs")
        starts = {"sketch": spread, "hierarchical": init.hierarchical(gr, d, t, seed=seed, **o).emb, "random": plain}
        return {(t, k): stash(sgns.fit(pairs, gr.nodes, d, s, 1, rate=rate, seed=seed, tie=t == "edge-proximity"), "emb") for k, s in starts.items()}

    out: dict[tuple[str, str], DataFrame] = {}
    for part in together(*(lambda t=t: one(t) for t in targets)):
        out |= part
    return out


def link_rows(spark: SparkSession, graphs: dict[str, DataFrame], targets: tuple[str, ...] = tuple(target.TARGETS), seeds: tuple[int, ...] = SEEDS, d: int = DIM, options: dict[str, dict] = OPTIONS) -> list[Row]:
    """Precision of every graph, target, initializer and similarity."""
    found: dict[tuple, list[float]] = {}

    def one(name: str, seed: int) -> list[tuple[tuple, float]]:
        s = linkpred.split(graphs[name], seed=seed)
        embs = trained(Graph(s.nodes, s.train), seed, targets, d, options)

        def cell(key: tuple[str, str], sim: str) -> tuple[tuple, float]:
            p = linkpred.precision_global(stash(linkpred.scored(s.pos, s.neg, embs[key], sim), "scored")).first()["precision"]
            return ("W2", name, *key, f"precision_{sim}"), float(p)

        return together(*(lambda k=k, m=m: cell(k, m) for k in embs for m in ("cosine", "euclid")))

    for rows in together(*(lambda n=n, s=s: one(n, s) for s in seeds for n in graphs)):
        for key, v in rows:
            found.setdefault(key, []).append(v)
    return _summed(found)


def class_rows(spark: SparkSession, graphs: dict[str, tuple[DataFrame, DataFrame]], targets: tuple[str, ...] = tuple(target.TARGETS), seeds: tuple[int, ...] = SEEDS[:1], d: int = DIM, options: dict[str, dict] = OPTIONS) -> list[Row]:
    """Micro and macro F1 of every graph, target and initializer; graphs: name -> (edges, labels)."""
    found: dict[tuple, list[float]] = {}

    def one(name: str, seed: int) -> list[tuple[tuple, float]]:
        e, labels = graphs[name]
        gr = Graph(stash(nodes(e), "nodes"), e)
        split = stash(classify.node_split(labels.join(gr.nodes, "node", "left_semi"), seed=seed), "split")
        embs = trained(gr, seed, targets, d, options)

        def cell(key: tuple[str, str]) -> list[tuple[tuple, float]]:
            pred = stash(classify.fit(embs[key], split), "pred")
            r = classify.f1(pred.select("node", "label"), pred.select("node", F.col("truth").alias("label"))).first()
            return [(("W3", name, *key, m), float(r[m])) for m in ("micro", "macro")]

        return [x for rows in together(*(lambda k=k: cell(k) for k in embs)) for x in rows]

    for rows in together(*(lambda n=n, s=s: one(n, s) for s in seeds for n in graphs)):
        for key, v in rows:
            found.setdefault(key, []).append(v)
    return _summed(found)


def _labels(spark: SparkSession, sf: str, name: str) -> DataFrame:
    if name == "wordadj":
        return stash(g.word_labels(spark, sf).where("label is not null"), "labels")
    return stash(table(spark, sf, "documents").select(F.col("doc_id").alias("node"), F.col("lang").alias("label")).where("lang is not null"), "labels")


@query("link_prediction_table")
def _links(spark: SparkSession, sf: str) -> DataFrame:
    """72 cells: four graphs, three targets, three initializers, two similarities."""
    return spark.createDataFrame(link_rows(spark, {k: edges(spark, sf, k) for k in LINK_GRAPHS}), RESULT)


@query("link_prediction_planted")
def _planted(spark: SparkSession, sf: str) -> DataFrame:
    """The same protocol on planted groups, where the truth is known."""
    return spark.createDataFrame(link_rows(spark, {"planted": stash(g.planted(spark, 20, 30, 0.3, 0.004), "edges")}), RESULT)


@query("classification_table")
def _classes(spark: SparkSession, sf: str) -> DataFrame:
    """36 cells: two labelled graphs, three targets, three initializers, two scores."""
    return spark.createDataFrame(class_rows(spark, {k: (edges(spark, sf, k), _labels(spark, sf, k)) for k in CLASS_GRAPHS}), RESULT)


@query("multi_label_table")
def _multi(spark: SparkSession, sf: str) -> DataFrame:
    """Several labels a node: language, quality and toxicity of documents, as many surest labels as a document has."""
    e = edges(spark, sf, "docshare")
    gr = Graph(stash(nodes(e), "nodes"), e)
    marks = table(spark, sf, "labels").select(F.col("doc_id").alias("node"), F.explode(F.array(F.when(F.col("quality") == 1, "good"), F.when(F.col("toxic") == 1, "toxic"))).alias("label"))
    labels = stash(_labels(spark, sf, "docshare").unionByName(marks).where("label is not null").distinct().join(gr.nodes, "node", "left_semi"), "labels")
    split = stash(classify.node_split(labels), "split")
    o = OPTIONS["uniform-walk"]
    pairs = stash(target.walk_pairs(gr, o["r"], o["length"], o["window"]), "pairs")  # the same for both starts

    def one(name: str, start: Callable[..., init.InitResult]) -> list[Row]:
        emb = stash(sgns.fit(pairs, gr.nodes, DIM, start(gr, DIM).emb, rate=o["rate"]), "emb")
        pred = stash(classify.fit_multi(emb, split), "pred")
        r = classify.f1(pred, split.where("role = 'test'").select("node", "label")).first()
        return [("W3", "docshare-multi", "uniform-walk", name, m, float(r[m]), 0.0, 1) for m in ("micro", "macro")]

    rows = [row for part in together(lambda: one("sketch", init.sketch), lambda: one("random", init.random)) for row in part]
    return spark.createDataFrame(rows, RESULT)


def time_rows(graphs: dict[str, DataFrame], seeds: tuple[int, ...] = SEEDS, d: int = DIM, walks: dict[str, int] = WALKS) -> list[Row]:
    """Seconds of each initializer on whole graphs and their ratio. Both walk equally often and far; runs take turns, one at a time."""
    found: dict[tuple, list[float]] = {}
    for seed in seeds:
        for name, e in graphs.items():
            gr = Graph(stash(nodes(e), "nodes"), e)
            pair = (walks["r"], walks["length"])
            runs = {
                "sketch": lambda: init.sketch(gr, d, how=pair, seed=seed),
                "sketch, learned pair": lambda: init.sketch(gr, d, seed=seed),
                "hierarchical": lambda: init.hierarchical(gr, d, seed=seed, rate=RATE, **walks),
                "random": lambda: init.random(gr, d, seed),
            }
            took = {}
            for k, run in runs.items():
                t = time.time()
                r = run()
                r.emb.write.format("noop").mode("overwrite").save()
                took[k] = time.time() - t
                found.setdefault(("W4", name, "uniform-walk", k, "seconds"), []).append(took[k])
                if r.trace:
                    found.setdefault(("W4", name, "uniform-walk", k, "converged"), []).append(float(r.trace[-1]["converged"]))
            for k in ("sketch", "sketch, learned pair"):
                found.setdefault(("W4", name, "uniform-walk", k, "ratio to hierarchical"), []).append(took[k] / took["hierarchical"])
    return _summed(found)


@query("initializer_times")
def _times(spark: SparkSession, sf: str) -> DataFrame:
    graphs = {k: edges(spark, sf, k) for k in LINK_GRAPHS}
    return spark.createDataFrame(time_rows(graphs, SEEDS[:1]), RESULT)


def loss_rows(gr: Graph, dataset: str, d: int = DIM, epochs: int = 2, seed: int = 1, options: dict = OPTIONS["uniform-walk"]) -> list[Row]:
    """End-to-end seconds (start and training) until the loss that the random start reaches after `epochs`, for each start; -1 where it is not reached.

    The three starts run side by side, each step of theirs in a few tasks, so
    all are timed while the others run.
    """
    pairs = stash(target.walk_pairs(gr, options["r"], options["length"], options["window"], seed), "pairs")
    starts = {"random": lambda: init.random(gr, d, seed), "sketch": lambda: init.sketch(gr, d, seed=seed), "hierarchical": lambda: init.hierarchical(gr, d, seed=seed, **options)}

    def one(make: Callable[[], init.InitResult]) -> tuple[float, list[tuple[float, float]]]:
        """Seconds of the start, then (seconds of training so far, loss) after each epoch."""
        t = time.time()
        emb = make().emb
        own, spent, after = time.time() - t, 0.0, []
        for epoch in range(epochs):
            t = time.time()
            emb = stash(sgns.fit(pairs, gr.nodes, d, emb, 1, rate=options["rate"], seed=seed + epoch), "emb")
            spent += time.time() - t
            after.append((spent, metrics.reconstruction(gr.edges, emb, "cosine")))
        return own, after

    runs = dict(zip(starts, together(*(lambda m=m: one(m) for m in starts.values()))))
    goal = runs["random"][1][-1][1]
    rows: list[Row] = []
    for name, (own, after) in runs.items():
        rows += [("W4", dataset, "uniform-walk", name, f"loss after {i + 1}", loss, 0.0, 1) for i, (_, loss) in enumerate(after)]
        ends = after[-1:] if name == "random" else after  # the goal is the random start's last loss
        hit = next((own + spent for spent, loss in ends if loss <= goal), -1.0)
        rows += [("W4", dataset, "uniform-walk", name, "seconds of the start", own, 0.0, 1), ("W4", dataset, "uniform-walk", name, "seconds of training", after[-1][0], 0.0, 1), ("W4", dataset, "uniform-walk", name, "seconds to the loss", hit, 0.0, 1)]
    return rows


@query("time_to_loss")
def _to_loss(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    return spark.createDataFrame(loss_rows(Graph(stash(nodes(e), "nodes"), e), "wordadj"), RESULT)


def ablation_rows(e: DataFrame, dataset: str, d: int = DIM, seed: int = 1) -> list[Row]:
    """Link precision of the sketch start alone under each choice of the method."""
    s = linkpred.split(e, seed=seed)
    gr = Graph(s.nodes, s.train)
    n = gr.nodes.count()
    k = partition.choose_k(n)
    parts = stash(partition.multilevel(gr, k, seed=seed), "parts")  # the same parts wherever they are not what varies
    base = {"partitioner": parts, "k": k}
    kinds: dict[str, dict] = {
        "learned, highest score": base, "learned, lowest score": {**base, "select": "lowest"}, "learned with products, lowest": {**base, "how": "learned-crossed", "select": "lowest"},
        "random pair": {**base, "how": "random"}, "grid search": {**base, "how": "grid"},
        "no propagation": {**base, "max_iter": 0}, **{f"delta {c} / n": {**base, "delta": c / n} for c in (10.0, 0.1)},
        **{f"k = {f} sqrt n": {"k": max(2, round(f * n**0.5)), "how": (10, 10)} for f in (0.5, 1, 2, 4)},
        **{f"parts by {p}": {"partitioner": p, "how": (10, 10)} for p in ("label_prop", "hash", "range")},
    }

    def one(name: str, options: dict) -> list[Row]:
        r = init.sketch(gr, d, seed=seed, **options)
        out = [("W5", dataset, "none", name, "precision_cosine", float(linkpred.precision_global(stash(linkpred.scored(s.pos, s.neg, r.emb), "scored")).first()["precision"]))]
        out += [("W5", dataset, "none", name, "steps", float(len(r.trace))), ("W5", dataset, "none", name, "spread", propagate.spread(r.emb)), ("W5", dataset, "none", name, "distinct vectors", float(r.emb.select("vec").distinct().count()))]
        out += [("W5", dataset, "none", name, "walks", float(r.hyper[0])), ("W5", dataset, "none", name, "length", float(r.hyper[1]))]
        return [(*x, 0.0, 1) for x in out]

    return [row for rows in together(*(lambda a=a, b=b: one(a, b) for a, b in kinds.items())) for row in rows]


@query("ablations")
def _ablations(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(ablation_rows(edges(spark, sf, "wordadj"), "wordadj"), RESULT)


@query("ablation_no_propagation")
def _plain(spark: SparkSession, sf: str) -> DataFrame:
    """Without propagation the nodes of a part share one vector: distinct vectors = parts."""
    e = edges(spark, sf, "wordadj")
    r = init.sketch(Graph(stash(nodes(e), "nodes"), e), DIM, max_iter=0)
    return r.emb.agg(F.count_distinct("vec").alias("vectors")).crossJoin(r.parts.agg(F.count_distinct("part").alias("parts")))


@query("propagation_convergence")
def _converged(spark: SparkSession, sf: str) -> DataFrame:
    """The moves of every step until their mean is at most 1 / nodes."""
    e = edges(spark, sf, "wordadj")
    r = init.sketch(Graph(stash(nodes(e), "nodes"), e), DIM, how=(10, 10))
    return spark.createDataFrame([(t["iter"], t["delta"], t["converged"]) for t in r.trace], "iter int, delta double, converged boolean")


@query("spark_cost")
def _cost(spark: SparkSession, sf: str) -> DataFrame:
    """What a propagation step costs in Spark: jobs, stages, tasks, records and bytes shuffled."""
    e = edges(spark, sf)
    v = stash(sgns.random_vectors(nodes(e), DIM), "emb")
    got = metrics.spark_cost(spark, lambda: propagate.step(e, v).write.format("noop").mode("overwrite").save())
    return spark.createDataFrame([(k, float(x)) for k, x in sorted(got.items())], "measure string, value double")


