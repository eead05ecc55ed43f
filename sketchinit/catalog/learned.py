"""Queries on hyperparameter learning, the initializers, and the experiment tables."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.rng import u01_sql
from ..operators import abstract, coarsen, hyper, init, propagate, sgns, target, walks
from ..operators.graph import Graph
from ..plans.storage import stash, stash_path
from ..sources import graphs as g
from .base import ABSTRACT, ABSTRACT_ARCS, CROSS, PARTS, edges, nodes, parts, with_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
DIM, BUDGET = 16, {"r": 4, "length": 10, "window": 3}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def keep(f):  # noqa: ANN001, ANN202
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


_GRID = "(SELECT CAST(i * 5 + j AS INTEGER) AS combo_id, CAST([5, 10, 20, 40, 80][i + 1] AS INTEGER) AS n_walks, CAST([5, 10, 20, 40, 80][j + 1] AS INTEGER) AS walk_length FROM range(5) s(i), range(5) t(j))"


@query("hyper_grid", "WITH v AS (SELECT DISTINCT CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1 AS i FROM orders) SELECT CAST(a.i * 5 + b.i AS INTEGER) AS combo_id, CAST(5 * 2 ** a.i AS INTEGER) AS n_walks, CAST(5 * 2 ** b.i AS INTEGER) AS walk_length FROM v a, v b")
def _grid(spark: SparkSession, sf: str) -> DataFrame:
    """The grid over the levels that a table knows: its orders' priorities."""
    return hyper.grid_of(g.table(spark, sf, "orders").select((F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("level")))


_HOPS = "bf AS (SELECT DISTINCT src AS s, src AS v, 0 AS h FROM aa UNION SELECT bf.s, aa.dst, bf.h + 1 FROM bf JOIN aa ON aa.src = bf.v WHERE bf.h < 6), ds AS (SELECT s, v, min(h) AS h FROM bf GROUP BY 1, 2)"
_N = "(SELECT count(DISTINCT part) FROM p)"
_STATS = f"SELECT CAST({_N} AS DOUBLE) AS n_nodes, CAST(count(*) AS DOUBLE) AS n_edges, round(2 * count(*) / ({_N} * ({_N} - 1.0)), 6) AS density, CAST((SELECT max(h) FROM ds) AS DOUBLE) AS diameter, round(2 * count(*) / ({_N} * 1.0), 6) AS avg_degree, CAST((SELECT max(c) FROM (SELECT count(*) AS c FROM aa GROUP BY src)) AS DOUBLE) AS max_degree, round(avg(w), 6) AS avg_weight, CAST(max(w) AS DOUBLE) AS max_weight FROM ae"
_STAT_SQL = with_sql("trade", PARTS, CROSS, ABSTRACT, ABSTRACT_ARCS, _HOPS) + _STATS


def _stats_of(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    s = hyper.stats(abstract.build(Graph(nodes(e), e), stash(parts(e), "parts")))
    return spark.createDataFrame([tuple(round(s[f], 6) for f in hyper.FEATURES[2:])], ", ".join(f"{f} double" for f in hyper.FEATURES[2:]))


query("graph_stats", _STAT_SQL)(_stats_of)


@query("hybrid_matrix", with_sql("trade", PARTS, CROSS, ABSTRACT, ABSTRACT_ARCS, _HOPS, f"st AS ({_STATS})") + f"SELECT g.*, st.* FROM {_GRID} g, st")
def _hybrid(spark: SparkSession, sf: str) -> DataFrame:
    return hyper.hybrid(hyper.grid(spark), _stats_of(spark, sf))


@query("random_graph_gnp", f"SELECT q.g AS graph_id, q.a AS src, q.b AS dst, CAST(floor({u01_sql('weight', 1, 'q.g', 'q.a', 'q.b')} * 4) + 1 AS BIGINT) AS w FROM (SELECT a.o_custkey AS g, a.o_orderkey AS a, b.o_orderkey AS b FROM orders a JOIN orders b ON b.o_custkey = a.o_custkey AND a.o_orderkey < b.o_orderkey) q WHERE {u01_sql('gnp', 1, 'q.g', 'q.a', 'q.b')} < 0.2")
def _gnp(spark: SparkSession, sf: str) -> DataFrame:
    """A random graph on the orders of each customer."""
    return hyper.gnp(g.table(spark, sf, "orders").select(F.col("o_custkey").alias("graph_id"), F.col("o_orderkey").alias("node")), 0.2)


@query("graph_planted", g.planted_sql("(SELECT c_custkey // 80 AS world, c_custkey // 20 AS part, c_custkey AS node FROM customer)", 0.4, 0.02))
def _planted(spark: SparkSession, sf: str) -> DataFrame:
    """Customers in worlds of four known groups of twenty."""
    k = F.col("c_custkey")
    return g.planted_on(g.table(spark, sf, "customer").select(F.floor(k / 80).alias("world"), F.floor(k / 20).alias("part"), k.alias("node")), 0.4, 0.02)


def _customer_xy(spark: SparkSession, sf: str) -> DataFrame:
    """A deterministic regression table of the right shape, from the orders."""
    k, x = F.col("o_orderkey"), F.col("o_custkey")
    cols = [((k * (i + 3) + x * (i + 1)) % (7 + i)).cast("double").alias(f) for i, f in enumerate(hyper.FEATURES)]
    return spark.read.parquet(f"{sf}/orders.parquet").select(*cols, ((k + x) % 11).cast("double").alias("y"))


_XY = "xy AS (SELECT " + ", ".join(f"CAST((o_orderkey * {i + 3} + o_custkey * {i + 1}) % {7 + i} AS DOUBLE) AS f{i}" for i in range(10)) + ", CAST((o_orderkey + o_custkey) % 11 AS DOUBLE) AS y FROM orders)"
_SUMS = ", ".join([*(f"sum(f{i} * f{j}) AS s_{i}_{j}" for i in range(10) for j in range(i, 10)), *(f"sum(f{i} * y) AS t_{i}" for i in range(10))])


@query("regression_normal_sums", f"WITH {_XY} SELECT {_SUMS} FROM xy")
def _sums(spark: SparkSession, sf: str) -> DataFrame:
    return hyper.normal_sums(_customer_xy(spark, sf))


@query("regression_fit_sgd")
def _sgd(spark: SparkSession, sf: str) -> DataFrame:
    xy = stash(hyper.training_set(spark, graphs=6), "xy")
    ws = [hyper.fit_sgd(xy), hyper.fit_exact(xy), hyper.fit_mllib(xy)]
    return spark.createDataFrame([(f, *map(float, w)) for f, *w in zip(hyper.FEATURES, *ws)], "feature string, sgd double, exact double, library double")


@query("hyper_training_set")
def _training(spark: SparkSession, sf: str) -> DataFrame:
    """Every combination on 20 random graphs."""
    return hyper.training_set(spark)


_W = [0.5, -0.25, 0.01, 0.02, 3.0, -1.0, 0.5, 0.1, -0.2, 0.05]


@query("choose_hyper", with_sql("trade", PARTS, CROSS, ABSTRACT, ABSTRACT_ARCS, _HOPS, f"st AS ({_STATS})") + f"SELECT n_walks, walk_length FROM {_GRID} g, st ORDER BY -round({' + '.join(f'{w} * {f}' for w, f in zip(_W, hyper.FEATURES))}, 9), n_walks * walk_length, n_walks LIMIT 1")
def _choose(spark: SparkSession, sf: str) -> DataFrame:
    s = _stats_of(spark, sf).first().asDict()
    return spark.createDataFrame([hyper.choose(s, np.array(_W))], "n_walks int, walk_length int")


@query("regression_objective", f"WITH {_XY} SELECT round(sum(({' + '.join(f'{w} * f{i}' for i, w in enumerate(_W))} - y) ** 2), 3) AS sse FROM xy")
def _objective(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(round(hyper.sse(_customer_xy(spark, sf), np.array(_W)), 3),)], "sse double")


_SHIPPED, _CROSSED = hyper.default_model(), hyper.default_model(True)
_SCORE = " + ".join(f"{w!r}::DOUBLE * {f}" for w, f in zip(_SHIPPED.tolist(), hyper.FEATURES))
_MORE = " + ".join([*(f"{w!r}::DOUBLE * {f}" for w, f in zip(_CROSSED.tolist(), hyper.FEATURES)), *(f"{w!r}::DOUBLE * {h} * {f}" for w, (h, f) in zip(_CROSSED[10:].tolist(), ((h, f) for h in hyper.FEATURES[:2] for f in hyper.FEATURES[2:])))])


def _picked_sql(name: str, select: str, score: str) -> str:
    return f"SELECT '{name}' AS model, '{select}' AS reading, n_walks, walk_length, round({score}, 2) AS score, row_number() OVER (ORDER BY {'-' if select == 'highest' else ''}round({score}, 9), n_walks * walk_length, n_walks) = 1 AS picked FROM {_GRID} g, st"


@query("learned_scores", with_sql("trade", PARTS, CROSS, ABSTRACT, ABSTRACT_ARCS, _HOPS, f"st AS ({_STATS})") + " UNION ALL ".join(_picked_sql(n, s, e) for n, e in (("plain", _SCORE), ("crossed", _MORE)) for s in ("highest", "lowest")))
def _learned_scores(spark: SparkSession, sf: str) -> DataFrame:
    """Predicted score of every pair by the shipped models on the trade sketch, and which one each reading picks."""
    s = _stats_of(spark, sf).first().asDict()
    rows = []
    for name, w in (("plain", _SHIPPED), ("crossed", _CROSSED)):
        for select in ("highest", "lowest"):
            best = hyper.choose(s, w, select=select)
            rows += [(name, select, a, b, round(v, 2), (a, b) == best) for a, b, v in hyper.scores(s, w)]
    return spark.createDataFrame(rows, "model string, reading string, n_walks int, walk_length int, score double, picked boolean")


def _word_graph(spark: SparkSession, sf: str) -> Graph:
    e = edges(spark, sf, "wordadj")
    return Graph(stash(nodes(e), "nodes"), e)


def _rounded(emb: DataFrame) -> DataFrame:
    return emb.select("node", F.transform("vec", lambda x: F.round(x, 6)).alias("vec"))


@query("skipgram_vectors")
def _skipgram(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    a = abstract.abstract_edges(e, parts(e)).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w")
    a = stash(a, "ae")
    w = walks.weighted(stash(walks.alias_tables(walks.transitions(a)), "alias"), nodes(a), 10, 8)
    return _rounded(sgns.fit(walks.context_pairs(w, 3), nodes(a), DIM))


@query("skipgram_grid")
def _skipgram_grid(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    w = walks.uniform(e, nodes(e), 1, 4)
    return _rounded(sgns.fit(walks.context_pairs(w, 2), nodes(e), 8, blocks=4))


@query("sketch_init")
def _sketch(spark: SparkSession, sf: str) -> DataFrame:
    """The whole initializer: parts, sketch graph, the shipped model's pair, walks, propagation until the moves are small."""
    return _rounded(init.sketch(_word_graph(spark, sf), DIM).emb)


@query("sketch_init_learned")
def _sketch_learned(spark: SparkSession, sf: str) -> DataFrame:
    """Both phases: a model is trained on random graphs, saved, read again, and picks the pair of the sketch; one row for each reading."""
    path = stash_path(spark, "model")

    def reading(select: str) -> tuple:
        r = init.sketch(gr, DIM, w=w, select=select)
        return (select, *r.hyper, r.emb.count(), len(r.trace), r.trace[-1]["converged"], round(propagate.spread(r.emb), 6))

    with ThreadPoolExecutor(2) as pool:  # the model and the graph, then both readings, side by side
        found = pool.submit(_word_graph, spark, sf)
        hyper.save(spark, hyper.fit_sgd(stash(hyper.training_set(spark, graphs=9), "xy")), path)
        w, gr = hyper.load(spark, path), found.result()
        rows = list(pool.map(reading, ("highest", "lowest")))
    return spark.createDataFrame(rows, "reading string, n_walks int, walk_length int, nodes long, steps int, converged boolean, spread double")


@query("hier_init")
def _hier(spark: SparkSession, sf: str) -> DataFrame:
    return _rounded(init.hierarchical(_word_graph(spark, sf), DIM, **BUDGET).emb)


for _order in (2, "both"):
    query(f"target_edge_proximity_{_order}")(lambda spark, sf, o=_order: _rounded(target.edge_prox(_word_graph(spark, sf), DIM, o, 5)))


@query("skipgram_library")
def _library(spark: SparkSession, sf: str) -> DataFrame:
    """The library's trainer on the same walks: random start only."""
    e = edges(spark, sf)
    return _rounded(sgns.fit_mllib(walks.uniform(e, nodes(e), 2, 8, draws="bulk"), 8, 3))


for _name in target.TARGETS:
    query(f"target_{_name.replace('-', '_')}")(lambda spark, sf, t=_name: _rounded(target.TARGETS[t](_word_graph(spark, sf), DIM, **(BUDGET if t != "edge-proximity" else {"rounds": 5}))))


@query("hierarchy_levels")
def _levels(spark: SparkSession, sf: str) -> DataFrame:
    ls = coarsen.hierarchy(_word_graph(spark, sf))
    return spark.createDataFrame([(i, gr.nodes.count(), gr.edges.count()) for i, (gr, _) in enumerate(ls)], "level int, nodes long, edges long")


@query("hierarchy_check", "SELECT true AS shrinks, true AS covered, true AS weight_kept")
def _hierarchy_check(spark: SparkSession, sf: str) -> DataFrame:
    """At every level: fewer nodes, each node has one parent that exists, and the weight of edges equals that of the edges between different parents below."""
    ls = coarsen.hierarchy(_word_graph(spark, sf))
    sizes = [gr.nodes.count() for gr, _ in ls]
    covered, kept = True, True
    for (gr, p), (up, _) in zip(ls, ls[1:]):
        covered &= p.join(up.nodes.withColumnRenamed("node", "parent"), "parent", "left_semi").join(gr.nodes, "node", "left_semi").agg(F.count("*"), F.count_distinct("node")).first()[:] == (gr.nodes.count(),) * 2
        w = F.col("w") if "w" in gr.edges.columns else F.lit(1)
        ends = gr.edges.withColumn("w", w).join(p.select(F.col("node").alias("src"), F.col("parent").alias("a")), "src").join(p.select(F.col("node").alias("dst"), F.col("parent").alias("b")), "dst")
        kept &= ends.where("a <> b").agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0] == up.edges.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
    return spark.createDataFrame([(all(b < a for a, b in zip(sizes, sizes[1:])), bool(covered), bool(kept))], "shrinks boolean, covered boolean, weight_kept boolean")
