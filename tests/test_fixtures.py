"""Hand-computed examples and invariants of the methods."""

from __future__ import annotations

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchinit.functions import vec
from sketchinit.functions.rng import u32, u32_py
from sketchinit.operators import abstract, classify, coarsen, components, graph, hyper, init, linkpred, local, metrics, partition, propagate, sgns, target, walks
from sketchinit.operators.graph import Graph
from sketchinit.operators.local import Csr, alias_table, diameter, random_graph, reconstruction
from sketchinit.plans import storage
from sketchinit.sources import graphs, pairs, tables

FIG = [(1, 2), (1, 3), (2, 3), (4, 5), (4, 6), (5, 6), (7, 8), (7, 9), (8, 9), (10, 11), (10, 12), (11, 12), (3, 4), (2, 5), (6, 7), (9, 10)]


def make(spark, pairs, nodes=None):
    return graph.canonical(spark.createDataFrame(pairs, "src long, dst long"), None if nodes is None else spark.createDataFrame([(n,) for n in nodes], "node long"))


@pytest.fixture(scope="module")
def fig(spark):
    g = make(spark, FIG)
    parts = spark.createDataFrame([(n, (n - 1) // 3) for n in range(1, 13)], "node long, part int")
    return g, parts


def test_portable_hash(spark):
    r = spark.range(3).select(u32("x", 5, F.col("id")).alias("h")).collect()
    assert [x.h for x in r] == [u32_py("x", 5, i) for i in range(3)]


def test_worked_example(fig):
    g, parts = fig
    assert partition.choose_k(12) == 4
    ag = abstract.build(g, parts)
    assert sorted(map(tuple, ag.edges.collect())) == [(0, 1, 2), (1, 2, 1), (2, 3, 1)]
    assert ag.nodes.agg(F.sum("internal_edges")).first()[0] == 12 and partition.edge_cut(g.edges, parts).count() == 4
    s = hyper.stats(ag)
    assert [s[f] for f in hyper.FEATURES[2:]] == [4, 3, 0.5, 3, 1.5, 2, pytest.approx(4 / 3), 2]
    assert hyper.bfs_diameter(ag.edges) == 3 and hyper.double_sweep(ag.edges) == 3
    t = {(r.src, r.dst): r.prob for r in walks.transitions(ag.edges).collect()}
    assert t[1, 0] == pytest.approx(2 / 3) and t[1, 2] == pytest.approx(1 / 3)


def test_canonical_drops_what_is_no_edge(spark):
    g = make(spark, [(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None)])
    assert [tuple(r) for r in g.edges.collect()] == [(1, 2)]
    with pytest.raises(ValueError):
        graph.canonical(g.edges, directed=True)


@pytest.mark.parametrize("weights,keep,alias", [([1, 1, 2], [0.75, 0.75, 1.0], [2, 2, 2]), ([3], [1.0], [0]), ([2, 2, 2, 2], [1.0] * 4, [0, 1, 2, 3])])
def test_alias(weights, keep, alias):
    k, a = alias_table(weights)
    assert k.tolist() == pytest.approx(keep) and a.tolist() == alias


def test_alias_keeps_every_probability():
    rng = np.random.default_rng(3)
    for n in (2, 7, 50, 400):
        w = rng.random(n) ** 4 + 1e-9
        k, a = alias_table(w)
        mass = k.copy()
        np.add.at(mass, a, 1 - k)
        assert np.allclose(mass / n, w / w.sum()) and (k >= 0).all() and (k <= 1).all()


def test_propagation_step(spark):
    g = make(spark, [(1, 2), (2, 3)], [9])
    emb = spark.createDataFrame([(1, [0.0]), (2, [0.0]), (3, [6.0]), (9, [4.0])], "node long, vec array<double>")
    out = propagate.step(g.edges, emb)
    got = {r.node: r.vec[0] for r in out.collect()}
    assert got == {1: 0.0, 2: 1.5, 3: 3.0, 9: 4.0}
    assert propagate.displacement(emb, out) == pytest.approx(1.125)


def test_propagation_by_membership(spark, fig):
    g, parts = fig
    f_a = spark.createDataFrame([(p, [float(p), 1.0 - p]) for p in range(4)], "part int, vec array<double>")
    m = propagate.membership(g.edges, parts, 3)
    assert all(r.s == pytest.approx(1) for r in m.groupBy("node").agg(F.sum("weight").alias("s")).collect())
    dense = {r.node: r.vec for r in propagate.fixed(g.edges, propagate.inherit(parts, f_a), 3).collect()}
    for r in propagate.from_membership(m, f_a).collect():
        assert r.vec == pytest.approx(dense[r.node])
    emb, trace = propagate.run(g, parts, f_a, delta=1e9)
    assert len(trace) == 1 and trace[0]["converged"]  # at least one step
    emb, trace = propagate.run(g, parts, f_a, max_iter=0)
    assert not trace and emb.select("vec").distinct().count() == 4 and propagate.spread(emb) > 0


def test_loss_without_all_pairs(spark):
    g = Csr(2, np.array([0]), np.array([1]), np.array([2.0]))
    assert reconstruction(g, np.array([[0.0], [1.0]])) == pytest.approx(2)
    rng = np.random.default_rng(1)
    e = [(i, j) for i, j in itertools.combinations(range(8), 2) if (i * j) % 3 == 1]
    x = rng.normal(size=(8, 3))
    df, emb = spark.createDataFrame(e, "src long, dst long"), spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "node long, vec array<double>")
    a = np.zeros((8, 8))
    for i, j in e:
        a[i, j] = a[j, i] = 1
    n = x / np.linalg.norm(x, axis=1, keepdims=True)
    dist = np.linalg.norm(x[:, None] - x[None], axis=2)
    for theta, t in (("dot", x @ x.T), ("cosine", n @ n.T), ("euclid_distance", dist), ("neg_distance", -dist)):
        want = ((a - t) ** 2).sum()
        assert metrics.reconstruction(df, emb, theta) == pytest.approx(want)
        assert reconstruction(Csr(8, *(np.array(c) for c in zip(*e))), x, theta) == pytest.approx(want)


def test_similarities(spark):
    r = spark.createDataFrame([([3.0, 4.0], [4.0, 3.0], [0.0, 0.0])], "a array<double>, b array<double>, z array<double>")
    assert r.select(vec.cosine(r.a, r.b), vec.euclid(r.a, r.b), vec.cosine(r.a, r.z)).first()[:] == (pytest.approx(0.96), pytest.approx(2**0.5), None)
    vec.register(spark)
    r.createOrReplaceTempView("r")
    assert spark.sql("SELECT vec_cosine(a, b) c, vec_euclid(a, b) d FROM r").first().c == pytest.approx(0.96)
    assert spark.sql("SELECT count(*) n FROM skip_gram_pairs(array(1L, 2L, 3L), 1)").first().n == 4


def test_top_pairs(spark):
    t = spark.createDataFrame([(1, 2, 1, -0.1), (1, 3, 1, -0.4), (2, 3, 0, -0.2), (4, 5, 0, -0.9)], "src long, dst long, y int, s double")
    assert linkpred.precision_global(t).first()["precision"] == 0.5
    assert linkpred.auc(t) == pytest.approx(0.75)
    assert linkpred.precision_global(t.limit(0)).first()["precision"] == 0


def test_f1(spark):
    truth = spark.createDataFrame(list(zip(range(4), "AABC")), "node long, label string")
    pred = spark.createDataFrame(list(zip(range(4), "ABBB")), "node long, label string")
    r = classify.f1(pred, truth).first()
    assert (r.micro, r.macro) == (0.5, pytest.approx(7 / 18, abs=1e-6))


def test_components(spark):
    import random

    rng = random.Random(2)
    pairs = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(1000 + i, 1001 + i) for i in range(40)]
    root = {v: v for p in pairs for v in p}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    for a, b in pairs:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    got = {r.node: r.root for r in components.connected(spark.createDataFrame(pairs, "src long, dst long")).collect()}
    linked = {v for a, b in pairs if a != b for v in (a, b)}
    assert got == {v: find(v) for v in linked}
    assert components.connected(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_split_protocol(spark):
    e = graphs.planted(spark, 4, 15, 0.5, 0.03)
    s = linkpred.split(e)
    edges, pos, neg, train = ({tuple(r)[:2] for r in x.select("src", "dst").collect()} for x in (e, s.pos, s.neg, s.train))
    assert s.held == -(-len(edges) // 10) and not neg & edges and not pos & train and pos <= edges
    assert len(pos) == len(neg) and not s.unmatched
    deg = lambda x: np.bincount(np.array(sorted(x)).ravel(), minlength=60)
    assert (deg(pos) == deg(neg)).all()
    c = {r.node for r in s.nodes.collect()}
    assert all(a in c and b in c for a, b in pos | neg | train)
    full = spark.createDataFrame(list(itertools.combinations(range(6), 2)), "src long, dst long")
    assert linkpred.uniform_negatives(full, spark.range(6).withColumnRenamed("id", "node"), 5).count() == 0


def test_partitions(spark):
    e = graphs.planted(spark, 6, 20, 0.5, 0.01)
    g = graph.canonical(e)
    n = g.nodes.count()
    cut = {}
    for name, p in (("multilevel", partition.multilevel(g, 6)), ("label_prop", partition.label_prop(g, 6)), ("hash", partition.hashed(g.nodes, 6))):
        assert p.count() == n == p.select("node").distinct().count()
        if name != "hash":
            r = partition.balance(p, 6, 0.03).first()
            assert r.ok and r.parts == 6, name
        cut[name] = partition.edge_cut(g.edges, p).count()
    assert cut["multilevel"] < cut["label_prop"] <= cut["hash"]
    assert partition.multilevel(g, n).select("part").distinct().count() == n
    with pytest.raises(ValueError):
        partition.from_table(spark.createDataFrame([(0, 1)], "node long, part int"), g.nodes)


def test_walks_follow_edges(spark, fig):
    g, parts = fig
    ok = {(a, b) for a, b in FIG} | {(b, a) for a, b in FIG}
    for w in (walks.uniform(g.edges, g.nodes, 2, 5), walks.biased(g.edges, g.nodes, 2, 5, 0.5, 2.0)):
        rows = w.collect()
        assert len(rows) == 24
        for r in rows:
            assert len(r.path) == 5 and all(p in ok for p in zip(r.path, r.path[1:]))
    assert walks.uniform(g.edges, spark.createDataFrame([(77,)], "node long"), 1, 4).first().path == [77]


def test_alias_and_scan_agree(spark, fig):
    g, parts = fig
    e = abstract.build(g, parts).edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w")
    t, n = walks.transitions(e), spark.createDataFrame([(1,)], "node long")
    for w in (walks.weighted(walks.alias_tables(t), n, 900, 2), walks.by_cdf(t, n, 900, 2)):
        share = w.where(F.element_at("path", 2) == 0).count() / 900
        assert abs(share - 2 / 3) < 4 * (2 / 9 / 900) ** 0.5


def test_warm_start_matters(spark, fig):
    g, _ = fig
    far = spark.createDataFrame([(n, [float((n - 1) // 3 == k) * 3 for k in range(4)]) for n in range(1, 13)], "node long, vec array<double>")
    for f in target.TARGETS.values():
        out = f(g, 4, init=far, **({"r": 1, "length": 3} if f is not target.edge_prox else {"rounds": 1}))
        assert {r.node for r in out.collect()} == set(range(1, 13))
        near = metrics.reconstruction(g.edges, out, "euclid_distance")
        assert abs(near - metrics.reconstruction(g.edges, far, "euclid_distance")) < abs(near)
    assert len(target.edge_prox(g, 6, "both", 1).first().vec) == 6
    part = sgns.started(g.nodes, 4, far.where("node < 5"), 1)
    assert part.count() == 12


def test_grid_trainer_separates_groups(spark):
    g = graph.canonical(graphs.planted(spark, 2, 12, 0.9, 0.02))
    p = walks.context_pairs(walks.uniform(g.edges, g.nodes, 8, 6), 3)
    x = {r.node: np.array(r.vec) for r in sgns.fit(p, g.nodes, 8, epochs=3, rate=0.05, blocks=4).collect()}
    cos = lambda a, b: float(x[a] @ x[b] / np.linalg.norm(x[a]) / np.linalg.norm(x[b]))
    same = np.mean([cos(a, b) for a in range(12) for b in range(a)])
    other = np.mean([cos(a, b) for a in range(12) for b in range(12, 24)])
    assert same > other


def test_learning(spark, tmp_path):
    xy = hyper.training_set(spark, graphs=6, d=4, n_walks=(5, 10, 20), lengths=(5, 10, 20)).cache()
    assert xy.count() == 54
    exact, sgd = hyper.fit_exact(xy), hyper.fit_sgd(xy)
    assert hyper.sse(xy, exact) <= hyper.sse(xy, sgd) * (1 + 1e-6)
    assert hyper.sse(xy, sgd) <= 1.5 * hyper.sse(xy, exact) + 1e-6
    stats = [dict(zip(hyper.FEATURES[2:], map(float, [n, 2 * n, 0.1, 4, 4, 9, 2, 5]))) for n in (10, 100)]
    assert hyper.choose(stats[0], exact) == hyper.choose(stats[1], exact)  # additive: the graph cannot matter
    w = np.array([1.0, -1.0, *[0.3] * 8])
    assert hyper.choose(stats[0], w, (5, 10), (5, 10)) == (10, 5) and hyper.choose(stats[0], w, (5, 10), (5, 10), "lowest") == (5, 10)
    hyper.save(spark, w, f"{tmp_path}/model")
    assert hyper.load(spark, f"{tmp_path}/model").tolist() == w.tolist()


def test_training_rows_are_made_in_parallel(spark, monkeypatch):
    rows = hyper.training_set(spark, graphs=2, d=4, n_walks=(5, 10), lengths=(5, 10))
    assert len({r[0] for r in rows.select(F.spark_partition_id()).collect()}) > 1  # each on its own, not by size
    got = {(r.graph_id, r.combo_id): r.y for r in rows.collect()}
    assert len(got) == 8 and rows.rdd.getNumPartitions() == 8
    monkeypatch.setattr(hyper, "TRAINING_TASKS", 1)
    again = hyper.training_set(spark, graphs=2, d=4, n_walks=(5, 10), lengths=(5, 10))
    assert {(r.graph_id, r.combo_id): r.y for r in again.collect()} == got


def test_walk_numbers_that_go_together_give_the_same_walks(monkeypatch):
    g = random_graph("gnp", 30, 4)
    whole = list(local.walks(g, 7, 6, 3))
    assert len(whole) == 1
    pairs = local.count_pairs(whole, 3, g.n)
    monkeypatch.setattr(local, "WALK_CELLS", 1)
    single = list(local.walks(g, 7, 6, 3))
    assert len(single) == 7 and (np.vstack(single) == whole[0]).all()
    monkeypatch.setattr(local, "DENSE", 0)
    assert all((a == b).all() for a, b in zip(local.count_pairs(single, 3, g.n), pairs))


def test_the_summary_counts_the_pairs_of_words_once(spark, monkeypatch):
    from sketchinit.catalog import graphs as queries

    seen, pairs = [], graphs.word_pairs
    monkeypatch.setattr(graphs, "word_pairs", lambda *a: seen.append(a) or pairs(*a))
    rows = {r.dataset: r for r in queries.QUERIES["dataset_summary"](spark, "/root/testdata/sf0.001").collect()}
    assert len(seen) == 1 and set(rows) == set(graphs.BUILDERS)
    e = graphs.wordadj(spark, "/root/testdata/sf0.001")
    assert rows["wordadj"].edges == e.count() and rows["wordadj"].labels > 0


def test_the_starts_of_the_multi_label_table_share_their_walks(spark, monkeypatch):
    from sketchinit.catalog import experiments

    seen, pairs = [], target.walk_pairs
    monkeypatch.setattr(target, "walk_pairs", lambda gr, *a, **k: ("w" in gr.edges.columns or seen.append(a)) and None or pairs(gr, *a, **k))
    rows = experiments.QUERIES["multi_label_table"](spark, "/root/testdata/sf0.001").collect()
    assert len(seen) == 1 and len(rows) == 4


def test_coarsening(spark):
    star = make(spark, [(0, i) for i in range(1, 5)])
    assert sorted(map(tuple, coarsen.stars(star.edges).collect())) == [(1, 1), (2, 1), (3, 3), (4, 3)]
    g = graph.canonical(graphs.planted(spark, 3, 15, 0.5, 0.05))
    levels = coarsen.hierarchy(g, 10)
    sizes = [x.nodes.count() for x, _ in levels]
    assert sizes == sorted(sizes, reverse=True) and len(sizes) > 1


@pytest.mark.parametrize("kind", ["gnp", "planted", "pref_attach"])
def test_random_graphs(kind):
    g = random_graph(kind, 30, 3)
    assert len(g.src) > 10 and (g.src != g.dst).all() and diameter(g) >= 2


def test_sketch_start_beats_random_on_planted_groups(spark):
    e = graphs.planted(spark, 5, 16, 0.6, 0.02)
    s = linkpred.split(e)
    g = Graph(s.nodes, s.train)
    score = {}
    for name, start in (("sketch", init.sketch(g, 8, k=5, max_iter=4, how=(10, 10)).emb), ("random", init.random(g, 8).emb)):
        score[name] = linkpred.precision_global(linkpred.scored(s.pos, s.neg, start)).first()["precision"]
    assert score["sketch"] > score["random"] + 0.1
    assert init.hierarchical(g, 8, min_nodes=20, r=2, length=5, window=2).emb.count() == g.nodes.count()


def test_sources(spark, tmp_path):
    f = tmp_path / "e.txt"
    f.write_text("# head\n1 2\n2\t3 # note\nbad\na b\n3.5 7\n% more\n  4 5 9\n-1 2\n99999999999999999999 1\n")
    want = [(-1, 2), (1, 2), (2, 3), (4, 5)]
    assert sorted(map(tuple, tables.edges_text(spark, str(f)).collect())) == want
    spark.dataSource.register(tables.EdgeListSource)
    assert sorted(map(tuple, spark.read.format("edges").load(str(f)).collect())) == want
    c = tmp_path / "e.csv"
    c.write_text("1,2\n2,3\n4,5\n")
    assert sorted(map(tuple, tables.edges_csv(spark, str(c)).collect())) == want[1:]
    emb = spark.createDataFrame([(1, [0.5, 1.0])], "node long, vec array<double>")
    for kind in ("parquet", "text", "csv"):
        tables.write_embeddings(emb, str(tmp_path / kind), kind)
    assert spark.read.text(str(tmp_path / "text")).first()[0] == "1 0.5 1.0"


def test_empty_graph(spark):
    g = make(spark, [])
    assert g.nodes.count() == 0 and graph.degrees(g.edges).count() == 0
    assert abstract.abstract_edges(g.edges, spark.createDataFrame([], "node long, part int")).count() == 0


def test_whole_texts_are_read(spark, tmp_path):
    from sketchinit.catalog.graphs import QUERIES
    from sketchinit.sources.graphs import MIN_COUNT

    far = " ".join(f"{a}{b}x" for a in "abcdef" for b in "ghijkl")
    texts = [(i, " ".join(f"{c}{'abcdefghij'[n % 10]}{'klmnopqrst'[n // 10 % 10]}{'uvwxyzabcd'[n // 100]}" for n in range(500)) + " " + " ".join([far] * MIN_COUNT), lang) for i, c, lang in ((1, "y", "en"), (2, "z", "de"))]
    spark.createDataFrame(texts, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    assert {tuple(r) for r in QUERIES["graph_docshare"](spark, str(tmp_path)).collect()} == {(1, 2)}
    assert QUERIES["graph_wordadj"](spark, str(tmp_path)).count() == 36  # 35 pairs, and the last word beside the first


def test_grid_tries_every_combination(spark, monkeypatch):
    from types import SimpleNamespace

    from sketchinit.operators import hyper, init

    tried = []
    monkeypatch.setattr(init, "embed_abstract", lambda ag, a, b, d, seed: tried.append((a, b)) or SimpleNamespace(withColumnRenamed=lambda *x: (a, b)))
    monkeypatch.setattr(init, "reconstruction", lambda edges, emb, theta: float(abs(emb[0] - 20) + abs(emb[1] - 40)))
    ag = SimpleNamespace(edges=None)
    assert init.pick(ag, "grid", None, "highest", 4, 1) == (20, 40)  # the least loss
    assert set(tried) == {(a, b) for a in hyper.WALKS for b in hyper.LENGTHS}


@pytest.mark.parametrize("seed", [1, 2, 3, 4, 5])
def test_negatives_match_every_degree(spark, seed):
    e = graphs.planted(spark, 4, 15, 0.5, 0.03)
    s = linkpred.split(e, seed=seed)
    assert not s.unmatched and s.neg.join(e, ["src", "dst"], "left_semi").count() == 0 and s.neg.distinct().count() == s.pos.count()
    assert linkpred.negative_degrees(s.pos, s.neg).where("positives <> negatives").count() == 0


def test_negatives_that_cannot_be_are_counted(spark):
    full = spark.createDataFrame(list(itertools.combinations(range(6), 2)), "src long, dst long")
    neg, left = linkpred.matched_negatives(full, full.where("src = 0"))
    assert neg.count() == 0 and left == 10


def test_bulk_draws_are_those_of_numpy(spark):
    from sketchinit.functions.rng import draw, draw_np

    got = [r[0] for r in spark.range(-3, 200).select(draw("slot", 7, F.col("id"), F.lit(3))).collect()]
    assert got == draw_np("slot", 7, np.arange(-3, 200), 3).tolist()


@pytest.mark.parametrize("biased", [None, (0.25, 4.0)])
def test_walks_by_joins_are_those_of_one_task(spark, biased):
    g = graph.canonical(graphs.planted(spark, 3, 12, 0.4, 0.05), spark.createDataFrame([(99,)], "node long"))
    pairs = [{tuple(r) for r in target.walk_pairs(g, 2, 6, 2, 5, biased, local).collect()} for local in (True, False)]
    assert pairs[0] == pairs[1] and pairs[0]


def test_weighted_walks_by_joins_are_those_of_one_task(spark, fig):
    g, parts = fig
    ag = abstract.build(g, parts)
    a = Graph(ag.nodes.select(F.col("part").cast("long").alias("node")), ag.edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w"))
    pairs = [{tuple(r) for r in target.walk_pairs(a, 6, 5, 2, 1, None, local).collect()} for local in (True, False)]
    assert pairs[0] == pairs[1]


def test_second_order_walks_follow_their_distribution(spark):
    g = make(spark, [(0, 1), (1, 2), (1, 3), (0, 2)])
    w = walks.biased(g.edges, spark.createDataFrame([(0,)], "node long"), 3000, 3, 0.1, 5.0, tries=1).collect()
    from_one = [r.path[2] for r in w if r.path[1] == 1]
    want = {0: 10 / 11.2, 2: 1 / 11.2, 3: 0.2 / 11.2}
    for v, p in want.items():
        assert abs(from_one.count(v) / len(from_one) - p) < 4 * (p * (1 - p) / len(from_one)) ** 0.5


def test_hub_blocks_give_the_same_odds(spark, fig):
    g, parts = fig
    e = abstract.build(g, parts).edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w")
    outer, inner = walks.alias_blocks(walks.transitions(e), 1)
    w = walks.weighted_blocked(outer, inner, spark.createDataFrame([(1,)], "node long"), 900, 2)
    assert abs(w.where(F.element_at("path", 2) == 0).count() / 900 - 2 / 3) < 4 * (2 / 9 / 900) ** 0.5


def test_propagation_by_blocks_is_that_of_one_task(spark):
    g = graph.canonical(graphs.planted(spark, 3, 12, 0.4, 0.05), spark.createDataFrame([(99,)], "node long"))
    parts = partition.hashed(g.nodes, 4)
    f_a = spark.createDataFrame([(p, [float(p), 1.0, -p / 2]) for p in range(4)], "part int, vec array<double>")
    (one, a), (many, b) = (propagate.run(g, parts, f_a, max_iter=9, blocks=k) for k in (0, 3))
    assert [t["delta"] for t in a] == pytest.approx([t["delta"] for t in b])
    x, y = ({r.node: r.vec for r in e.collect()} for e in (one, many))
    assert x.keys() == y.keys() and all(x[v] == pytest.approx(y[v]) for v in x)
    _, trace = propagate.run(g, parts, f_a)
    assert trace[-1]["converged"] and trace[-1]["delta"] <= 1 / 37


def test_every_block_count_trains_both_kinds_of_tables(spark):
    g = graph.canonical(graphs.planted(spark, 2, 12, 0.9, 0.02))
    for tie in (False, True):
        for blocks in (1, 4):
            x = {r.node: np.array(r.vec) for r in sgns.fit(target.edge_samples(g.edges, 40), g.nodes, 8, epochs=2, rate=0.1, tie=tie, blocks=blocks).collect()}
            middle = np.mean(list(x.values()), axis=0)  # negatives give all vectors one common part
            x = {k: v - middle for k, v in x.items()}
            cos = lambda a, b: float(x[a] @ x[b] / np.linalg.norm(x[a]) / np.linalg.norm(x[b]))
            same, other = ([cos(a, b) for a in range(12) for b in range(*r) if a != b] for r in ((0, 12), (12, 24)))
            assert len(x) == 24 and np.mean(same) > np.mean(other) + 0.1, (tie, blocks)


def test_parts_without_a_task_for_the_coarse_graph(spark):
    g = graph.canonical(graphs.planted(spark, 6, 20, 0.5, 0.01), spark.range(500, 520).withColumnRenamed("id", "node"))
    p = partition.multilevel(g, 6, coarse_nodes=1, coarse_edges=1)
    r = partition.balance(p, 6).first()
    assert r.ok and r.parts == 6 and r.nodes == 140
    assert partition.edge_cut(g.edges, p).count() < partition.edge_cut(g.edges, partition.hashed(g.nodes, 6)).count()


def test_warm_start_of_new_nodes(spark):
    from sketchinit.streaming.edges import warm_start

    emb = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 4.0])], "node long, vec array<double>")
    new = spark.createDataFrame([(1, 5), (2, 5), (5, 6)], "src long, dst long")
    assert [(r.node, r.vec) for r in warm_start(emb, new).collect()] == [(5, [0.5, 2.0])]


def test_products_let_the_graph_matter():
    stats = [dict(zip(hyper.FEATURES[2:], map(float, [n, 2 * n, 0.1, 4, 4, 9, 2, 5]))) for n in (10, 1000)]
    w = np.zeros(26)
    w[0], w[10] = 1.0, -0.01  # walks are good, but not times many nodes
    assert hyper.choose(stats[0], w) != hyper.choose(stats[1], w)
    assert len(hyper.default_model()) == 10 and len(hyper.default_model(True)) == 26


def test_probabilities_of_two_level_alias_round_like_the_quotient(spark):
    """Weights of 128 in all: every odd one is a tie at the seventh digit."""
    from sketchinit.catalog.graphs import _rebuilt

    rows = []
    for node in range(200, 260):
        rng, w = np.random.default_rng(node), np.ones(30, int)
        np.add.at(w, rng.integers(0, 30, 98), 1)
        rows += [(i, node, int(x)) for i, x in enumerate(w)]
    trans = walks.transitions(spark.createDataFrame(rows, "src long, dst long, w long")).where("src >= 200")
    got = {(r.src, r.dst): r.prob for r in _rebuilt(*walks.alias_blocks(trans, 8)).collect()}
    want = {(n, i): (w * 10**6 * 2 + 128) // 256 / 10**6 for i, n, w in rows}
    assert got == pytest.approx(want, abs=1e-9)


def _halved(spark, folder, names):
    """Tables of which every second row is left, or, for hyper_grid, the two highest priorities."""
    for t in names:
        df = spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet")
        df.where(F.col("o_orderpriority") < "3" if t == "orders" else F.col("c_custkey") % 2 == 0).write.parquet(f"{folder}/{t}.parquet")


def test_gain_table_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('orders', 'customer'))
    whole, half = (registry.queries()["gain_table"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_result_rollup_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('orders', 'customer'))
    whole, half = (registry.queries()["result_rollup"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_result_cube_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('orders', 'customer'))
    whole, half = (registry.queries()["result_cube"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_hyper_grid_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('orders',))
    whole, half = (registry.queries()["hyper_grid"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_random_graph_gnp_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('orders',))
    whole, half = (registry.queries()["random_graph_gnp"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_graph_planted_reads_its_table(spark, tmp_path):
    from sketchinit.catalog import registry

    _halved(spark, tmp_path, ('customer',))
    whole, half = (registry.queries()["graph_planted"](spark, d) for d in ("/root/testdata/sf0.001", str(tmp_path)))
    assert sorted(map(str, whole.collect())) != sorted(map(str, half.collect()))


def test_second_order_step_writes_no_candidates(spark, monkeypatch):
    """A draw from the whole distribution, against brute force, whatever the blocks; no row for each candidate."""
    g = graph.canonical(graphs.planted(spark, 3, 12, 0.4, 0.05))
    near = {}
    for a, b in ((r.src, r.dst) for r in graph.arcs(g.edges).collect()):
        near.setdefault(a, set()).add(b)
    rows = [(a, b, (a * 37 + b * 11) % 101 / 101) for a in near for b in sorted(near[a])] + [(None, a, 0.35) for a in near] + [(1, 777, 0.5)]
    want = {}
    for prev, cur, u in rows:
        c = sorted(near.get(cur, ()))
        w = [1.0 if prev is None else 2.0 if x == prev else 1.0 if x in near[prev] else 0.5 for x in c]
        if c:
            want[prev, cur] = next(x for x, r in zip(c, itertools.accumulate(w)) if r > u * sum(w))
    state = spark.createDataFrame(rows, "prev long, cur long, v double")
    monkeypatch.setattr(walks, "CANDIDATES", 50)
    for blocks in (1, 3):
        out = walks.second_order_step(g.edges, state, F.col("v"), 0.5, 2.0, blocks)
        assert {(r.prev, r.cur): r.cand for r in out.collect()} == want
    assert "Window" not in out._jdf.queryExecution().toString() and "FlatMapCoGroupsInArrow" in out._jdf.queryExecution().toString()


def test_sessions_end_in_files_and_none_stays_open(spark):
    """No session passes through the driver; those open at the last event are told too."""
    from sketchinit.catalog import registry

    out = registry.queries()["stream_session"](spark, "/root/testdata/sf0.001")
    events = tables.table(spark, "/root/testdata/sf0.001", "events")
    assert out.inputFiles() and out.agg(F.sum("n")).first()[0] == events.count()
    assert out.agg(F.max("end")).first()[0] > events.agg(F.max("ts")).first()[0]


def test_updates_of_rows_met_once_are_not_added_up():
    rng = np.random.default_rng(3)
    for n in (40, 90_000):
        at, each, what = rng.integers(0, n, 1500), np.ones(1500), rng.random((1500, 4)).astype(np.float32)
        at[::7] = 5  # a row that takes many
        runs = local._Runs(at, each, 512, n)
        assert (runs.lone is not None) == (n > 1500)
        got, want = np.zeros((n, 4), np.float32), np.zeros((n, 4))
        for k in range(3):
            mine = slice(512 * k, min(512 * k + 512, 1500))
            runs.add(got, what[mine], k)
            scale = np.minimum(1, 20 / np.maximum(1, np.bincount(at[mine], minlength=n)))[:, None]
            one = np.zeros((n, 4))
            np.add.at(one, at[mine], what[mine])
            want += one * scale
        assert np.allclose(got, want, atol=1e-4)


def test_training_of_many_nodes_learns_as_much(monkeypatch):
    rng = np.random.default_rng(0)
    n, groups = 3000, 60
    i = rng.integers(0, n, 30_000)
    j = np.where(rng.random(len(i)) < 0.9, i % groups + groups * rng.integers(0, n // groups, len(i)), rng.integers(0, n, len(i)))
    key = np.unique(np.minimum(i, j)[i != j] * n + np.maximum(i, j)[i != j])
    c, o, t = local.count_pairs(local.walks(Csr(n, key // n, key % n), 10, 10), 4, n)
    found = []
    for wide in (n, 100):
        monkeypatch.setattr(local, "WIDE", wide)
        x, y = (np.random.default_rng(1).random((n, 8)) - 0.5) / 8, np.zeros((n, 8))
        local.train(x, y, c, o, t, 5, (0.1, 0.005), 1)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        near = (x[c] * x[o]).sum(axis=1)
        far = (x[rng.permutation(c)] * x[o]).sum(axis=1)
        found.append(float(near.mean() - far.mean()))
    assert found[0] > 0.1 and abs(found[1] - found[0]) < 0.1 * found[0]


def test_fit_reads_stored_pairs_where_they_are(spark, monkeypatch):
    g = graph.canonical(graphs.planted(spark, 2, 12, 0.9, 0.02))
    pairs = storage.stash(target.edge_samples(g.edges, 4), "pairs")
    tags, keep = [], sgns.stash
    monkeypatch.setattr(sgns, "stash", lambda df, tag: tags.append(tag) or keep(df, tag))
    assert sgns.fit(pairs, g.nodes, 4).count() == 24 and "pairs" not in tags
    assert sgns.fit(pairs.where("n > 0"), g.nodes, 4).count() == 24 and "pairs" in tags


def test_blocks_own_pairs_are_spread_over_rounds(spark, monkeypatch):
    g = graph.canonical(graphs.planted(spark, 4, 30, 0.9, 0.5))
    paths, path = [], sgns.stash_path
    monkeypatch.setattr(sgns, "stash_path", lambda s, tag: paths.append(path(s, tag)) or paths[-1])
    pairs = target.edge_samples(g.edges, 4)
    assert sgns.fit(pairs, g.nodes, 4, blocks=4).count() == 120
    dealt = spark.read.parquet(paths[0])
    assert dealt.count() == pairs.count()
    of = F.pmod(F.xxhash64(F.lit(1), F.col("center")), F.lit(4)) == F.pmod(F.xxhash64(F.lit(1), F.col("context")), F.lit(4))
    own = dealt.where(of).groupBy(F.pmod(F.xxhash64(F.lit(1), F.col("center")), F.lit(4)).alias("b")).agg(F.count_distinct("round").alias("n")).collect()
    assert own and all(r.n == 3 for r in own)


def test_a_graph_of_many_edges_and_few_nodes_is_walked_in_one_task(spark, monkeypatch):
    nodes = spark.range(1100).withColumnRenamed("id", "node")
    e = nodes.select(F.col("node").alias("src"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(1099).cast("long"))).alias("dst")).where("src < dst")
    monkeypatch.setattr(walks, "uniform", None)  # the walks by joins
    assert target.walk_pairs(Graph(nodes, e), 1, 2, 1).agg(F.sum("n")).first()[0] == 2200


def test_the_diameter_is_exact_at_every_size(spark, monkeypatch):
    chain = spark.range(60).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).alias("w"))
    ag = abstract.AbstractGraph(spark.range(61).select(F.col("id").alias("part")), chain)
    monkeypatch.setattr(hyper, "EXACT_NODES", 3, raising=False)  # nodes beyond which a lower bound was taken before
    monkeypatch.setattr(hyper, "SOURCES", 8, raising=False)
    assert hyper.stats(ag)["diameter"] == 60
    few = abstract.AbstractGraph(ag.nodes.where("part < 6"), chain.where("dst < 6"))
    monkeypatch.setattr(hyper, "LOCAL_EDGES", 2)
    assert hyper.stats(few)["diameter"] == 5


def test_searches_side_by_side_are_those_one_by_one(monkeypatch):
    monkeypatch.setattr(local, "WORDS", 16)
    for seed in range(6):
        g = random_graph("gnp", 60 + seed, seed)
        every = diameter(g)
        assert every == max(diameter(g, np.array([v])) for v in range(g.n))
        monkeypatch.setattr(local, "SEARCHES", 7)
        assert diameter(g) == every


def test_the_summary_writes_no_edges_but_those_of_words(spark, monkeypatch):
    from sketchinit.catalog import base, graphs as queries

    tags, keep = [], storage.stash
    for m in (base, queries):
        monkeypatch.setattr(m, "stash", lambda df, tag: tags.append(tag) or keep(df, tag))
    rows = {r.dataset: r for r in queries.QUERIES["dataset_summary"](spark, "/root/testdata/sf0.001").collect()}
    assert tags.count("edges") == 1
    for k in ("coactive", "trade", "docshare"):
        e = graphs.BUILDERS[k](spark, "/root/testdata/sf0.001")
        assert (rows[k].edges, rows[k].nodes) == (e.count(), e.select(F.explode(F.array("src", "dst"))).distinct().count())
    assert tuple(graph.summary(graph.degrees(graphs.trade(spark, "/root/testdata/sf0.001").limit(0))).first()) == (0, 0)


def test_degrees_within_are_those_of_the_pairs(spark):
    rows = spark.createDataFrame([(k, (k * k + 7 * i) % 23) for k in range(9) for i in range(5)], "key long, member long")
    for blocks in (1, 3):
        got = {r.node: r.degree for r in pairs.degrees_within(rows, 45, 23, blocks).collect()}
        assert got == {r.node: r.degree for r in graph.degrees(pairs.pairs_within(rows, 45, 23, blocks)).collect()}


def test_both_readings_of_the_model_are_made_side_by_side(spark, monkeypatch):
    import threading

    from sketchinit.catalog import learned

    both, sketch = threading.Barrier(2, timeout=60), init.sketch
    monkeypatch.setattr(hyper, "training_set", lambda s, graphs: s.createDataFrame([(0, 0, 5.0, 5.0, *[float(i)] * 8, 1.0) for i in range(1, 4)], hyper.HYBRID))
    monkeypatch.setattr(init, "sketch", lambda *a, **k: both.wait() >= 0 and sketch(*a, **k))
    rows = learned.QUERIES["sketch_init_learned"](spark, "/root/testdata/sf0.001").collect()
    assert [r.reading for r in rows] == ["highest", "lowest"] and rows[0].nodes == rows[1].nodes > 0


def test_a_graph_of_over_two_million_edges_propagates_in_one_task(spark, monkeypatch):
    nodes = spark.range(2100).select(F.col("id").alias("node"))
    e = nodes.select(F.col("node").alias("src"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(2099).cast("long"))).alias("dst")).where("src < dst")
    monkeypatch.setattr(propagate, "_Blocks", None)
    f_a = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0])], "part int, vec array<double>")
    emb, trace = propagate.run(Graph(nodes, storage.stash(e, "edges")), partition.hashed(nodes, 2), f_a, 0.0, 1)
    assert emb.count() == 2100 and len(trace) == 1


def test_strips_of_neighbours_give_the_sums_of_all(monkeypatch):
    monkeypatch.setattr(local, "STRIP", 3)
    for seed, chunk in itertools.product(range(4), (1, 40, 1 << 17)):
        g = random_graph("pref_attach", 80, seed)
        g = Csr(84, np.append(g.src, np.full(60, 80)), np.append(g.dst, np.arange(60)))  # a hub, and nodes without neighbours
        x = np.random.default_rng(seed).random((84, 3))
        a = np.zeros((84, 84))
        a[g.src, g.dst] = a[g.dst, g.src] = 1
        deg = a.sum(axis=1, keepdims=True)
        want = np.where(deg > 0, 0.5 * x + 0.5 * (a @ x) / np.maximum(deg, 1), x)
        got, trace = local.propagate(g, x, 0.0, 1, chunk)
        assert np.allclose(got, want, rtol=1e-12) and trace[0][0] == pytest.approx(np.sqrt(((want - x) ** 2).sum(axis=1)).mean())
