"""Queries on vectors, measures and protocols."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.rng import u01_sql, u32_sql
from ..functions.vec import cosine, euclid
from ..operators import classify, linkpred, metrics, sgns
from ..operators.components import connected, largest
from ..plans.storage import stash
from ..sources import graphs as g
from ..sources.tables import table
from .base import D, edges, nodes, stand_in, with_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def keep(f):  # noqa: ANN001, ANN202
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _vec_pairs(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings")
    return e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("o")), "vec_id")


_PAIRS = "FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


@query("vec_cosine", f"SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine {_PAIRS}")
def _cos(spark: SparkSession, sf: str) -> DataFrame:
    return _vec_pairs(spark, sf).select("vec_id", F.round(cosine(F.col("embedding"), F.col("o")), 6).alias("cosine"))


@query("vec_euclid", f"SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS euclid {_PAIRS}")
def _euc(spark: SparkSession, sf: str) -> DataFrame:
    return _vec_pairs(spark, sf).select("vec_id", F.round(euclid(F.col("embedding"), F.col("o")), 6).alias("euclid"))


@query("nearest_vectors", "SELECT query, node, CAST(rank AS INTEGER) AS rank, value FROM (SELECT a.vec_id AS query, b.vec_id AS node, round(list_cosine_similarity(b.embedding::DOUBLE[], a.embedding::DOUBLE[]), 6) AS value, row_number() OVER (PARTITION BY a.vec_id ORDER BY -round(list_cosine_similarity(b.embedding::DOUBLE[], a.embedding::DOUBLE[]), 6), b.vec_id) AS rank FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0) WHERE rank <= 5")
def _near(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("node"), F.col("embedding").alias("vec"))
    return metrics.nearest(e, e.where("node % 50 = 0"), 5)


def _vectors(e: DataFrame) -> DataFrame:
    return nodes(e).select("node", stand_in("vec", F.col("node")).alias("vec"))


_VEC = f"v AS (SELECT node, [{', '.join(u01_sql('vec', 1, 'node', str(i)) for i in range(D))}] AS vec FROM n)"
_ALL = "(SELECT COALESCE(t.a, 0) - s.theta AS d FROM s LEFT JOIN t ON t.x = s.x AND t.y = s.y)"


@query("reconstruction_loss", with_sql("geo", _VEC, "s AS (SELECT p.node AS x, q.node AS y, list_dot_product(p.vec, q.vec) AS theta FROM v p, v q)", "t AS (SELECT src AS x, dst AS y, 1.0 AS a FROM a)") + f"SELECT round(sum(d * d), 3) AS loss FROM {_ALL}")
def _loss(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "geo")
    return spark.createDataFrame([(round(metrics.reconstruction(e, _vectors(e), "dot"), 3),)], "loss double")


@query("weighted_reconstruction", with_sql("geo", _VEC, "s AS (SELECT p.node AS x, q.node AS y, list_distance(p.vec, q.vec) AS theta FROM v p, v q)", "t AS (SELECT src AS x, dst AS y, (src + dst) % 5 + 1.0 AS a FROM a)") + f"SELECT round(sum(d * d), 3) AS loss FROM {_ALL}")
def _weighted(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "geo").withColumn("w", (F.col("src") + F.col("dst")) % 5 + 1)
    return spark.createDataFrame([(round(metrics.reconstruction(e, _vectors(e), "euclid_distance"), 3),)], "loss double")


_HOLD = f"hs AS (SELECT src, dst FROM e ORDER BY {u32_sql('hold', 1, 'src', 'dst')}, src, dst LIMIT (SELECT CAST(ceil(0.1 * count(*)) AS BIGINT) FROM e)), er AS (SELECT * FROM e EXCEPT SELECT * FROM hs)"


@query("holdout_split", with_sql("trade", _HOLD) + "SELECT src, dst FROM hs")
def _holdout(spark: SparkSession, sf: str) -> DataFrame:
    return linkpred.holdout(edges(spark, sf))[0]


_REACH = "ra AS (SELECT src, dst FROM er UNION ALL SELECT dst, src FROM er), rr AS (SELECT DISTINCT src AS node, src AS root FROM ra UNION SELECT ra.dst, rr.root FROM rr JOIN ra ON ra.src = rr.node), lb AS (SELECT node, min(root) AS root FROM rr GROUP BY 1), bg AS (SELECT node FROM lb WHERE root = (SELECT root FROM lb GROUP BY root ORDER BY count(*) DESC, root LIMIT 1))"


@query("components", with_sql("pagenav", "er AS (SELECT * FROM e)", _REACH) + "SELECT node, root FROM lb")
def _components(spark: SparkSession, sf: str) -> DataFrame:
    return connected(edges(spark, sf, "pagenav"))


@query("largest_component", with_sql("pagenav", _HOLD, _REACH) + "SELECT node FROM bg")
def _largest(spark: SparkSession, sf: str) -> DataFrame:
    return largest(connected(linkpred.holdout(edges(spark, sf, "pagenav"))[1]))


def _inside_sql(rows: str) -> str:
    return f"SELECT src, dst FROM {rows} WHERE src IN (SELECT node FROM bg) AND dst IN (SELECT node FROM bg)"


@query("train_edges", with_sql("pagenav", _HOLD, _REACH) + _inside_sql("er"))
def _train(spark: SparkSession, sf: str) -> DataFrame:
    held, rest = linkpred.holdout(edges(spark, sf, "pagenav"))
    return linkpred.inside(rest, stash(largest(connected(rest)), "lcc"))


@query("positives", with_sql("pagenav", _HOLD, _REACH) + _inside_sql("hs"))
def _positives(spark: SparkSession, sf: str) -> DataFrame:
    held, rest = linkpred.holdout(edges(spark, sf, "pagenav"))
    return linkpred.inside(held, stash(largest(connected(rest)), "lcc"))


_DRAWS = f"dr AS (SELECT i AS id, {u32_sql('neg_a', 1, 'i')} % (SELECT count(*) FROM n) AS a, {u32_sql('neg_b', 1, 'i')} % (SELECT count(*) FROM n) AS b FROM range((SELECT CAST(floor(500 * 1.5 * (1 + (SELECT count(*) FROM e) / GREATEST(1, (SELECT count(*) FROM n) * ((SELECT count(*) FROM n) - 1) / 2))) AS BIGINT) + 20)) t(i)), rk AS (SELECT node, row_number() OVER (ORDER BY node) - 1 AS r FROM n), ps AS (SELECT LEAST(a, b) AS a, GREATEST(a, b) AS b, min(id) AS id FROM dr WHERE a <> b GROUP BY 1, 2), nm AS (SELECT LEAST(x.node, y.node) AS src, GREATEST(x.node, y.node) AS dst, id FROM ps JOIN rk x ON x.r = ps.a JOIN rk y ON y.r = ps.b)"


@query("negatives_uniform", with_sql("trade", _DRAWS) + "SELECT src, dst FROM nm WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.src = nm.src AND e.dst = nm.dst) ORDER BY id LIMIT 500")
def _uniform(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return linkpred.uniform_negatives(e, nodes(e), 500)


@query("negatives_matched")
def _matched(spark: SparkSession, sf: str) -> DataFrame:
    s = linkpred.split(edges(spark, sf, "wordadj"))
    return s.pos.withColumn("y", F.lit(1)).unionAll(s.neg.withColumn("y", F.lit(0)))


_ONE = "ra AS (SELECT src, dst FROM er UNION ALL SELECT dst, src FROM er), bg AS (SELECT min(src) AS node FROM ra UNION SELECT ra.dst FROM bg JOIN ra ON ra.src = bg.node)"  # the component of the smallest node, where it is the largest


@query("negatives_degrees", with_sql("copurchase", _HOLD, _ONE, f"ps AS ({_inside_sql('hs')})") + "SELECT node, CAST(count(*) AS BIGINT) AS positives, CAST(count(*) AS BIGINT) AS negatives FROM (SELECT src AS node FROM ps UNION ALL SELECT dst FROM ps) GROUP BY 1")
def _matched_degrees(spark: SparkSession, sf: str) -> DataFrame:
    """Every node has as many negatives as positives."""
    s = linkpred.split(edges(spark, sf, "copurchase"))
    return linkpred.negative_degrees(s.pos, s.neg)


_TEST = f"ts AS (SELECT e.src, e.dst, CAST({u32_sql('y', 1, 'src', 'dst')} % 2 AS INTEGER) AS y FROM e), sc AS (SELECT ts.*, round(SIM, 9) AS s FROM ts JOIN v p ON p.node = ts.src JOIN v q ON q.node = ts.dst)"


def _test_rows(spark: SparkSession, sf: str, sim: str) -> DataFrame:
    """A deterministic test set: the trade edges, half of them called positive by hash, under given vectors."""
    from ..functions.rng import u32

    e = edges(spark, sf)
    y = (u32("y", 1, F.col("src"), F.col("dst")) % 2).cast("int")
    pos, neg = (e.where(y == k) for k in (1, 0))
    return stash(linkpred.scored(pos, neg, _vectors(e), sim), "scored")


_SIMS = {"cosine": "list_cosine_similarity(p.vec, q.vec)", "euclid": "-list_distance(p.vec, q.vec)"}
for _name, _sim in (("cos", "cosine"), ("euc", "euclid")):
    query(f"precision_global_{_name}", with_sql("trade", _VEC, _TEST.replace("SIM", _SIMS[_sim])) + "SELECT CAST((SELECT sum(y) FROM sc) AS BIGINT) AS positives, CAST(sum(y) AS BIGINT) AS hits, round(sum(y) / (SELECT sum(y) FROM sc), 6) AS precision FROM (SELECT y, row_number() OVER (ORDER BY s DESC, src, dst) AS r FROM sc) WHERE r <= (SELECT sum(y) FROM sc)")(lambda spark, sf, sim=_sim: linkpred.precision_global(_test_rows(spark, sf, sim)))


@query("precision_per_node", with_sql("trade", _VEC, _TEST.replace("SIM", _SIMS["cosine"]), "bo AS (SELECT src, dst, y, s FROM sc UNION ALL SELECT dst, src, y, s FROM sc)") + "SELECT count(*) AS predicted, CAST(sum(y) AS BIGINT) AS hits, round(sum(y) / count(*), 6) AS precision FROM (SELECT y, row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) AS r, sum(y) OVER (PARTITION BY src) AS t FROM bo) WHERE r <= t")
def _per_node(spark: SparkSession, sf: str) -> DataFrame:
    return linkpred.precision_per_node(_test_rows(spark, sf, "cosine"))


@query("ranking_auc", with_sql("trade", _VEC, _TEST.replace("SIM", _SIMS["cosine"])) + "SELECT round(sum(CASE WHEN y = 1 THEN r END - 0) / ((SELECT sum(y) FROM sc) * (SELECT sum(1 - y) FROM sc)) - ((SELECT sum(y) FROM sc) + 1) / 2.0 / (SELECT sum(1 - y) FROM sc), 6) AS auc FROM (SELECT y, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2.0 AS r FROM sc)")
def _auc(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(round(linkpred.auc(_test_rows(spark, sf, "cosine")), 6),)], "auc double")


_SPLIT = f"lab AS ({g.LABEL_SQL}), hh AS (SELECT node, label, {u32_sql('node_split', 1, 'node')} AS h FROM lab), sp AS (SELECT node, label, CASE WHEN row_number() OVER (PARTITION BY h % 16 ORDER BY h, node) <= floor(count(*) OVER (PARTITION BY h % 16) * 0.5 + 0.5) THEN 'train' ELSE 'test' END AS role FROM hh)"


@query("word_labels", g.LABEL_SQL)
def _word_labels(spark: SparkSession, sf: str) -> DataFrame:
    return g.word_labels(spark, sf)


@query("node_split", f"WITH {_SPLIT} SELECT node, label, role FROM sp")
def _node_split(spark: SparkSession, sf: str) -> DataFrame:
    return classify.node_split(stash(g.word_labels(spark, sf), "labels")).select("node", "label", "role")


_F1 = "pd AS (SELECT node, arg_min(label, (-c, label)) AS label FROM (SELECT a.src AS node, lab.label, count(*) AS c FROM a JOIN lab ON lab.node = a.dst GROUP BY 1, 2) GROUP BY 1), tt AS (SELECT lab.node, lab.label FROM lab JOIN n ON n.node = lab.node), cf AS (SELECT COALESCE(pd.label, tt.label) AS label, CASE WHEN pd.node IS NULL THEN 0 ELSE 1 END AS p, CASE WHEN tt.node IS NULL THEN 0 ELSE 1 END AS t FROM pd FULL JOIN tt ON pd.node = tt.node AND pd.label = tt.label), bl AS (SELECT label, sum(p * t) AS tp, sum(p) AS np, sum(t) AS nt FROM cf GROUP BY 1)"


@query("f1_micro_macro", with_sql("wordadj", f"lab AS ({g.LABEL_SQL})", _F1) + "SELECT round(2 * sum(tp) / (sum(np) + sum(nt)), 6) AS micro, round(avg(2 * tp / (np + nt)), 6) AS macro FROM bl")
def _f1(spark: SparkSession, sf: str) -> DataFrame:
    e, labels = edges(spark, sf, "wordadj"), stash(g.word_labels(spark, sf), "labels")
    truth = labels.join(nodes(e), "node", "left_semi")
    return classify.f1(classify.majority_neighbor(e, labels), truth)


@query("random_init", with_sql("trade") + f"SELECT node, j AS dim, round(({u01_sql('init', 1, 'node', 'j')} - 0.5) / 8, 6) AS val FROM n, range(8) t(j)")
def _random(spark: SparkSession, sf: str) -> DataFrame:
    v = sgns.random_vectors(nodes(edges(spark, sf)), 8)
    return v.select("node", F.posexplode("vec").alias("dim", "x")).select("node", F.col("dim").cast("long").alias("dim"), F.round("x", 6).alias("val"))


@query("common_neighbors", with_sql("trade", "dg AS (SELECT src AS node, count(*) AS d FROM a GROUP BY 1)", "pr AS (SELECT src, dst FROM a WHERE false UNION SELECT src, src + 2 FROM a WHERE src + 2 IN (SELECT node FROM n))", "cn AS (SELECT pr.src, pr.dst, count(*) AS c FROM pr JOIN a x ON x.src = pr.src JOIN a y ON y.src = pr.dst AND y.dst = x.dst GROUP BY 1, 2)") + "SELECT pr.src, pr.dst, COALESCE(c, 0) AS common, round(COALESCE(c, 0) / (p.d + q.d - COALESCE(c, 0)), 6) AS jaccard FROM pr LEFT JOIN cn ON cn.src = pr.src AND cn.dst = pr.dst JOIN dg p ON p.node = pr.src JOIN dg q ON q.node = pr.dst")
def _common(spark: SparkSession, sf: str) -> DataFrame:
    from ..operators.graph import common_neighbors

    e = edges(spark, sf)
    n = nodes(e)
    pairs = n.select(F.col("node").alias("src"), (F.col("node") + 2).alias("dst")).join(n.withColumnRenamed("node", "dst"), "dst", "left_semi")
    return common_neighbors(e, pairs.select("src", "dst")).withColumn("jaccard", F.round("jaccard", 6))


def _prices(spark: SparkSession, sf: str) -> DataFrame:
    """(priority, segment, status, price) of the orders."""
    o = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return o.select(F.col("o_orderpriority").alias("priority"), F.col("c_mktsegment").alias("segment"), F.col("o_orderstatus").alias("status"), F.col("o_totalprice").alias("price"))


_PRICES = "(SELECT o_orderpriority AS priority, c_mktsegment AS segment, o_orderstatus AS status, o_totalprice AS price FROM orders JOIN customer ON c_custkey = o_custkey)"


@query("gain_table", f"WITH r AS (SELECT priority, segment, status, avg(price) AS value FROM {_PRICES} GROUP BY 1, 2, 3) SELECT s.priority, s.segment, o.status AS versus, round((s.value - o.value) / o.value, 6) AS gain FROM r s JOIN r o ON o.priority = s.priority AND o.segment = s.segment WHERE s.status = 'F' AND o.status <> 'F'")
def _gains(spark: SparkSession, sf: str) -> DataFrame:
    """What finished orders bring on average over those of each other status, by priority and segment."""
    r = stash(_prices(spark, sf).groupBy("priority", "segment", "status").agg(F.avg("price").alias("value")), "means")
    s = r.where("status = 'F'").select("priority", "segment", F.col("value").alias("a"))
    return s.join(r.where("status <> 'F'"), ["priority", "segment"]).select("priority", "segment", F.col("status").alias("versus"), F.round((F.col("a") - F.col("value")) / F.col("value"), 6).alias("gain"))


@query("result_rollup", f"SELECT priority, status, round(avg(price), 2) AS mean, count(*) AS n FROM {_PRICES} GROUP BY ROLLUP (priority, status)")
def _rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _prices(spark, sf).rollup("priority", "status").agg(F.round(F.avg("price"), 2).alias("mean"), F.count("*").alias("n"))


@query("result_cube", f"SELECT status, segment, round(avg(price), 2) AS mean, count(*) AS n FROM {_PRICES} GROUP BY CUBE (status, segment)")
def _cube(spark: SparkSession, sf: str) -> DataFrame:
    return _prices(spark, sf).cube("status", "segment").agg(F.round(F.avg("price"), 2).alias("mean"), F.count("*").alias("n"))
