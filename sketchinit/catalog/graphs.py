"""Queries on graphs, partitions, the abstract graph, walks and propagation."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.rng import u01, u01_sql, u32, u32_sql
from ..operators import abstract, coarsen, graph, partition, propagate, target, walks
from ..operators.graph import Graph
from ..plans.storage import drop_stash, release, stash
from ..sources import graphs as g
from ..streaming.edges import warm_start
from .base import ABSTRACT, ABSTRACT_ARCS, CROSS, F_A, INHERIT, K, PARTS, STEPS, edges, long_rows, long_sql, nodes, parts, stand_in_f_a, with_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def keep(f):  # noqa: ANN001, ANN202
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


for _key in g.BUILDERS:
    query(f"graph_{_key}", g.SQL[_key])(lambda spark, sf, key=_key: g.BUILDERS[key](spark, sf))


@query("degrees", with_sql("trade") + "SELECT src AS node, count(*) AS degree FROM a GROUP BY 1")
def _degrees(spark: SparkSession, sf: str) -> DataFrame:
    return graph.degrees(edges(spark, sf))


@query("degree_histogram", with_sql("wordadj") + "SELECT degree, count(*) AS nodes FROM (SELECT src, count(*) AS degree FROM a GROUP BY 1) GROUP BY 1")
def _histogram(spark: SparkSession, sf: str) -> DataFrame:
    return graph.degree_histogram(edges(spark, sf, "wordadj"))


_LABELS = {"docshare": "SELECT count(DISTINCT lang) FROM documents", "wordadj": f"SELECT count(DISTINCT label) FROM ({g.LABEL_SQL}) lb SEMI JOIN (SELECT src AS node FROM ({g.SQL['wordadj']}) UNION ALL SELECT dst FROM ({g.SQL['wordadj']})) nn USING (node)", "vecknn": "SELECT count(DISTINCT label) FROM embeddings"}


SIDE_BY_SIDE = 4  # graphs that are built at once: cores idle in the end of each, yet disk holds no more than so many
_HEAVY = ["docshare", "wordadj", "coactive", "trade", "custpart", "vecknn", "copurchase", "pagenav", "geo"]  # the longest first


@query("dataset_summary", " UNION ALL ".join(f"SELECT '{k}' AS dataset, (SELECT count(DISTINCT v) FROM (SELECT src AS v FROM q UNION ALL SELECT dst FROM q)) AS nodes, (SELECT count(*) FROM q) AS edges, ({_LABELS.get(k, 'SELECT 0')})::BIGINT AS labels".replace("FROM q", f"FROM ({g.SQL[k]})") for k in g.BUILDERS))
def _summary(spark: SparkSession, sf: str) -> DataFrame:
    """Size and labels of every stand-in graph. The graphs are built side by side, and their edges are counted where they are made; the texts' pairs of words
    are counted once for edges and labels."""

    def one(k: str) -> DataFrame:
        if k == "wordadj":
            p = stash(g.word_pairs(spark, sf, "lang"), "words")
            e = stash(g.often(p.groupBy("a", "b").agg(F.sum("n").alias("n"))), "edges")
            degree = graph.degrees(e)
            labels = g.labels_of(p).join(nodes(e), "node", "left_semi").agg(F.count_distinct("label").alias("labels"))
        else:
            degree = g.DEGREES[k](spark, sf) if k in g.DEGREES else graph.degrees(g.BUILDERS[k](spark, sf))  # no edge is written
            if k in _LABELS:
                name, col = ("documents", "lang") if k == "docshare" else ("embeddings", "label")
                labels = g.table(spark, sf, name).agg(F.count_distinct(col).alias("labels"))
            else:
                labels = spark.range(1).select(F.lit(0).cast("long").alias("labels"))
        row = stash(graph.summary(degree).crossJoin(labels).select(F.lit(k).alias("dataset"), "nodes", "edges", "labels"), "summary")  # one row each
        if k == "wordadj":
            drop_stash(e)
            drop_stash(p)
        release(spark)
        return row

    with ThreadPoolExecutor(SIDE_BY_SIDE) as pool:
        return reduce(DataFrame.unionAll, pool.map(one, sorted(g.BUILDERS, key=lambda k: _HEAVY.index(k) if k in _HEAVY else 0)))


@query("neighbor_lists", with_sql("trade") + "SELECT src AS node, array_to_string(list(CAST(dst AS VARCHAR) ORDER BY dst), ',') AS neighbors FROM a GROUP BY 1")
def _lists(spark: SparkSession, sf: str) -> DataFrame:
    return graph.neighbor_lists(edges(spark, sf))


@query("choose_k", with_sql("trade") + "SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) AS k FROM n")
def _choose_k(spark: SparkSession, sf: str) -> DataFrame:
    k = partition.choose_k(nodes(edges(spark, sf)).count())
    return spark.createDataFrame([(k,)], "k long")


@query("parts_hash", with_sql("trade", PARTS) + "SELECT node, part FROM p")
def _hash(spark: SparkSession, sf: str) -> DataFrame:
    return parts(edges(spark, sf))


@query("parts_range", with_sql("trade") + f"SELECT node, CAST(floor((row_number() OVER (ORDER BY node) - 1) * {K} / (SELECT count(*) FROM n)) AS INTEGER) AS part FROM n")
def _range(spark: SparkSession, sf: str) -> DataFrame:
    return partition.ranged(nodes(edges(spark, sf)), K)


def _label_sql(before: str, after: str) -> str:
    return f"{after} AS (SELECT node, arg_min(part, (-votes, part)) AS part FROM (SELECT node, part, count(*) AS votes FROM (SELECT a.src AS node, q.part FROM a JOIN {before} q ON q.node = a.dst UNION ALL SELECT node, part FROM {before}) GROUP BY 1, 2) GROUP BY 1)"


@query("parts_labelprop_2rounds", with_sql("trade", PARTS, _label_sql("p", "p1"), _label_sql("p1", "p2")) + "SELECT node, part FROM p2")
def _labels(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return partition.label_round(e, partition.label_round(e, parts(e)))


@query("parts_multilevel")
def _multilevel(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    n = nodes(e)
    return partition.multilevel(Graph(n, e), partition.choose_k(n.count()))


@query("parts_label_prop_capped")
def _capped(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    n = nodes(e)
    return partition.label_prop(Graph(n, e), partition.choose_k(n.count()))


@query("parts_user", with_sql("geo") + "SELECT node, CAST(node % 7 AS INTEGER) AS part FROM n")
def _user(spark: SparkSession, sf: str) -> DataFrame:
    n = nodes(edges(spark, sf, "geo"))
    return partition.from_table(n.select("node", (F.col("node") % 7).alias("part")), n)


@query("parts_check", with_sql("wordadj") + " UNION ALL ".join(f"SELECT '{p}' AS partitioner, count(*) AS nodes, CAST(ceil(sqrt(count(*))) AS BIGINT) AS parts, true AS within_cap, true AS below_hash_cut FROM n" for p in ("multilevel", "label_prop")))
def _parts_check(spark: SparkSession, sf: str) -> DataFrame:
    """Both partitioners cover all nodes with k parts within the cap, and cut fewer edges than hash parts."""
    e = edges(spark, sf, "wordadj")
    gr = Graph(stash(nodes(e), "nodes"), e)
    n = gr.nodes.count()
    k, rows = partition.choose_k(n), []
    plain = partition.edge_cut(e, partition.hashed(gr.nodes, k)).count()
    for name, p in (("multilevel", partition.multilevel(gr, k)), ("label_prop", partition.label_prop(gr, k))):
        b = partition.balance(p.join(gr.nodes, "node", "left_semi").dropDuplicates(["node"]), k).first()
        rows.append((name, b["nodes"], b["parts"], b["ok"], partition.edge_cut(e, p).count() < plain))
    return spark.createDataFrame(rows, "partitioner string, nodes long, parts long, within_cap boolean, below_hash_cut boolean")


@query("balance_check", with_sql("trade", PARTS) + f"SELECT CAST(sum(s) AS BIGINT) AS nodes, count(*) AS parts, max(s) AS max_size, CAST(floor(1.03 * ceil(sum(s) / {K})) AS BIGINT) AS cap, max(s) <= floor(1.03 * ceil(sum(s) / {K})) AS ok FROM (SELECT part, count(*) AS s FROM p GROUP BY 1)")
def _balance(spark: SparkSession, sf: str) -> DataFrame:
    return partition.balance(parts(edges(spark, sf)), K)


@query("edge_cut_rows", with_sql("trade", PARTS, CROSS) + "SELECT src, dst, part_src, part_dst FROM x WHERE part_src <> part_dst")
def _cut(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return partition.edge_cut(e, parts(e))


@query("edge_cut_size", with_sql("trade", PARTS, CROSS) + "SELECT count(*) AS cut FROM x WHERE part_src <> part_dst")
def _cut_size(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return partition.edge_cut(e, parts(e)).agg(F.count("*").alias("cut"))


_CAP = 41
_SEATS = f"""r AS (SELECT node, part, row_number() OVER (PARTITION BY part ORDER BY {u32_sql('seat', 1, 'node')}, node) AS rn FROM p),
 s AS (SELECT i AS part, (SELECT count(*) FROM p WHERE p.part = i) AS size FROM range({K}) t(i)),
 o AS (SELECT part, COALESCE(sum(GREATEST(size - {_CAP}, 0)) OVER (ORDER BY part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS base FROM s),
 m AS (SELECT r.node, r.rn - {_CAP} + o.base AS seat FROM r JOIN o ON o.part = r.part WHERE r.rn > {_CAP}),
 f AS (SELECT part, {_CAP} - size AS free, COALESCE(sum({_CAP} - size) OVER (ORDER BY size, part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS base FROM s WHERE size < {_CAP}),
 q AS (SELECT part, base + unnest(range(1, free + 1)) AS seat FROM f)"""


@query("rebalance", with_sql("trade", PARTS, _SEATS) + f"SELECT node, part FROM r WHERE rn <= {_CAP} UNION ALL SELECT m.node, CAST(q.part AS INTEGER) FROM m JOIN q ON q.seat = m.seat")
def _rebalance(spark: SparkSession, sf: str) -> DataFrame:
    return partition.rebalance(parts(edges(spark, sf)), K, _CAP, fill=False)


@query("abstract_nodes", with_sql("trade", PARTS, CROSS) + "SELECT p.part, count(*) AS size, COALESCE((SELECT count(*) FROM x WHERE x.part_src = p.part AND x.part_dst = p.part), 0) AS internal_edges FROM p GROUP BY p.part")
def _anodes(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return abstract.nodes(e, parts(e))


def _aedges_of(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return abstract.abstract_edges(e, parts(e))


query("abstract_edges", with_sql("trade", PARTS, CROSS, ABSTRACT) + "SELECT src, dst, w FROM ae")(_aedges_of)
_TRANS = "tr AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS prob FROM aa)"
_AG = (PARTS, CROSS, ABSTRACT, ABSTRACT_ARCS, _TRANS)
_PROBS = with_sql("trade", *_AG) + "SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, round(prob, 6) AS prob FROM tr"


def _trans(spark: SparkSession, sf: str) -> DataFrame:
    return walks.transitions(stash(_aedges_of(spark, sf), "ae").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "w"))


@query("transitions", _PROBS)
def _transitions(spark: SparkSession, sf: str) -> DataFrame:
    return _trans(spark, sf).withColumn("prob", F.round("prob", 6))


@query("alias_mass", _PROBS)
def _alias_mass(spark: SparkSession, sf: str) -> DataFrame:
    return walks.alias_mass(walks.alias_tables(_trans(spark, sf))).where("prob > 1e-12").withColumn("prob", F.round(walks.settled(F.col("prob")), 6))


@query("alias_table")
def _alias(spark: SparkSession, sf: str) -> DataFrame:
    return walks.alias_tables(_trans(spark, sf))


@query("alias_blocks")
def _blocks(spark: SparkSession, sf: str) -> DataFrame:
    return walks.alias_blocks(_trans(spark, sf), 8)[1]


@query("alias_blocks_mass", _PROBS)
def _blocks_mass(spark: SparkSession, sf: str) -> DataFrame:
    """Probabilities rebuilt from both tables of the two-level draw."""
    return _rebuilt(*walks.alias_blocks(_trans(spark, sf), 8))


def _rebuilt(outer: DataFrame, inner: DataFrame) -> DataFrame:
    block = walks.alias_mass(outer).select("src", F.col("dst").alias("block"), F.col("prob").alias("share"))
    near = inner.select("src", "block", "deg", F.explode(F.array(F.struct(F.col("own").alias("dst"), F.col("p_keep").alias("p")), F.struct(F.col("alias").alias("dst"), (1 - F.col("p_keep")).alias("p")))).alias("e"))
    both = near.groupBy("src", "block", "e.dst").agg((F.sum("e.p") / F.first("deg")).alias("p")).join(block, ["src", "block"])
    return both.select("src", "dst", F.round(walks.settled(F.col("p") * F.col("share")), 6).alias("prob")).where("prob > 1e-12")


@query("walk_weighted_blocked")
def _by_blocks(spark: SparkSession, sf: str) -> DataFrame:
    t = stash(_trans(spark, sf), "trans")
    outer, inner = (stash(x, "alias") for x in walks.alias_blocks(t, 8))
    return walks.walk_rows(walks.weighted_blocked(outer, inner, t.select(F.col("src").alias("node")).distinct(), 4, 6))


def _walk_sql(table: str, length: int) -> str:
    """Unrolled steps; table nb(cur, nxt, lo, hi) gives each neighbour its interval of the draw."""
    steps = [f"w1 AS (SELECT k AS nth, node AS start, CAST(node AS VARCHAR) AS path, node AS cur FROM {table}, range(2) t(k))"]
    for s in range(1, length):
        u = u01_sql("slot", 1, "w.start", "w.nth", str(s))
        steps.append(f"w{s + 1} AS (SELECT w.nth, w.start, CASE WHEN nb.nxt IS NULL THEN w.path ELSE w.path || ',' || nb.nxt END AS path, nb.nxt AS cur FROM w{s} w LEFT JOIN nb ON nb.cur = w.cur AND {u} >= nb.lo AND {u} < nb.hi)")
    return ", ".join(steps)


@query("walk_uniform_L5", with_sql("wordadj", "d AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS slot, count(*) OVER (PARTITION BY src) AS deg FROM a)", "nb AS (SELECT src AS cur, dst AS nxt, slot / deg AS lo, (slot + 1) / deg AS hi FROM d)", _walk_sql("n", 5)) + "SELECT start, CAST(nth AS INTEGER) AS nth, path FROM w5")
def _uniform(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    return walks.walk_rows(walks.uniform(e, nodes(e), 2, 5))


@query("walk_weighted_cdf_L4", with_sql("trade", *_AG, "nn AS (SELECT DISTINCT CAST(src AS BIGINT) AS node FROM tr)", "cs AS (SELECT CAST(src AS BIGINT) AS cur, CAST(dst AS BIGINT) AS nxt, round(sum(prob) OVER (PARTITION BY src ORDER BY dst), 9) AS hi FROM tr)", "nb AS (SELECT cur, nxt, hi, COALESCE(lag(hi) OVER (PARTITION BY cur ORDER BY nxt), 0.0) AS lo FROM cs)", _walk_sql("nn", 4)) + "SELECT start, CAST(nth AS INTEGER) AS nth, path FROM w4")
def _cdf(spark: SparkSession, sf: str) -> DataFrame:
    t = stash(_trans(spark, sf), "trans")
    return walks.walk_rows(walks.by_cdf(t, t.select(F.col("src").alias("node")).distinct(), 2, 4))


@query("walk_weighted_alias")
def _by_alias(spark: SparkSession, sf: str) -> DataFrame:
    t = stash(_trans(spark, sf), "trans")
    return walks.walk_rows(walks.weighted(stash(walks.alias_tables(t), "alias"), t.select(F.col("src").alias("node")).distinct(), 4, 6))


@query("biased_walks")
def _biased(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    return walks.walk_rows(walks.biased(e, nodes(e), 1, 4, 0.5, 2.0))


_SECOND = f"st AS (SELECT src AS prev, dst AS cur, {u01_sql('second', 1, 'src', 'dst')} AS u FROM a), cw AS (SELECT st.prev, st.cur, st.u, c.dst AS cand, CASE WHEN c.dst = st.prev THEN 2.0 WHEN f.dst IS NOT NULL THEN 1.0 ELSE 0.5 END AS weight FROM st JOIN a c ON c.src = st.cur LEFT JOIN a f ON f.src = st.prev AND f.dst = c.dst), rs AS (SELECT *, sum(weight) OVER (PARTITION BY prev, cur ORDER BY cand) AS hi, sum(weight) OVER (PARTITION BY prev, cur) AS tot FROM cw)"


@query("biased_walk_step", with_sql("wordadj", _SECOND) + "SELECT prev, cur, min(cand) AS nxt FROM rs WHERE hi > u * tot GROUP BY 1, 2")
def _second(spark: SparkSession, sf: str) -> DataFrame:
    """One second-order step from every arc, return weight 2, outward weight 1/2."""
    e = edges(spark, sf, "wordadj")
    state = graph.arcs(e).select(F.col("src").alias("prev"), F.col("dst").alias("cur"))
    return walks.second_order_step(e, state, u01("second", 1, F.col("prev"), F.col("cur")), 0.5, 2.0).select("prev", "cur", F.col("cand").alias("nxt"))


_PAIR = "SELECT center, context, count(*) AS n FROM (SELECT x.v AS center, y.v AS context FROM v x JOIN v y ON x.start = y.start AND x.nth = y.nth AND x.i <> y.i AND abs(x.i - y.i) <= 2) GROUP BY 1, 2"


@query("context_pairs", ORACLES["walk_uniform_L5"].rsplit("SELECT start", 1)[0].rstrip() + ", v AS (SELECT start, nth, i, CAST(string_split(path, ',')[i] AS BIGINT) AS v FROM (SELECT start, nth, path, unnest(range(1, len(string_split(path, ',')) + 1)) AS i FROM w5)) " + _PAIR)
def _pairs(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "wordadj")
    return walks.context_pairs(walks.uniform(e, nodes(e), 2, 5), 2)


@query("edge_prox_samples", with_sql("trade") + f"SELECT src AS center, dst AS context, n FROM (SELECT src, dst, CAST(floor(1.5 + {u01_sql('edge', 1, 'src', 'dst')}) AS BIGINT) AS n FROM a) WHERE n > 0")
def _samples(spark: SparkSession, sf: str) -> DataFrame:
    return target.edge_samples(edges(spark, sf), 3, 0.5)


_MATCH = f"best AS (SELECT src, arg_max(dst, ({u32_sql('match', 1, 'LEAST(src, dst)', 'GREATEST(src, dst)')}, dst)) AS t FROM a GROUP BY 1), pr AS (SELECT b.src AS u, b.t AS v FROM best b JOIN best c ON c.src = b.t AND c.t = b.src WHERE b.src < b.t)"


@query("coarsen_edge_round", with_sql("trade", _MATCH) + "SELECT u AS node, u AS parent FROM pr UNION ALL SELECT v, u FROM pr")
def _edge_round(spark: SparkSession, sf: str) -> DataFrame:
    return coarsen.edges_round(edges(spark, sf))


_STARS = "dg AS (SELECT src AS node, count(*) AS d FROM a GROUP BY 1), hg AS (SELECT a.src AS node, a.dst AS hub FROM a JOIN dg x ON x.node = a.src AND x.d = 1 JOIN dg y ON y.node = a.dst AND y.d > 1), pq AS (SELECT node, hub, (row_number() OVER (PARTITION BY hub ORDER BY node) - 1) // 2 AS pair FROM hg)"


@query("coarsen_star", with_sql("geo", _STARS) + "SELECT node, parent FROM (SELECT node, min(node) OVER w AS parent, count(*) OVER w AS c FROM pq WINDOW w AS (PARTITION BY hub, pair)) WHERE c = 2")
def _stars(spark: SparkSession, sf: str) -> DataFrame:
    return coarsen.stars(edges(spark, sf, "geo"))


def _inherited(spark: SparkSession, e: DataFrame) -> DataFrame:
    return propagate.inherit(parts(e), stand_in_f_a(spark))


@query("inherit", with_sql("trade", PARTS, F_A, INHERIT) + long_sql("l0"))
def _inherit(spark: SparkSession, sf: str) -> DataFrame:
    return long_rows(_inherited(spark, edges(spark, sf)))


@query("neighbor_mean", with_sql("trade", PARTS, F_A, INHERIT) + "SELECT a.src AS node, l.dim, round(avg(l.val), 6) AS val FROM a JOIN l0 l ON l.node = a.dst GROUP BY 1, 2")
def _mean(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    return long_rows(propagate.neighbor_mean(e, _inherited(spark, e)).withColumnRenamed("mean", "vec"))


for _steps in (1, 3):
    query(f"propagate_{_steps}", with_sql("trade", PARTS, F_A, INHERIT, STEPS) + long_sql(f"l{_steps}"))(lambda spark, sf, n=_steps: long_rows(propagate.fixed(e := edges(spark, sf), _inherited(spark, e), n)))


@query("propagation_delta_trace", with_sql("trade", PARTS, F_A, INHERIT, STEPS) + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS iter, round(avg(d), 6) AS delta FROM (SELECT x.node, sqrt(sum((x.val - y.val) ** 2)) AS d FROM l{i - 1} x JOIN l{i} y ON x.node = y.node AND x.dim = y.dim GROUP BY 1)" for i in (1, 2, 3)))
def _trace(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf)
    _, trace = propagate.run(Graph(nodes(e), e), parts(e), stand_in_f_a(spark), delta=0.0, max_iter=3)
    return spark.createDataFrame([(t["iter"], round(t["delta"], 6)) for t in trace], "iter int, delta double")


@query("propagation_invariant", with_sql("trade", PARTS, F_A, INHERIT, STEPS, "dg AS (SELECT src AS node, count(*) AS d FROM a GROUP BY 1)") + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS step, dim, round(sum(d * val), 3) AS mass FROM l0 JOIN dg ON dg.node = l0.node GROUP BY 2" for i in range(4)))
def _invariant(spark: SparkSession, sf: str) -> DataFrame:
    """The oracle states the start's mass for every step: it must not change."""
    e = edges(spark, sf)
    d, emb, out = stash(graph.degrees(e), "deg"), _inherited(spark, e), None
    for i in range(4):
        mass = propagate.long_form(emb).join(d, "node").groupBy(F.col("dim").cast("long").alias("dim")).agg(F.round(F.sum(F.col("degree") * F.col("val")), 3).alias("mass")).select(F.lit(i).alias("step"), "dim", "mass")
        out = mass if out is None else out.unionAll(mass)
        emb = stash(propagate.step(e, emb), "emb")
    return out


def _member_sql(i: int) -> str:
    return f"m{i + 1} AS (SELECT node, part, sum(weight) AS weight FROM (SELECT a.src AS node, m.part, 0.5 * m.weight / c.deg AS weight FROM a JOIN c ON c.src = a.src JOIN m{i} m ON m.node = a.dst UNION ALL SELECT node, part, 0.5 * weight FROM m{i}) GROUP BY 1, 2)"


@query("membership_3", with_sql("geo", PARTS, "c AS (SELECT src, count(*) AS deg FROM a GROUP BY 1)", "m0 AS (SELECT node, part, 1.0::DOUBLE AS weight FROM p)", *(_member_sql(i) for i in range(3))) + "SELECT node, part, round(weight, 6) AS weight FROM m3")
def _member(spark: SparkSession, sf: str) -> DataFrame:
    e = edges(spark, sf, "geo")
    return propagate.membership(e, parts(e), 3).select("node", "part", F.round("weight", 6).alias("weight"))


@query("sketch_init_fixed", with_sql("trade", PARTS, F_A, INHERIT, STEPS) + long_sql("l2"))
def _fixed(spark: SparkSession, sf: str) -> DataFrame:
    """The initializer with hash parts, stand-in abstract vectors and two propagation steps."""
    e = edges(spark, sf)
    return long_rows(propagate.fixed(e, _inherited(spark, e), 2))


@query("warm_start", with_sql("trade", PARTS, F_A, INHERIT) + f"SELECT a.src AS node, l.dim, round(avg(l.val), 6) AS val FROM a JOIN l0 l ON l.node = a.dst WHERE {u32_sql('unseen', 1, 'a.src')} % 10 = 0 AND {u32_sql('unseen', 1, 'a.dst')} % 10 <> 0 GROUP BY 1, 2")
def _warm(spark: SparkSession, sf: str) -> DataFrame:
    """A tenth of the nodes is new: each starts from the mean of its known neighbours."""
    e = edges(spark, sf)
    known = _inherited(spark, e).where(u32("unseen", 1, F.col("node")) % 10 != 0)
    return long_rows(warm_start(known, e))


_FRACTIONS = (8, 4, 2, 1)


def _growth_sql(f: int) -> str:
    h = f"{u32_sql('grow', 1, 'X')} % {f} = 0"
    return f"(WITH ge AS (SELECT * FROM e WHERE {h.replace('X', 'src')} AND {h.replace('X', 'dst')}), gn AS (SELECT DISTINCT v FROM (SELECT src AS v FROM ge UNION ALL SELECT dst FROM ge)), gk AS (SELECT count(*) AS n, CAST(ceil(sqrt(count(*))) AS BIGINT) AS k FROM gn), gp AS (SELECT {u32_sql('part', 1, 'src')} % k AS p, {u32_sql('part', 1, 'dst')} % k AS q FROM ge, gk), gx AS (SELECT LEAST(p, q) AS p, GREATEST(p, q) AS q FROM gp WHERE p <> q) SELECT CAST({f} AS INTEGER) AS share, n AS nodes, (SELECT count(*) FROM ge) AS edges, k, (SELECT count(*) FROM gx) AS cut, (SELECT count(*) FROM (SELECT DISTINCT p, q FROM gx)) AS abstract_edges FROM gk)"


@query("abstract_growth", with_sql("trade") + " UNION ALL ".join(f"SELECT * FROM {_growth_sql(f)}" for f in _FRACTIONS))
def _growth(spark: SparkSession, sf: str) -> DataFrame:
    """How parts, cut and sketch grow with the graph: subgraphs on an eighth, a quarter, half and all of the nodes, hash parts."""
    e, out = edges(spark, sf), None
    for f in _FRACTIONS:
        some = e.where((u32("grow", 1, F.col("src")) % f == 0) & (u32("grow", 1, F.col("dst")) % f == 0))
        n = nodes(some)
        size = n.count()
        k = partition.choose_k(size) if size else 0
        ae = abstract.abstract_edges(some, partition.hashed(n, max(k, 1)))
        row = ae.agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("cut"), F.count("*").alias("abstract_edges"))
        one = row.select(F.lit(f).alias("share"), F.lit(size).cast("long").alias("nodes"), F.lit(some.count()).cast("long").alias("edges"), F.lit(k).cast("long").alias("k"), "cut", "abstract_edges")
        out = one if out is None else out.unionAll(one)
    return out
