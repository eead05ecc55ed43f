"""Stand-in graphs built from the given tables; each builder has its DuckDB form beside it.

Node ids are arithmetic on the tables' keys (two kinds of nodes: doubled keys,
the second kind odd) or 60 bits of an md5 for words, so no global numbering
is needed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, functions as F, types as T

from ..functions.rng import key_id, key_id_py, key_id_sql, u01, u01_sql
from .pairs import degrees_within, pairs_within
from .tables import spread, table

WORD = r"\A\p{L}+\z"


def simple(df: DataFrame, a: Column, b: Column) -> DataFrame:
    """Distinct undirected edges: src < dst, no nulls, no loops."""
    return df.select(F.least(a, b).cast("long").alias("src"), F.greatest(a, b).cast("long").alias("dst")).where("src <> dst and src is not null and dst is not null").distinct()


def _simple_sql(a: str, b: str, source: str) -> str:
    return f"SELECT DISTINCT CAST(LEAST({a}, {b}) AS BIGINT) AS src, CAST(GREATEST({a}, {b}) AS BIGINT) AS dst FROM {source} AND {a} <> {b}"


def _order_lines(spark: SparkSession, sf_dir: str, *cols: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return table(spark, sf_dir, "lineitem").select("l_orderkey", *cols).join(o, F.col("l_orderkey") == F.col("o_orderkey"))


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer - supplier."""
    return simple(_order_lines(spark, sf_dir, "l_suppkey"), F.col("o_custkey") * 2, F.col("l_suppkey") * 2 + 1)


def custpart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer - part."""
    return simple(_order_lines(spark, sf_dir, "l_partkey"), F.col("o_custkey") * 2, F.col("l_partkey") * 2 + 1)


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of one order; an order has few lines, so no group is large."""
    a = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    return simple(a.join(a.withColumnRenamed("l_partkey", "p"), "l_orderkey").where("l_partkey < p"), F.col("l_partkey"), F.col("p"))


def _active(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int, int]:
    """What pairs_within() takes for coactive."""
    e = table(spark, sf_dir, "events").select(F.unix_micros(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("key"), F.col("user_id").alias("member")).distinct()
    return e, *e.agg(F.count("*"), F.approx_count_distinct("member")).first()


def coactive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with events in one clock hour."""
    return pairs_within(*_active(spark, sf_dir))


def geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region - nation - customer and supplier."""
    n, c, s = (table(spark, sf_dir, t) for t in ("nation", "customer", "supplier"))
    pairs = n.select((F.col("n_regionkey").cast("long") * 4).alias("a"), (F.col("n_nationkey").cast("long") * 4 + 1).alias("b"))
    pairs = pairs.unionAll(c.select(F.col("c_nationkey").cast("long") * 4 + 1, F.col("c_custkey") * 4 + 2)).unionAll(s.select(F.col("s_nationkey").cast("long") * 4 + 1, F.col("s_suppkey") * 4 + 3))
    return simple(pairs, F.col("a"), F.col("b"))


MIN_COUNT = 5  # times that two words must stand side by side


def word_pairs(spark: SparkSession, sf_dir: str, *by: str) -> DataFrame:
    """(a, b, *by, n): how often two letter-only words, given by their ids, stand side by side in the whole texts, a < b. A batch of texts counts its
    pairs by numbers of its words, so a pair becomes a row once a batch."""
    d = spread(table(spark, sf_dir, "documents").select(F.lower("text").alias("text"), *by)).where("text is not null")
    schema = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType()), *d.schema.fields[1:], T.StructField("n", T.LongType())])
    return d.mapInArrow(_adjacent, schema).groupBy("a", "b", *by).agg(F.sum("n").alias("n"))


def _adjacent(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counted pairs of each batch (text, at most one other column)."""
    for batch in it:
        lists = pc.split_pattern(batch.column(0), " ")
        flat = lists.flatten().dictionary_encode()
        code, words = flat.indices.to_numpy(), flat.dictionary
        if not len(code):
            continue
        good = pc.match_substring_regex(words, WORD).to_numpy(zero_copy_only=False)
        ids = np.full(len(words), -1, np.int64)
        ids[good] = [key_id_py(w) for w in words.filter(pa.array(good)).to_pylist()]
        sizes = pc.list_value_length(lists).to_numpy()
        inside = np.ones(len(code), bool)
        inside[np.cumsum(sizes) - 1] = False  # a text's last word
        at = np.flatnonzero(inside[:-1] & good[code[:-1]] & good[code[1:]] & (code[:-1] != code[1:]))
        x, y = code[at].astype(np.int64), code[at + 1].astype(np.int64)
        key = np.where(ids[x] < ids[y], x * len(words) + y, y * len(words) + x)
        some = batch.column(1).dictionary_encode() if batch.num_columns > 1 else None
        kinds = 1
        if some is not None:
            kinds = len(some.dictionary) + 1  # the last one: null
            key = key * kinds + some.indices.fill_null(kinds - 1).to_numpy()[np.repeat(np.arange(len(sizes)), sizes)[at]]
        key, n = np.unique(key, return_counts=True)
        key, kind = key // kinds, key % kinds
        out = {"a": pa.array(ids[key // len(words)]), "b": pa.array(ids[key % len(words)])}
        if some is not None:
            out[batch.schema.names[1]] = some.dictionary.take(pa.array(kind, mask=kind == kinds - 1))
        yield pa.RecordBatch.from_pydict({**out, "n": pa.array(n.astype(np.int64))})


def wordadj(spark: SparkSession, sf_dir: str, min_count: int = MIN_COUNT) -> DataFrame:
    """Words that stand side by side at least min_count times."""
    return often(word_pairs(spark, sf_dir), min_count)


def often(pairs: DataFrame, min_count: int = MIN_COUNT) -> DataFrame:
    """Edges of the pairs(a, b, n) that stand there min_count times or more."""
    kept = pairs.where(F.col("n") >= min_count)
    return simple(kept, F.col("a"), F.col("b"))


def word_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node, label): each word's most frequent language over all its pairs, ties to the larger name."""
    return labels_of(word_pairs(spark, sf_dir, "lang"))


def labels_of(pairs: DataFrame) -> DataFrame:
    """(node, label) from pairs(a, b, lang, n)."""
    each = pairs.select(F.explode(F.array("a", "b")).alias("w"), "lang", "n")
    n = each.groupBy("w", "lang").agg(F.sum("n").alias("n"))
    return n.groupBy("w").agg(F.max(F.struct("n", "lang"))["lang"].alias("label")).select(F.col("w").alias("node"), "label")


WORD_BYTES = 5  # of a word in a text, about


def _runs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int, int]:
    """What pairs_within() takes for docshare."""
    d = spread(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", F.split(F.lower("text"), " ").alias("w"))
    each = F.transform(F.sequence(F.lit(0), F.size("w") - 5), lambda i: F.xxhash64(F.array_join(F.slice("w", i + 1, 5), " ")))
    s = d.where(F.size("w") >= 5).select(F.explode(F.array_distinct(each)).alias("key"), F.col("doc_id").alias("member"))
    n = table(spark, sf_dir, "documents").agg(F.sum(F.octet_length("text")), F.count("*")).first()
    return s, (n[0] or 0) // WORD_BYTES, n[1]


def docshare(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share 5 consecutive tokens anywhere in their texts. Runs of tokens are told apart by XXH64."""
    return pairs_within(*_runs(spark, sf_dir))


def pagenav(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page - word of a navigation link."""
    p = table(spark, sf_dir, "pages").select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit(r'href="/([^"/]+)"'), 1))).alias("w"))
    return simple(p, key_id(F.concat(F.lit("p"), F.col("page_id").cast("string"))), key_id(F.concat(F.lit("w"), F.col("w"))))


def vecknn(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """Vectors and their k nearest by cosine, by exact search in pairs of blocks with partial top k."""
    from ..operators.metrics import nearest

    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), F.col("embedding").alias("vec"))
    return simple(nearest(e, e, k, digits=9), F.col("query"), F.col("node"))


def planted(spark: SparkSession, groups: int, size: int, p_in: float, p_out: float, seed: int = 1) -> DataFrame:
    """Known groups: node // size is the group."""
    n = groups * size
    a = spark.range(n).withColumnRenamed("id", "src")
    a = a.select("src", F.explode(F.sequence(F.col("src"), F.lit(n - 1))).alias("dst")).where("src <> dst")
    p = F.when(F.floor(F.col("src") / size) == F.floor(F.col("dst") / size), p_in).otherwise(p_out)
    return a.where(u01("planted", seed, F.col("src"), F.col("dst")) < p)


def planted_on(nodes: DataFrame, p_in: float, p_out: float, seed: int = 1) -> DataFrame:
    """Known groups on given nodes(world, part, node): edges inside a part, and fewer between the parts of a world."""
    other = nodes.select("world", F.col("part").alias("other"), F.col("node").alias("dst"))
    both = nodes.withColumnRenamed("node", "src").join(other, "world").where("src < dst")
    p = F.when(F.col("part") == F.col("other"), p_in).otherwise(p_out)
    return both.where(u01("planted", seed, F.col("src"), F.col("dst")) < p).select("src", "dst")


def planted_sql(nodes: str, p_in: float, p_out: float, seed: int = 1) -> str:
    return f"SELECT a.node AS src, b.node AS dst FROM {nodes} a JOIN {nodes} b ON b.world = a.world AND a.node < b.node WHERE {u01_sql('planted', seed, 'a.node', 'b.node')} < CASE WHEN a.part = b.part THEN {p_in} ELSE {p_out} END"


BUILDERS = {"trade": trade, "custpart": custpart, "copurchase": copurchase, "coactive": coactive, "geo": geo, "wordadj": wordadj, "docshare": docshare, "pagenav": pagenav, "vecknn": vecknn}

#: (node, degree) of graphs whose pairs are too many to leave their tasks only to be counted
DEGREES = {"coactive": lambda spark, sf: degrees_within(*_active(spark, sf)), "docshare": lambda spark, sf: degrees_within(*_runs(spark, sf))}

_WORD_PAIRS = """(SELECT w[i] AS a, w[i + 1] AS b, lang FROM (SELECT w, lang, unnest(range(1, len(w))) AS i FROM (SELECT string_split(lower(text), ' ') AS w, lang FROM documents))
 WHERE regexp_full_match(w[i], '\\p{L}+') AND regexp_full_match(w[i + 1], '\\p{L}+') AND w[i] <> w[i + 1])"""

SQL = {
    "trade": _simple_sql("o_custkey * 2", "l_suppkey * 2 + 1", "lineitem JOIN orders ON l_orderkey = o_orderkey WHERE true"),
    "custpart": _simple_sql("o_custkey * 2", "l_partkey * 2 + 1", "lineitem JOIN orders ON l_orderkey = o_orderkey WHERE true"),
    "copurchase": _simple_sql("a.l_partkey", "b.l_partkey", "lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey WHERE true"),
    "coactive": "SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM (SELECT DISTINCT user_id, date_trunc('hour', ts) AS h FROM events) a JOIN (SELECT DISTINCT user_id, date_trunc('hour', ts) AS h FROM events) b ON a.h = b.h AND a.user_id < b.user_id",
    "geo": _simple_sql("a", "b", "(SELECT CAST(n_regionkey AS BIGINT) * 4 AS a, CAST(n_nationkey AS BIGINT) * 4 + 1 AS b FROM nation UNION ALL SELECT CAST(c_nationkey AS BIGINT) * 4 + 1, c_custkey * 4 + 2 FROM customer UNION ALL SELECT CAST(s_nationkey AS BIGINT) * 4 + 1, s_suppkey * 4 + 3 FROM supplier) WHERE true"),
    "wordadj": f"SELECT LEAST({key_id_sql('a')}, {key_id_sql('b')}) AS src, GREATEST({key_id_sql('a')}, {key_id_sql('b')}) AS dst FROM (SELECT LEAST(a, b) AS a, GREATEST(a, b) AS b FROM {_WORD_PAIRS}) GROUP BY a, b HAVING count(*) >= {MIN_COUNT}",
    "docshare": "WITH s AS (SELECT DISTINCT doc_id, md5(array_to_string(w[i:i + 4], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM (SELECT doc_id, string_split(lower(text), ' ') AS w FROM documents))) SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM s a JOIN s b ON a.h = b.h AND a.doc_id < b.doc_id",
    "pagenav": _simple_sql(key_id_sql("'p' || page_id"), key_id_sql("'w' || w"), "(SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"/([^\"/]+)\"', 1)) AS w FROM pages) WHERE true"),
    "vecknn": "SELECT DISTINCT LEAST(v, o) AS src, GREATEST(v, o) AS dst FROM (SELECT a.vec_id AS v, b.vec_id AS o, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(-list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9), b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 10",
}
LABEL_SQL = f"SELECT {key_id_sql('w')} AS node, label FROM (SELECT w, arg_max(lang, (n, lang)) AS label FROM (SELECT w, lang, count(*) AS n FROM (SELECT a AS w, lang FROM {_WORD_PAIRS} UNION ALL SELECT b, lang FROM {_WORD_PAIRS}) GROUP BY w, lang) GROUP BY w)"
