"""What the query modules share: the graphs most queries run on, and pieces of DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions.rng import u01, u01_sql, u32_sql
from ..operators import partition
from ..plans.storage import stash
from ..sources import graphs

D = 4  # dimensions of oracle-checked vectors
K = 40  # parts of the oracle-checked partition of the trade graph


def edges(spark: SparkSession, sf_dir: str, key: str = "trade") -> DataFrame:
    return stash(graphs.BUILDERS[key](spark, sf_dir), "edges")


def nodes(e: DataFrame) -> DataFrame:
    return e.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def parts(e: DataFrame, k: int = K) -> DataFrame:
    return partition.hashed(nodes(e), k)


def stand_in(purpose: str, key: Column, d: int = D) -> Column:
    """A deterministic vector of a key: d portable draws."""
    return F.array(*[u01(purpose, 1, key, F.lit(i)) for i in range(d)])


def stand_in_f_a(spark: SparkSession, k: int = K) -> DataFrame:
    return spark.range(k).select(F.col("id").cast("int").alias("part"), stand_in("fa", F.col("id")).alias("vec"))


def with_sql(key: str, *ctes: str) -> str:
    """WITH clause: e(src, dst) of the graph, a(src, dst) both ways, n(node), then more."""
    first = [f"e AS ({graphs.SQL[key]})", "a AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)", "n AS (SELECT DISTINCT src AS node FROM a)"]
    return "WITH RECURSIVE " + ", ".join([*first, *ctes]) + " "


PARTS = f"p AS (SELECT node, CAST({u32_sql('part', 1, 'node')} % {K} AS INTEGER) AS part FROM n)"
CROSS = "x AS (SELECT e.src, e.dst, ps.part AS part_src, pd.part AS part_dst FROM e JOIN p ps ON ps.node = e.src JOIN p pd ON pd.node = e.dst)"
ABSTRACT = "ae AS (SELECT LEAST(part_src, part_dst) AS src, GREATEST(part_src, part_dst) AS dst, count(*) AS w FROM x WHERE part_src <> part_dst GROUP BY 1, 2)"
ABSTRACT_ARCS = "aa AS (SELECT src, dst, w FROM ae UNION ALL SELECT dst, src, w FROM ae)"
F_A = f"fa AS (SELECT i AS part, j AS dim, {u01_sql('fa', 1, 'i', 'j')} AS val FROM range({K}) t(i), range({D}) s(j))"
INHERIT = "l0 AS (SELECT p.node, fa.dim, fa.val FROM p JOIN fa ON fa.part = p.part)"


def step_sql(before: str, after: str) -> str:
    return f"{after} AS (SELECT l.node, l.dim, CASE WHEN m.val IS NULL THEN l.val ELSE 0.5 * l.val + 0.5 * m.val END AS val FROM {before} l LEFT JOIN (SELECT a.src AS node, b.dim, avg(b.val) AS val FROM a JOIN {before} b ON b.node = a.dst GROUP BY 1, 2) m ON m.node = l.node AND m.dim = l.dim)"


STEPS = ", ".join(step_sql(f"l{i}", f"l{i + 1}") for i in range(3))


def long_rows(emb: DataFrame) -> DataFrame:
    return emb.select("node", F.posexplode("vec").alias("dim", "v")).select("node", F.col("dim").cast("long").alias("dim"), F.round("v", 6).alias("val"))


def long_sql(table: str) -> str:
    return f"SELECT node, dim, round(val, 6) AS val FROM {table}"
