"""Reading tables and edge lists, writing embeddings and models."""

from __future__ import annotations

import json
import re

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGE = "src long, dst long"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """df over all cores where its files give fewer parts than there are cores; large tables come split already and do not move."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(2 * cores) if df.rdd.getNumPartitions() < cores else df


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for n in names:
        table(spark, sf_dir, n).createOrReplaceTempView(n)


def edges_csv(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """CSV or TSV with two id columns, comment lines with #."""
    return spark.read.schema(EDGE).option("sep", sep).option("comment", "#").csv(path)


def edges_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(EDGE).json(path)


def edges_text(spark: SparkSession, path: str) -> DataFrame:
    """White-space separated pairs, comments behind # or %; whatever does not parse is dropped."""
    part = F.split(F.btrim(F.regexp_replace("value", "[#%].*", "")), r"\s+")
    whole = lambda i: F.when(F.get(part, i).rlike(r"^[+-]?\d{1,19}$"), F.get(part, i).try_cast("long"))
    return spark.read.text(path).select(whole(0).alias("src"), whole(1).alias("dst")).where("src is not null and dst is not null")


def parse_edge(line: str) -> tuple[int, int] | None:
    """The first two fields of a line as ids; None where they are not whole numbers of 64 bits. The same rule as edges_text()."""
    p = re.sub("[#%].*", "", line).split()
    if len(p) < 2 or not all(re.fullmatch(r"[+-]?[0-9]{1,19}", x) for x in p[:2]):
        return None
    a, b = int(p[0]), int(p[1])
    return (a, b) if all(-(1 << 63) <= x < 1 << 63 for x in (a, b)) else None


def edges_of(spark: SparkSession, pairs: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame(pairs, EDGE)


class _Lines(InputPartition):
    def __init__(self, path: str, part: int, parts: int) -> None:
        self.path, self.part, self.parts = path, part, parts


class EdgeListSource(DataSource):
    """spark.read.format("edges").load(path): an edge-list text file on a path that every executor sees."""

    @classmethod
    def name(cls) -> str:
        return "edges"

    def schema(self) -> str:
        return EDGE

    def reader(self, schema: object) -> DataSourceReader:
        return _EdgeReader(self.options)


class _EdgeReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.parts = options["path"], int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        return [_Lines(self.path, i, self.parts) for i in range(self.parts)]

    def read(self, partition: _Lines):  # noqa: ANN201
        import os

        size = os.path.getsize(partition.path)
        lo, hi = (size * k // partition.parts for k in (partition.part, partition.part + 1))
        with open(partition.path, "rb") as f:
            if lo:
                f.seek(lo - 1)
                f.readline()
            while f.tell() < hi:
                line = f.readline()
                if not line:
                    break
                edge = parse_edge(line.decode("utf-8", "replace"))
                if edge:
                    yield edge


def write_embeddings(emb: DataFrame, path: str, kind: str = "parquet", by: str | None = None) -> None:
    """parquet (optionally partitioned), text (word-vector lines: id and numbers) or csv."""
    if kind == "parquet":
        w = emb.write
        (w.partitionBy(by) if by else w).parquet(path)
        return
    numbers = F.array_join(F.transform("vec", lambda x: x.cast("string")), " " if kind == "text" else ";")
    if kind == "text":
        emb.select(F.concat_ws(" ", F.col("node").cast("string"), numbers).alias("value")).write.text(path)
    else:
        emb.select("node", numbers.alias("vec")).write.option("header", True).csv(path)


def save_model(spark: SparkSession, model: dict, path: str) -> None:
    spark.createDataFrame([(json.dumps(model),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(path).first()[0])
