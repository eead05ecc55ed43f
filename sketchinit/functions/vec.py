"""Vector functions on array columns, and sums of vectors by key."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.functions import pandas_udf


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Null where a vector is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n)


def euclid(a: Column, b: Column) -> Column:
    """The distance; smaller is more similar."""
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))


def similarity(a: Column, b: Column, sim: str) -> Column:
    """Larger is more similar, for either measure."""
    return cosine(a, b) if sim == "cosine" else -euclid(a, b)


def sum_vectors(df: DataFrame, key: str = "node", vec: str = "vec", counts: str | None = None) -> DataFrame:
    """(key, vec, n): element-wise sums and counts (those of the column `counts`, else of rows). Batches combine before the exchange, so a hub costs one row a batch."""

    def combine(keys: np.ndarray, x: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        order = np.argsort(keys, kind="stable")
        k = keys[order]
        at = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        return k[at], np.add.reduceat(x[order], at, axis=0), np.add.reduceat(n[order], at)

    def batch(k: np.ndarray, x: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        width = x.shape[1]
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, width or 1), pa.int32()), pa.array(x.ravel()))
        return pa.RecordBatch.from_arrays([pa.array(k), lists, pa.array(n)], names=[key, vec, "n"])

    def parts(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        flat = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        return b.column(0).to_numpy(zero_copy_only=False), flat.reshape(b.num_rows, -1)

    def first(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            if b.num_rows:
                k, x = parts(b)
                yield batch(*combine(k, x, b.column(2).to_numpy()))

    def last(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None
        for b in it:
            if not b.num_rows:
                continue
            k, x = parts(b)
            n = b.column(2).to_numpy()
            if held is not None:
                k, x, n = np.concatenate([held[0], k]), np.vstack([held[1], x]), np.concatenate([held[2], n])
            k, x, n = combine(k, x, n)
            held = (k[-1:], x[-1:], n[-1:])
            if len(k) > 1:
                yield batch(k[:-1], x[:-1], n[:-1])
        if held is not None:
            yield batch(*held)

    kind = f"{key} long, {vec} array<double>, n long"
    some = df.select(F.col(key).cast("long"), F.col(vec).cast("array<double>"), (F.col(counts) if counts else F.lit(1)).cast("long").alias("n")).mapInArrow(first, kind)
    return some.repartition(key).sortWithinPartitions(key).mapInArrow(last, kind)


@pandas_udf(T.ArrayType(T.DoubleType()))
def vec_mean(v: pd.Series) -> list:
    """Grouped aggregate for SQL users; large groups should use sum_vectors."""
    return np.stack(v.to_numpy()).mean(axis=0).tolist()


@pandas_udf(T.DoubleType())
def vec_cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x: object, y: object) -> float:
        x, y = np.asarray(x, float), np.asarray(y, float)
        n = float(np.sqrt((x @ x) * (y @ y)))
        return float(x @ y) / n if n else float("nan")

    return pd.Series([one(x, y) for x, y in zip(a, b)])


@pandas_udf(T.DoubleType())
def vec_euclid(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.linalg.norm(np.asarray(x, float) - np.asarray(y, float))) for x, y in zip(a, b)])


def register(spark: SparkSession) -> None:
    """Make the functions usable in SQL text."""
    from .udtf import RandomWalks, SkipGramPairs

    for name, f in (("vec_mean", vec_mean), ("vec_cosine", vec_cosine), ("vec_euclid", vec_euclid)):
        spark.udf.register(name, f)
    spark.udtf.register("random_walks", RandomWalks)
    spark.udtf.register("skip_gram_pairs", SkipGramPairs)
