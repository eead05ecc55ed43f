"""Table functions for SQL users: walks over a neighbour table, and context pairs of one path."""

from __future__ import annotations

import json

from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from .rng import u32_py


@udtf(returnType=T.StructType([T.StructField("walk", T.IntegerType()), T.StructField("path", T.ArrayType(T.LongType()))]))
class RandomWalks:
    """random_walks(start, neighbours_json, walks, length, seed): uniform walks; neighbours_json maps a node to a list."""

    def eval(self, start: int, neighbours: str, walks: int, length: int, seed: int):  # noqa: ANN201
        table = json.loads(neighbours)
        for w in range(walks):
            path = [start]
            while len(path) < length and table.get(str(path[-1])):
                at = table[str(path[-1])]
                path.append(at[u32_py("udtf", seed, start, w, len(path)) * len(at) >> 32])
            yield w, path


@udtf(returnType=T.StructType([T.StructField("center", T.LongType()), T.StructField("context", T.LongType())]))
class SkipGramPairs:
    """skip_gram_pairs(path, window)."""

    def eval(self, path: list, window: int):  # noqa: ANN201
        for i, a in enumerate(path):
            for j in range(max(0, i - window), min(len(path), i + window + 1)):
                if i != j:
                    yield a, path[j]
