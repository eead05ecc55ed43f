"""Portable randomness: every draw is a pure function of purpose, seed, key and step, equal in Spark, DuckDB and Python."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, functions as F


def u32(purpose: str, seed: int, *keys: Column) -> Column:
    """A long in 0 .. 2**32 - 1."""
    text = F.concat_ws("|", F.lit(purpose), F.lit(str(seed)), *[k.cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def u01(purpose: str, seed: int, *keys: Column) -> Column:
    return u32(purpose, seed, *keys) / F.lit(4294967296.0)


def u32_py(purpose: str, seed: int, *keys: object) -> int:
    return int(hashlib.md5("|".join([purpose, str(seed), *map(str, keys)]).encode()).hexdigest()[:8], 16)


def u32_sql(purpose: str, seed: int, *keys: str) -> str:
    """The same in DuckDB SQL."""
    text = " || '|' || ".join([f"'{purpose}|{seed}'", *[f"CAST({k} AS VARCHAR)" for k in keys]])
    return f"CAST(('0x' || substr(md5({text}), 1, 8)) AS BIGINT)"


def u01_sql(purpose: str, seed: int, *keys: str) -> str:
    return f"({u32_sql(purpose, seed, *keys)} / 4294967296.0)"


def key_id(key: Column) -> Column:
    """A 60-bit id of a string key."""
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 15), 16, 10).cast("long")


def key_id_py(key: str) -> int:
    return int(hashlib.md5(key.encode()).hexdigest()[:15], 16)


def key_id_sql(key: str) -> str:
    return f"CAST(('0x' || substr(md5({key}), 1, 15)) AS BIGINT)"


# Bulk draws: a chain of XXH64 over longs, equal in Spark and numpy, for walks and samples of any size.

_SCALE = 2.0**-53
# The five primes of XXH64.
_P1, _P2, _P3, _P4, _P5 = (np.uint64(v) for v in (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261))


def _code(purpose: str) -> int:
    return int(hashlib.md5(purpose.encode()).hexdigest()[:12], 16)


def draw(purpose: str, seed: int, *keys: Column) -> Column:
    """Uniform in [0, 1) from long keys."""
    h = F.xxhash64(F.lit(_code(purpose)).cast("long"), F.lit(seed).cast("long"), *[k.cast("long") for k in keys])
    return F.shiftrightunsigned(h, 11) * F.lit(_SCALE)


def _turn(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _chain(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = (seed + _P5 + np.uint64(8)) ^ (_turn(value * _P2, 31) * _P1)
    h = _turn(h, 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def draw_np(purpose: str, seed: int, *keys: np.ndarray | int) -> np.ndarray:
    """The same numbers as draw() for arrays of keys."""
    with np.errstate(over="ignore"):
        h = np.full(1, 42, np.uint64)
        for k in (_code(purpose), seed, *keys):
            h = _chain(np.atleast_1d(np.asarray(k, np.int64)).view(np.uint64), h)
    return (h >> np.uint64(11)) * _SCALE
