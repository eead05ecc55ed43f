"""All queries of the library and their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable

from . import experiments, graphs, learned, measures, streams

Q = Callable


def queries() -> dict[str, Q]:
    return {k: v for m in (graphs, measures, learned, experiments, streams) for k, v in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in (graphs, measures, learned, experiments, streams) for k, v in m.ORACLES.items()}
