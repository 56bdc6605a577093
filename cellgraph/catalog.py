"""All queries of the graph engine by name, with their DuckDB SQL."""

from __future__ import annotations

from . import experiments, graph_queries  # noqa: F401  (these modules register their queries)
from .registry import ORACLES, QUERIES
from .relops import functions, relational  # noqa: F401
from .streaming import edges  # noqa: F401


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return dict(ORACLES)
