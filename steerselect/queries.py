"""Registry of the engine's own queries and of the SQL that checks them."""

from __future__ import annotations

from .plans import core_queries, measure_queries, more_queries, proxy_queries, relational_queries, workloads  # noqa: F401
from .plans.registry import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
