"""Registry of the workloads and operator queries: each module adds ``QUERIES`` and ``ORACLES``."""

from __future__ import annotations

from .plans import chain_queries, operator_queries, relational_queries, scan_queries, step_queries
from .plans.analysis import flagship as FLAGSHIP  # noqa: N812
from .streaming import streams

MODULES = (chain_queries, operator_queries, relational_queries, scan_queries, step_queries, streams)


def queries() -> dict:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in m.ORACLES.items()}
