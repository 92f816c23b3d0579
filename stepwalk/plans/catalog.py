"""All queries of the walk engine and of the surrounding operators, with their SQL."""

from __future__ import annotations

from .shared import Query, Registry


def _registries() -> list[Registry]:
    from ..functions import scalar
    from ..operators import relational, udfs
    from ..sources import queries as sources
    from ..streaming import queries as streams
    from . import graph_queries, walk_queries, workloads

    return [m.registry for m in (graph_queries, walk_queries, workloads, sources, relational, udfs, scalar, streams)]


def queries() -> dict[str, Query]:
    return {k: v for r in _registries() for k, v in r.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for r in _registries() for k, v in r.sql.items()}
