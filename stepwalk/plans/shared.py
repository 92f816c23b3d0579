"""What many queries need: a graph written once per call, its walk, and the registry that pairs a query with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..config import WalkParams, swept, written
from ..graph.build import GRAPHS, PAIRS, both_ways
from ..walk.engine import BASE, Engine, Variant, Walk

Query = Callable[[SparkSession, str], DataFrame]

P_LOCAL = WalkParams(0.5, 2.0, length=6, walks_per_vertex=1)
P_FAR = WalkParams(2.0, 0.5, length=6, walks_per_vertex=1)
P_PLAIN = WalkParams(length=6, walks_per_vertex=1)
PARTS = 7


class Registry:
    """Queries by name, each with SQL or without."""

    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, query: Query, sql: str | None = None) -> None:
        if name in self.queries:
            raise ValueError(f"{name} is registered already")
        self.queries[name] = query
        if sql is not None:
            self.sql[name] = sql

    def __call__(self, sql: str | None = None) -> Callable[[Query], Query]:
        def wrap(query: Query) -> Query:
            self.add(query.__name__, query, sql)
            return query

        return wrap


def graph(spark: SparkSession, sf_dir: str, name: str = "user") -> DataFrame:
    if name in PAIRS:
        out = both_ways(written(PAIRS[name](spark, sf_dir), f"graph-{name}", "zstd"))
        swept(spark)
        return out
    return written(GRAPHS[name](spark, sf_dir), f"graph-{name}")


def parts_for(edges: DataFrame, part_bytes: int = 64 << 20) -> int:
    """Partitions of a graph for walks whose results do not depend on it: PARTS, more where 16 bytes an edge would outgrow a task."""
    return max(PARTS, -(-edges.count() * 16 // part_bytes))


def walked(spark: SparkSession, sf_dir: str, name: str = "user", params: WalkParams = P_LOCAL, variant: Variant = BASE, **options) -> tuple[DataFrame, Walk]:
    edges = graph(spark, sf_dir, name)
    engine = Engine.of_edges(edges, parts=PARTS)
    try:
        return edges, engine.walk(params, variant, **options)
    finally:
        engine.close()
