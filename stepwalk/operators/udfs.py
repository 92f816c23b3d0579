"""The engine's pieces as user functions: pandas, Arrow, table and SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..graph.model import adjacency, part_of
from ..plans import oracle
from ..plans.graph_queries import _bounded_sql
from ..plans.shared import P_LOCAL, PARTS, Registry, graph, walked
from ..sources.tables import table
from ..walk import alias
from ..walk.bounds import gap
from ..walk.kernel import member, pick
from ..walk.pairs import transition_lists
from ..walk.rng import draw48

registry = Registry()


@registry(_bounded_sql(2.0, 0.5, "u, v, round(high - low, 9) AS gap", name="user"))
def udf_scalar_bounds(spark, sf_dir):
    edges = graph(spark, sf_dir)
    d = edges.groupBy("src").agg(F.count("*").alias("deg"), F.min("w").alias("wmin"), F.max("w").alias("wmax"))

    @pandas_udf("double")
    def spread(du: pd.Series, dv: pd.Series, low: pd.Series, high: pd.Series) -> pd.Series:
        return pd.Series(gap(du.to_numpy(), dv.to_numpy(), low.to_numpy(), high.to_numpy(), 2.0, 0.5))

    rows = edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).join(d.select(F.col("src").alias("u"), F.col("deg").alias("du")), "u")
    rows = rows.join(d.select(F.col("src").alias("v"), F.col("deg").alias("dv"), "wmin", "wmax"), "v")
    return rows.select("u", "v", F.round(spread("du", "dv", "wmin", "wmax"), 9).alias("gap"))


def _grouped_alias(spark, sf_dir, of="true"):
    """Alias tables of each pair's neighbours give back a distribution."""

    def total(us: np.ndarray, v: int, ids: np.ndarray, pi: np.ndarray) -> pa.RecordBatch:
        sums = [round(float(alias.probabilities(*alias.build(row)).sum()), 9) for row in pi]
        return pa.RecordBatch.from_arrays([pa.array(us), pa.array(np.full(len(us), v)), pa.array(np.full(len(us), len(ids))), pa.array(sums, pa.float64())], ["u", "v", "n", "total"])

    edges = graph(spark, sf_dir)
    return transition_lists(edges, P_LOCAL, total, "u long, v long, n long, total double", edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).where(of))


# Queries whose name ends in _all are the whole of those without the ending, which are slices by id.
registry.add("udf_grouped_alias", lambda s, d: _grouped_alias(s, d, "u <= 30"), oracle.transitions_sql("user", P_LOCAL, "SELECT u, v, count(*) AS n, 1.0::DOUBLE AS total FROM t WHERE u <= 30 GROUP BY u, v"))
registry.add("udf_grouped_alias_all", _grouped_alias, oracle.transitions_sql("user", P_LOCAL, "SELECT u, v, count(*) AS n, 1.0::DOUBLE AS total FROM t GROUP BY u, v"))


@registry(oracle.walk_sql("user", P_LOCAL.but(length=1), "SELECT start, cur AS vertex FROM walk WHERE step = 1"))
def udf_map_arrow_step(spark, sf_dir):
    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, ws = b.column("ids"), b.column("ws")
            lengths = np.asarray(ids.value_lengths())
            at = pick(np.asarray(ws.flatten()), lengths, np.asarray(b.column("draw")))
            yield pa.RecordBatch.from_arrays([b.column("vid"), pa.array(np.asarray(ids.flatten())[at])], ["start", "vertex"])

    rows = adjacency(graph(spark, sf_dir)).withColumn("draw", draw48(P_LOCAL.seed, 0, "vid", 1))
    return rows.mapInArrow(step, "start long, vertex long")


@registry(oracle.walk_sql("user", P_LOCAL.but(length=2), "SELECT w.start, w.prev, w.cur, count(e.dst) AS n_common FROM walk w LEFT JOIN edges e ON e.src = w.prev AND EXISTS (SELECT 1 FROM edges b WHERE b.src = w.cur AND b.dst = e.dst) WHERE w.step = 2 GROUP BY 1, 2, 3"))
def udf_cogroup_local(spark, sf_dir):
    """Common neighbours of each walker's last two vertices, where a partition's walkers meet the lists they need."""
    edges, walk = walked(spark, sf_dir, params=P_LOCAL.but(length=2))
    now = spark.read.parquet(f"{walk.path}/step=2").select("start", "prev", F.col("vertex").alias("cur"), part_of("vertex", PARTS).alias("part"))
    need = spark.read.parquet(f"{walk.path}/step=2").select(part_of("vertex", PARTS).alias("part"), "prev", F.col("vertex").alias("cur")).select("part", F.explode(F.array("prev", "cur")).alias("vid")).distinct()
    lists = adjacency(edges).select("vid", "ids").join(need.withColumnRenamed("part", "at"), "vid").select("vid", "ids", F.col("at").alias("at"))

    def count(walkers: pa.Table, adj: pa.Table) -> pa.Table:
        ids = {v: np.asarray(x) for v, x in zip(adj.column("vid").to_pylist(), adj.column("ids").to_pylist(), strict=True)}
        n = [int(member(np.zeros(len(ids[c]), int), ids[c], np.zeros(len(ids[p]), int), ids[p]).sum()) for p, c in zip(walkers.column("prev").to_pylist(), walkers.column("cur").to_pylist(), strict=True)]
        return walkers.select(["start", "prev", "cur"]).append_column("n_common", pa.array(n, pa.int64()))

    return now.groupBy("part").cogroup(lists.groupBy("at")).applyInArrow(count, "start long, prev long, cur long, n_common long")


class BiasedWalk:
    """Table function: walks over the adjacency rows (vid, ids, ws) of one partition; for graphs that fit a worker."""

    def __init__(self):
        self.edges: list[tuple[int, int, int]] = []

    def eval(self, row):
        self.edges += [(row["vid"], x, w) for x, w in zip(row["ids"], row["ws"], strict=True)]

    def terminate(self):
        from ..walk.baselines import reference_walk

        for start, path in reference_walk(self.edges, P_LOCAL, sorted({u for u, _, _ in self.edges})).items():
            for step, vertex in enumerate(path):
                yield start, step, vertex


def register_sql(spark) -> None:
    """``biased_walk(TABLE(adjacency))``, ``walk_alpha(is_return, is_common, p, q)`` and ``walk_draw(seed, round, start, move)`` for SQL."""
    spark.udtf.register("biased_walk", F.udtf(BiasedWalk, returnType="start: long, step: int, vertex: long"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION walk_alpha(is_return BOOLEAN, is_common BOOLEAN, p DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN CASE WHEN is_return THEN 1 / p WHEN is_common THEN 1D ELSE 1 / q END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION walk_draw(seed BIGINT, r BIGINT, start BIGINT, move BIGINT) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat_ws(':', seed, r, start, move)), 1, 12), 16, 10) AS BIGINT)")


@registry(oracle.walk_sql("user", P_LOCAL, "SELECT start, CAST(step AS INT) AS step, cur AS vertex FROM walk"))
def udtf_walk(spark, sf_dir):
    register_sql(spark)
    adjacency(graph(spark, sf_dir)).select("vid", "ids", "ws").createOrReplaceTempView("adjacency")
    return spark.sql("SELECT * FROM biased_walk(TABLE(adjacency) WITH SINGLE PARTITION)")


def _sql_function(spark, sf_dir, of="true"):
    from ..walk.alpha import distance_class

    register_sql(spark)
    distance_class(graph(spark, sf_dir)).createOrReplaceTempView("classes")
    return spark.sql(f"SELECT u, v, x, w * walk_alpha(dist = 0, dist = 1, 0.5D, 2D) AS pi FROM classes WHERE {of}")


_PI = f"SELECT u, v, x, pi / {oracle.scale(P_LOCAL)}::DOUBLE AS pi FROM t"
registry.add("udf_sql_function", lambda s, d: _sql_function(s, d, "u <= 30"), oracle.transitions_sql("user", P_LOCAL, _PI + " WHERE u <= 30"))
registry.add("udf_sql_function_all", _sql_function, oracle.transitions_sql("user", P_LOCAL, _PI))


@registry("SELECT event_id AS start, CAST('0x' || substr(md5(concat_ws(':', 42, 0, event_id, 5)), 1, 12) AS BIGINT) AS draw FROM events")
def sql_draws(spark, sf_dir):
    register_sql(spark)
    table(spark, sf_dir, "events").createOrReplaceTempView("events")
    return spark.sql("SELECT event_id AS start, walk_draw(42, 0, event_id, 5) AS draw FROM events")
