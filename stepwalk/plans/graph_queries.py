"""Queries on graphs, synthetic graphs, transition probabilities and bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import model, stats, synth
from ..graph.build import GRAPHS, SQL
from ..sources.tables import table
from ..walk import alias, alpha
from ..walk.baselines import alias_tables
from ..walk.bounds import bound_high, bound_low
from . import oracle
from .shared import P_FAR, P_LOCAL, PARTS, Registry, graph

registry = Registry()


def with_edges(name: str, select: str) -> str:
    return f"WITH {oracle.edges_cte(name)}, {oracle.DEG}, {oracle.popular_cte()} {select}"


for _name, _build in GRAPHS.items():
    registry.add(f"graph_{_name}_edges", _build, SQL[_name])


@registry(f"""WITH l AS (SELECT l_partkey + 2000000000000 AS a, l_suppkey + 3000000000000 AS b, count(*) AS w FROM lineitem WHERE l_shipdate < TIMESTAMP '1997-01-01' GROUP BY 1, 2)
SELECT a AS src, b AS dst, w FROM l UNION ALL SELECT b, a, w FROM l""")
def graph_symmetric_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").where("l_shipdate < TIMESTAMP '1997-01-01'").select((F.col("l_partkey") + 2 * 10**12).alias("src"), (F.col("l_suppkey") + 3 * 10**12).alias("dst"), F.lit(1).cast("long").alias("w"))
    return model.normalize(rows)


@registry(with_edges("entity", "SELECT vid, deg FROM deg"))
def graph_degrees(spark, sf_dir):
    return stats.degrees(graph(spark, sf_dir, "entity"))


@registry(with_edges("entity", "SELECT count(*) AS n_vertices, CAST(sum(deg) AS BIGINT) AS n_edges, max(deg) AS max_deg, avg(deg) AS avg_deg, quantile_cont(deg, 0.5) AS median_deg, max(deg) / avg(deg) AS max_over_avg FROM deg"))
def graph_degree_summary(spark, sf_dir):
    return stats.degree_summary(graph(spark, sf_dir, "entity"))


@registry(with_edges("docword", "SELECT deg, count(*) AS n_vertices FROM deg GROUP BY deg"))
def graph_degree_histogram(spark, sf_dir):
    return stats.degree_histogram(graph(spark, sf_dir, "docword"))


@registry(with_edges("entity", "SELECT CAST(ceil(deg / 200) * 200 AS BIGINT) AS bucket, count(*) AS n_vertices FROM deg GROUP BY 1"))
def graph_degree_buckets(spark, sf_dir):
    return stats.degree_buckets(graph(spark, sf_dir, "entity"))


@registry(f"WITH {oracle.edges_cte('user')} SELECT src AS vid, CAST((row_number() OVER (PARTITION BY src ORDER BY dst) - 1) // 16 AS INT) AS chunk, dst AS id, w FROM edges")
def graph_adjacency(spark, sf_dir):
    rows = model.adjacency(graph(spark, sf_dir), chunk=16)
    return rows.select("vid", "chunk", F.explode(F.arrays_zip("ids", "ws")).alias("e")).select("vid", "chunk", F.col("e.ids").alias("id"), F.col("e.ws").alias("w"))


@registry(with_edges("entity", "SELECT pop.vid, deg FROM pop JOIN deg USING (vid)"))
def graph_popular(spark, sf_dir):
    return stats.popular(graph(spark, sf_dir, "entity"), share=0.05)


@registry(with_edges("entity", f"SELECT CAST({oracle.PART.format('vid', PARTS)} AS INT) AS part, count(*) AS n_vertices, CAST(sum(deg) AS BIGINT) AS n_edges FROM deg GROUP BY 1"))
def graph_partition_sizes(spark, sf_dir):
    return stats.partition_sizes(graph(spark, sf_dir, "entity"), PARTS)


@registry(with_edges("user", "SELECT a.src, a.dst, count(c.src) AS n_common FROM edges a LEFT JOIN edges b ON b.src = a.src LEFT JOIN edges c ON c.src = a.dst AND c.dst = b.dst GROUP BY 1, 2"))
def graph_common_neighbors(spark, sf_dir):
    return stats.common_neighbors(graph(spark, sf_dir))


@registry(with_edges("user", "SELECT count(*) AS n_triangles FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = a.src AND c.dst = b.dst WHERE a.src < a.dst AND a.dst < b.dst"))
def graph_triangles(spark, sf_dir):
    return stats.triangles(graph(spark, sf_dir))


_PAIRS = "SELECT o_custkey AS src, 1000000 + (o_orderkey // 64) AS dst, 1::BIGINT AS w FROM orders WHERE o_totalprice > 300000"


@registry(f"""WITH RECURSIVE p AS ({_PAIRS}), e AS (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM p UNION ALL SELECT dst, src FROM p)),
r(vid, seen) AS (SELECT DISTINCT src, src FROM e UNION SELECT r.vid, e.dst FROM r JOIN e ON e.src = r.seen) SELECT vid, min(seen) AS root FROM r GROUP BY vid""")
def graph_components(spark, sf_dir):
    rows = table(spark, sf_dir, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("src"), (F.expr("o_orderkey div 64") + 1000000).alias("dst"), F.lit(1).cast("long").alias("w"))
    return stats.components(rows)


def _asymmetry(name, of):
    def query(spark, sf_dir):
        rows = table(spark, sf_dir, "lineitem").where(of).groupBy(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst")).agg(F.count("*").alias("w"))
        return model.asymmetric(rows)

    registry.add(name, query, f"""WITH e AS (SELECT l_partkey AS src, l_suppkey AS dst, count(*) AS w FROM lineitem WHERE {of} GROUP BY 1, 2)
SELECT src, dst, w FROM e WHERE NOT EXISTS (SELECT 1 FROM e b WHERE b.src = e.dst AND b.dst = e.src AND b.w = e.w)""")


_asymmetry("graph_asymmetry", "l_partkey <= 100 AND l_suppkey <= 100")
_asymmetry("graph_asymmetry_all", "true")

@registry(" UNION ALL ".join(f"SELECT '{g}' AS graph, CAST(8 * sum(d * d) AS BIGINT) AS bytes, 8.0 * sum(d) * sum(d) / count(*) AS floor_bytes, count(*) AS n, CAST(sum(d) AS BIGINT) AS n_edges FROM (SELECT count(*) AS d FROM ({SQL[g]}) GROUP BY src)" for g in ("user", "copart", "supply", "entity", "doc")))
def graph_prob_memory(spark, sf_dir):
    out = None
    for name in ("user", "copart", "supply", "entity", "doc"):
        row = stats.prob_memory(graph(spark, sf_dir, name)).withColumn("graph", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@registry(oracle.trimmed_sql("copart", 30))
def graph_trim30(spark, sf_dir):
    return stats.trim(graph(spark, sf_dir, "copart"))


@registry(f"WITH t AS MATERIALIZED ({oracle.trimmed_sql('copart', 30)}) SELECT t.src, t.dst, t.w FROM t JOIN t b ON b.src = t.dst AND b.dst = t.src")
def graph_trim30_symmetric(spark, sf_dir):
    return stats.trim(graph(spark, sf_dir, "copart"), symmetric=True)


@registry(with_edges("entity", "SELECT deg, count(*) AS n_vertices, least(30, deg) / deg AS retained FROM deg GROUP BY deg"))
def graph_trim_retention(spark, sf_dir):
    return stats.trim_retention(graph(spark, sf_dir, "entity"))


@registry(with_edges("user", "SELECT src, dst, w FROM edges WHERE src <= 40 AND dst <= 40"))
def graph_induced(spark, sf_dir):
    edges = graph(spark, sf_dir)
    return model.induced(edges, edges.where("src <= 40").select(F.col("src").alias("vid")))


@registry(with_edges("entity", "SELECT CAST(sum(deg * deg) AS DOUBLE) / sum(deg) AS plateau FROM deg"))
def graph_plateau(spark, sf_dir):
    return spark.range(1).select(F.lit(stats.plateau(graph(spark, sf_dir, "entity"))).alias("plateau"))


@registry(with_edges("entity", "SELECT CASE WHEN 8 * sum(deg * deg) <= 100000000 THEN 'precompute' ELSE 'on_demand' END AS choice FROM deg"))
def graph_plan_storage(spark, sf_dir):
    return spark.range(1).select(F.lit(stats.plan_storage(graph(spark, sf_dir, "entity"), 100_000_000)).alias("choice"))


@registry(oracle.transitions_sql("user", P_LOCAL, "SELECT u, v, x, w, CAST(dist AS INT) AS dist FROM t"))
def trans_distance_class(spark, sf_dir):
    return alpha.distance_class(graph(spark, sf_dir))


@registry(oracle.transitions_sql("user", P_FAR, "SELECT u, v, x, w, CAST(dist AS INT) AS dist, CAST(pi AS BIGINT) AS pi FROM t"))
def trans_unnormalized(spark, sf_dir):
    return alpha.transition_weights(graph(spark, sf_dir), P_FAR)


@registry(oracle.transitions_sql("user", P_LOCAL, "SELECT u, v, x, round(pi / total, 9) AS prob FROM t"))
def trans_probabilities(spark, sf_dir):
    return alpha.transition_probs(graph(spark, sf_dir), P_LOCAL).select("u", "v", "x", F.round("prob", 9).alias("prob"))


@registry(oracle.transitions_sql("user", P_LOCAL, "SELECT u, v, x, round(pi / total, 9) AS prob FROM t"))
def trans_alias(spark, sf_dir):
    """What alias tables draw, neighbour by neighbour: the exact probabilities again."""
    import numpy as np
    import pyarrow as pa

    def again(batches):
        for b in batches:
            made = [alias.probabilities(np.asarray(a), np.asarray(x)) for a, x in zip(b.column("accept").to_pylist(), b.column("alias").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("u"), b.column("v"), b.column("ids"), pa.array(made, pa.list_(pa.float64()))], ["u", "v", "ids", "prob"])

    rows = alias_tables(graph(spark, sf_dir), P_LOCAL).mapInArrow(again, "u long, v long, ids array<long>, prob array<double>")
    return rows.select("u", "v", F.explode(F.arrays_zip("ids", "prob")).alias("e")).select("u", "v", F.col("e.ids").alias("x"), F.round("e.prob", 9).alias("prob"))


def _bounded(spark, sf_dir, p, q, name="entity", form="tight"):
    edges = graph(spark, sf_dir, name)
    d = edges.groupBy("src").agg(F.count("*").alias("deg"), F.min("w").alias("wmin"), F.max("w").alias("wmax"))
    uv = edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).join(d.select(F.col("src").alias("u"), F.col("deg").alias("du")), "u")
    uv = uv.join(d.select(F.col("src").alias("v"), F.col("deg").alias("dv"), "wmin", "wmax"), "v")
    args = [F.col(c) for c in ("du", "dv", "wmin", "wmax")]
    return uv.select("u", "v", bound_low(*args, p, q, form).alias("low"), bound_high(*args, p, q, form).alias("high"))


def _bounded_sql(p, q, select, form="tight", name="entity"):
    low, high = oracle.bounds_sql("a.deg", "b.deg", "b.wmin", "b.wmax", p, q, form)
    return with_edges(name, f"SELECT {select} FROM (SELECT src AS u, dst AS v, {low} AS low, {high} AS high FROM edges JOIN deg a ON a.vid = src JOIN deg b ON b.vid = dst)")


@registry(_bounded_sql(2.0, 0.5, "u, v, round(low, 12) AS low, round(high, 12) AS high"))
def bounds_low_high(spark, sf_dir):
    return _bounded(spark, sf_dir, 2.0, 0.5).select("u", "v", F.round("low", 12).alias("low"), F.round("high", 12).alias("high"))


@registry(_bounded_sql(2.0, 0.5, "u, v, round(low, 12) AS low, round(high, 12) AS high", "loose"))
def bounds_loose(spark, sf_dir):
    return _bounded(spark, sf_dir, 2.0, 0.5, form="loose").select("u", "v", F.round("low", 12).alias("low"), F.round("high", 12).alias("high"))


@registry(_bounded_sql(0.5, 2.0, "u, v, round(high - low, 12) AS gap"))
def bounds_gap(spark, sf_dir):
    return _bounded(spark, sf_dir, 0.5, 2.0).select("u", "v", F.round(F.col("high") - F.col("low"), 12).alias("gap"))


@registry(_bounded_sql(0.5, 2.0, "eps, count(*) FILTER (high - low < eps) AS n_pairs", name="docword") + ", (SELECT unnest([1e-4, 1e-3, 1e-2]) AS eps) GROUP BY eps")
def bounds_trigger(spark, sf_dir):
    rows = _bounded(spark, sf_dir, 0.5, 2.0, "docword").withColumn("eps", F.explode(F.array(F.lit(1e-4), F.lit(1e-3), F.lit(1e-2))))
    return rows.groupBy("eps").agg(F.count(F.when(F.col("high") - F.col("low") < F.col("eps"), 1)).alias("n_pairs"))


def _synthetic(name: str, spec: synth.Matrix) -> None:
    """One drawn edge for each event; the vertices grow with the events."""

    def query(spark, sf_dir):
        ids = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"))
        return stats.degree_histogram(synth.rmat(spark, spec.fitted(ids.count()), ids=ids))

    edges = synth.rmat_table_sql(spec, "SELECT event_id AS id FROM events")
    registry.add(name, query, f"SELECT deg, count(*) AS n_vertices FROM (SELECT src, count(*) AS deg FROM ({edges}) GROUP BY src) GROUP BY deg")


_synthetic("synth_er_degrees", synth.er(10))
_synthetic("synth_wec_degrees", synth.wec(8))
for _s in (1.0, 2.0, 3.0, 4.0, 5.0):
    _synthetic(f"synth_skew{_s:.0f}_degrees", synth.skew(8, _s, 40))


@registry()
def synth_planted_edges(spark, sf_dir):
    """Planted communities among the customers: every 200 keys are one graph."""
    return synth.planted(spark, n=200, groups=4, vertices=table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("vid")))[0]
