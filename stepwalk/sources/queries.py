"""Round trips of edge lists and step logs through files."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..config import run_dir
from ..graph import model
from ..graph.build import SQL
from ..plans import oracle
from ..plans.shared import P_LOCAL, PARTS, Registry, graph, walked
from .edgelists import EDGE, read_csv, read_text, write_edges
from .tables import table

registry = Registry()


@registry("SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity > 45")
def src_parquet_prune(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45").select("l_partkey", "l_suppkey")


@registry(SQL["user"])
def src_csv_roundtrip(spark, sf_dir):
    path = run_dir(spark, "csv")
    write_edges(graph(spark, sf_dir), path, "csv")
    return read_csv(spark, path)[0]


@registry(SQL["user"])
def src_json_roundtrip(spark, sf_dir):
    path = run_dir(spark, "json")
    write_edges(graph(spark, sf_dir), path, "json")
    return spark.read.schema(EDGE).json(path)


@registry(SQL["user"])
def src_orc_roundtrip(spark, sf_dir):
    path = run_dir(spark, "orc")
    write_edges(graph(spark, sf_dir), path, "orc")
    return spark.read.schema(EDGE).orc(path)


@registry(SQL["user"])
def src_text_edgelist(spark, sf_dir):
    path = run_dir(spark, "text")
    write_edges(graph(spark, sf_dir), path, "text")
    return read_text(spark, path)[0]


@registry(oracle.walk_sql("user", P_LOCAL, "SELECT start, CAST(round AS INT) AS round, CAST(step AS INT) AS step, cur AS vertex FROM walk WHERE step = 3"))
def src_partitioned_log(spark, sf_dir):
    path = run_dir(spark, "log")
    walked(spark, sf_dir)[1].steps().write.partitionBy("round", "step").parquet(path)
    return spark.read.schema("start long, vertex long, round int, step int").parquet(path).where("step = 3").select("start", "round", "step", "vertex")


@registry(f"SELECT src AS vid, count(*) AS deg, CAST(sum(w) AS BIGINT) AS wsum FROM ({SQL['user']}) GROUP BY src")
def src_bucketed_adjacency(spark, sf_dir):
    return model.place(model.adjacency(graph(spark, sf_dir)), PARTS, "table").select("vid", "deg", "wsum")


@registry("SELECT CAST(l_orderkey AS VARCHAR) || ' x' AS row FROM lineitem WHERE l_orderkey % 1000 = 1")
def src_corrupt_rows(spark, sf_dir):
    path = run_dir(spark, "dirty")
    rows = table(spark, sf_dir, "lineitem")
    good = rows.select(F.concat_ws(" ", "l_partkey", "l_suppkey").alias("value"))
    bad = rows.where("l_orderkey % 1000 = 1").select(F.concat(F.col("l_orderkey").cast("string"), F.lit(" x")).alias("value"))
    good.unionByName(bad).write.text(path)
    return read_text(spark, path)[1]
