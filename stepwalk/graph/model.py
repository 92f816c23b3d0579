"""Edge frames and adjacency frames.

An edge frame is (src LONG, dst LONG, w LONG or DOUBLE > 0), with both directions of an undirected edge.  An adjacency frame
has a row per vertex (or per chunk of a vertex with very many neighbours): vid, chunk, deg, wsum, wmin, wmax, ids, ws; the
two arrays run by neighbour id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import run_dir


def check_edges(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(valid rows, quarantined rows with a reason): null ids, weights that are null, not positive or not a number."""
    w = F.col("w").cast("double")
    reason = F.when(F.col("src").isNull() | F.col("dst").isNull(), "null id").when(w.isNull() | F.isnan(w), "no weight").when(w <= 0, "weight not positive").when(w == float("inf"), "weight not finite")
    marked = edges.withColumn("reason", reason)
    return marked.where("reason IS NULL").drop("reason"), marked.where("reason IS NOT NULL")


def normalize(edges: DataFrame, directed: bool = False, keep_loops: bool = False, unit: bool = False) -> DataFrame:
    """Valid edges, loops dropped, both directions unless ``directed``, parallel edges summed (or all weights 1).

    An undirected input gives each edge once in either direction, or both ways with the weight in either row, which sums.
    """
    good, _ = check_edges(edges.select("src", "dst", "w"))
    good = good if keep_loops else good.where("src <> dst")
    if not directed:
        good = good.unionByName(good.where("src <> dst").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    if unit:
        return good.select("src", "dst").distinct().withColumn("w", F.lit(1).cast("long"))
    return good.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def asymmetric(edges: DataFrame) -> DataFrame:
    """Edges whose opposite is missing or has another weight."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return edges.join(back, ["src", "dst", "w"], "left_anti")


def part_of(vertex: str | Column, parts: int) -> Column:
    """The partition of a vertex: the same arithmetic in SQL, in Arrow kernels and in the oracle."""
    v = F.col(vertex) if isinstance(vertex, str) else vertex
    return F.pmod(v.bitwiseXOR(F.shiftright(v, 16)), F.lit(parts)).cast("int")


def adjacency(edges: DataFrame, chunk: int | None = None) -> DataFrame:
    """One row per vertex with out-edges; with ``chunk``, one row per ``chunk`` neighbours, so that no row outgrows memory."""
    if chunk:
        order = Window.partitionBy("src").orderBy("dst")
        edges = edges.withColumn("chunk", F.floor((F.row_number().over(order) - 1) / chunk).cast("int"))
    else:
        edges = edges.withColumn("chunk", F.lit(0))
    grouped = edges.groupBy(F.col("src").alias("vid"), "chunk").agg(
        F.count("*").alias("deg"), F.sum("w").alias("wsum"), F.min("w").alias("wmin"), F.max("w").alias("wmax"), F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("nbrs")
    )
    return grouped.select("vid", "chunk", "deg", "wsum", "wmin", "wmax", F.col("nbrs.dst").alias("ids"), F.col("nbrs.w").alias("ws"))


def place(adj: DataFrame, parts: int, keep: str = "memory") -> DataFrame:
    """The adjacency laid out by vertex partition, once.

    ``memory`` persists (recomputed from its source after a loss); ``table`` writes a bucketed table, for graphs beyond
    memory; joins on (part, vid) then shuffle walkers only.
    """
    placed = adj.withColumn("part", part_of("vid", parts))
    if keep == "table":
        name = "adjacency_" + run_dir(adj.sparkSession, "a").rsplit("-", 1)[1]
        placed.repartition(parts, "vid").write.bucketBy(parts, "vid").sortBy("vid").saveAsTable(name)
        return adj.sparkSession.table(name)
    return placed.repartition(parts, "vid").persist()


def unchunked(adj: DataFrame) -> DataFrame:
    """Edges again."""
    return adj.select("vid", F.explode(F.arrays_zip("ids", "ws")).alias("e")).select(F.col("vid").alias("src"), F.col("e.ids").alias("dst"), F.col("e.ws").alias("w"))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges between the given vertices (vid)."""
    left = vertices.select(F.col("vid").alias("src")).distinct()
    right = vertices.select(F.col("vid").alias("dst")).distinct()
    return edges.join(left, "src", "left_semi").join(right, "dst", "left_semi").select("src", "dst", "w")
