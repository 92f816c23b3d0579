"""Figures of a graph: degrees, popular vertices, memory of stored probabilities, common neighbours, components."""

from __future__ import annotations

from math import ceil

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import written
from .model import part_of


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))


def degree_summary(edges: DataFrame) -> DataFrame:
    """One row: vertices, directed edges, largest, mean and median degree, largest over mean."""
    d = degrees(edges).agg(F.count("*").alias("n_vertices"), F.sum("deg").alias("n_edges"), F.max("deg").alias("max_deg"), F.avg("deg").alias("avg_deg"), F.expr("percentile(deg, 0.5)").alias("median_deg"))
    return d.withColumn("max_over_avg", F.col("max_deg") / F.col("avg_deg"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("deg").agg(F.count("*").alias("n_vertices"))


def bucket(width: int, of: str = "deg"):
    """Upper end of the bucket (end - width, end]."""
    return (F.ceil(F.col(of) / width) * width).cast("long")


def degree_buckets(edges: DataFrame, width: int = 200) -> DataFrame:
    return degrees(edges).groupBy(bucket(width).alias("bucket")).agg(F.count("*").alias("n_vertices"))


def prob_memory(edges: DataFrame) -> DataFrame:
    """One row: bytes of all second-order probabilities at 8 each, and the floor 8*n*d^2 of a graph with this mean degree."""
    d = degrees(edges).agg(F.sum(F.col("deg") * F.col("deg")).alias("sq"), F.count("*").alias("n"), F.sum("deg").alias("m"))
    return d.select((8 * F.col("sq")).alias("bytes"), (8.0 * F.col("m") * F.col("m") / F.col("n")).alias("floor_bytes"), "n", F.col("m").alias("n_edges"))


def prob_memory_floor(n: float, d: float) -> float:
    return 8.0 * n * d * d


def plateau(edges: DataFrame) -> float:
    """Ids that a walker meets in the long run where the walk is unbiased: the size-biased mean degree."""
    r = degrees(edges).agg(F.sum(F.col("deg") * F.col("deg")).alias("a"), F.sum("deg").alias("b")).first()
    return float(r.a or 0) / max(1, r.b or 0)


def plan_storage(edges: DataFrame, memory_bytes: int) -> str:
    """``precompute`` where all probabilities fit the memory, else ``on_demand``."""
    return "precompute" if (prob_memory(edges).first().bytes or 0) <= memory_bytes else "on_demand"


def popular(edges: DataFrame, degree: int | None = None, share: float | None = None, hot_bytes: int | None = None) -> DataFrame:
    """(vid, deg) of popular vertices: at least ``degree``, or the top ``share`` by degree, or as many of the top as ``hot_bytes`` of lists hold.

    A budget is spent in two steps, so that no task ranks all vertices: whole degrees from the top while they fit, then
    ids within the first degree that does not.
    """
    d = degrees(edges)
    if degree is not None:
        return d.where(F.col("deg") >= degree)
    d = written(d, "degrees")  # counted once: it is read four times below
    if share is not None:
        budget, cost = ceil(share * d.count()), F.lit(1)
    elif hot_bytes is not None:
        budget, cost = hot_bytes, 8 * F.col("deg")
    else:
        raise ValueError("give a degree, a share or a budget")
    per = d.groupBy("deg").agg(F.sum(cost).cast("long").alias("cost"), F.first(cost).cast("long").alias("each"))
    per = per.withColumn("upto", F.sum("cost").over(Window.orderBy(F.desc("deg"))))
    edge = per.where(F.col("upto") > budget).orderBy(F.desc("deg")).first()
    if edge is None:
        return d
    left = int((budget - (edge.upto - edge.cost)) // edge.each)
    return d.where(F.col("deg") > edge.deg).unionByName(d.where(F.col("deg") == edge.deg).orderBy("vid").limit(max(0, left)))


def partition_sizes(edges: DataFrame, parts: int) -> DataFrame:
    return degrees(edges).groupBy(part_of("vid", parts).alias("part")).agg(F.count("*").alias("n_vertices"), F.sum("deg").alias("n_edges"))


def common_neighbors(edges: DataFrame) -> DataFrame:
    """(src, dst, n_common) of every edge; 0 where there is none."""
    first = edges.select("src", "dst")
    uv = first.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    ux = first.select(F.col("src").alias("u"), F.col("dst").alias("x"))
    vx = first.select(F.col("src").alias("v"), F.col("dst").alias("x"), F.lit(1).alias("hit"))
    both = uv.join(ux, "u").join(vx, ["v", "x"])
    counted = both.groupBy(F.col("u").alias("src"), F.col("v").alias("dst")).agg(F.count("*").alias("n"))
    return first.join(counted, ["src", "dst"], "left").select("src", "dst", F.coalesce("n", F.lit(0)).alias("n_common"))


def triangles(edges: DataFrame) -> DataFrame:
    """One row: the number of triangles, each edge directed from the lower to the higher (degree, id) end, so no hub's pairs are made."""
    d = degrees(edges)
    a, b = d.select(F.col("vid").alias("src"), F.col("deg").alias("da")), d.select(F.col("vid").alias("dst"), F.col("deg").alias("db"))
    up = edges.join(a, "src").join(b, "dst").where("da < db OR (da = db AND src < dst)").select("src", "dst")
    up = written(up, "oriented")
    first, second = up.toDF("x", "y"), up.toDF("x", "z")
    third = up.select(F.col("src").alias("y"), F.col("dst").alias("z"))
    return first.join(second, "x").where("y <> z").join(third, ["y", "z"]).agg(F.count("*").alias("n_triangles"))


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """(vid, root): the smallest vertex that can be reached, edges taken both ways; labels halve their distance by pointer jumps."""
    both = edges.select("src", "dst").union(edges.select("dst", "src")).distinct()
    label = written(both.select(F.col("src").alias("vid")).distinct().withColumn("root", F.col("vid")), "labels")
    for _ in range(max_rounds):
        near = both.join(label, both.dst == label.vid).groupBy(F.col("src").alias("v")).agg(F.min("root").alias("low"))
        step = label.join(near, label.vid == near.v, "left").select("vid", F.least("root", F.coalesce("low", "root")).alias("root"), F.col("root").alias("old"))
        jump = label.select(F.col("vid").alias("r"), F.col("root").alias("rr"))
        new = written(step.join(jump, step.root == jump.r, "left").select("vid", F.least("root", F.coalesce("rr", "root")).alias("root"), "old"), "labels")
        label = new.select("vid", "root")
        if new.where("root <> old").isEmpty():
            return label
    raise RuntimeError("components did not settle")


def trim(edges: DataFrame, k: int = 30, symmetric: bool = False) -> DataFrame:
    """The ``k`` heaviest out-edges of every vertex, ties by id; with ``symmetric``, edges that both ends keep."""
    order = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    kept = edges.withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= k).drop("_n")
    if symmetric:
        kept = kept.join(kept.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_semi")
    return kept.select("src", "dst", "w")


def trim_retention(edges: DataFrame, k: int = 30) -> DataFrame:
    """(deg, n_vertices, retained): the share of edges that vertices of a degree keep."""
    return degree_histogram(edges).select("deg", "n_vertices", (F.least(F.lit(k), F.col("deg")) / F.col("deg")).alias("retained"))
