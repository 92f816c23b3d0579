"""Cost measures, derived from step logs and degrees: a walk is never run again, nor slowed, for them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph.model import part_of
from .graph.stats import bucket, degrees
from .walk.bounds import bound_high, bound_low


def moves(steps: DataFrame) -> DataFrame:
    """(start, round, step, prev, cur, next): each move with the vertex before it."""
    by = Window.partitionBy("start", "round").orderBy("step")
    rows = steps.select("start", "round", "step", F.col("vertex").alias("next"))
    rows = rows.withColumns({"cur": F.lag("next").over(by), "prev": F.lag("next", 2).over(by)})
    return rows.where("step > 0")


def message_curve(steps: DataFrame, edges: DataFrame) -> DataFrame:
    """(step, n_walkers, n_ids, bytes): lists that ``base`` sends after each move but the last: the neighbours of the vertex left."""
    last = steps.agg(F.max("step")).first()[0] or 0
    sent = moves(steps).where(F.col("step") < last).join(degrees(edges), F.col("cur") == F.col("vid"))
    return sent.groupBy("step").agg(F.count("*").alias("n_walkers"), F.sum("deg").alias("n_ids"), (8 * F.sum("deg")).alias("bytes"))


def base_memory(edges: DataFrame, walks: int, length: int) -> DataFrame:
    """One row of bytes: topology (8 an edge end), weights (8), vertex values (8 a step of every walk)."""
    n = degrees(edges).agg(F.count("*").alias("n"), F.sum("deg").alias("m"))
    return n.select((8 * F.col("m")).alias("topology"), (8 * F.col("m")).alias("weights"), (8 * F.col("n") * walks * (length + 1)).alias("vertex_values"))


def memory_breakdown(steps: DataFrame, edges: DataFrame, walks: int, length: int) -> DataFrame:
    """(step, base_bytes, message_bytes, message_share)."""
    base = base_memory(edges, walks, length).select((F.col("topology") + F.col("weights") + F.col("vertex_values")).alias("base_bytes"))
    rows = message_curve(steps, edges).select("step", F.col("bytes").alias("message_bytes")).join(F.broadcast(base))
    return rows.select("step", "base_bytes", "message_bytes", (F.col("message_bytes") / (F.col("base_bytes") + F.col("message_bytes"))).alias("message_share"))


def visit_frequency(steps: DataFrame, edges: DataFrame, width: int = 200) -> DataFrame:
    """(bucket, n_vertices, n_visits, mean_visits): visits after the start, by degree bucket; vertices never visited count."""
    visits = steps.where("step > 0").groupBy("vertex").agg(F.count("*").alias("n"))
    rows = degrees(edges).join(visits, F.col("vid") == F.col("vertex"), "left").withColumn("bucket", bucket(width))
    out = rows.groupBy("bucket").agg(F.count("*").alias("n_vertices"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_visits"))
    return out.withColumn("mean_visits", F.col("n_visits") / F.col("n_vertices"))


def local_saved(steps: DataFrame, edges: DataFrame, parts: int) -> DataFrame:
    """One row: moves that need a list next, how many stay in one partition, ids and local ids."""
    last = steps.agg(F.max("step")).first()[0] or 0
    rows = moves(steps).where(F.col("step") < last).join(degrees(edges), F.col("cur") == F.col("vid"))
    stays = part_of("cur", parts) == part_of("next", parts)
    return rows.agg(F.count("*").alias("n_moves"), F.sum(stays.cast("long")).alias("n_local"), F.sum("deg").alias("n_ids"), F.sum(F.when(stays, F.col("deg")).otherwise(0)).alias("local_ids"))


def cache_saved(steps: DataFrame, edges: DataFrame, popular: DataFrame, parts: int) -> DataFrame:
    """One row: moves that leave a popular vertex for another partition, first sends among them, ids sent with and without the cache."""
    last = steps.agg(F.max("step")).first()[0] or 0
    rows = moves(steps).where(F.col("step") < last).join(popular.select(F.col("vid").alias("cur")), "cur", "left_semi")
    rows = rows.where(part_of("cur", parts) != part_of("next", parts)).join(degrees(edges), F.col("cur") == F.col("vid"))
    first = Window.partitionBy("cur", part_of("next", parts)).orderBy("step", "start", "round")
    rows = rows.withColumn("n", F.row_number().over(first))
    return rows.agg(F.count("*").alias("n_refs"), F.coalesce(F.sum((F.col("n") == 1).cast("long")), F.lit(0)).alias("n_first"), F.coalesce(F.sum("deg"), F.lit(0)).alias("ids_without"), F.coalesce(F.sum(F.when(F.col("n") == 1, F.col("deg")).otherwise(0)), F.lit(0)).alias("ids_with"))


def approx_saved(steps: DataFrame, edges: DataFrame, popular: DataFrame, params, eps: float, parts: int) -> DataFrame:
    """One row: moves after which the next draw is static (from another vertex to a popular one, tight bounds), and the ids not sent for them."""
    last = steps.agg(F.max("step")).first()[0] or 0
    per = edges.groupBy("src").agg(F.count("*").alias("deg"), F.min("w").alias("wmin"), F.max("w").alias("wmax"))
    hot = popular.select(F.col("vid").alias("next")).join(per, F.col("next") == F.col("src")).select("next", F.col("deg").alias("d_v"), "wmin", "wmax")
    rows = moves(steps).where(F.col("step") < last).join(popular.select(F.col("vid").alias("cur")), "cur", "left_anti").join(hot, "next")
    rows = rows.join(degrees(edges), F.col("cur") == F.col("vid"))
    gap = bound_high(F.col("deg"), F.col("d_v"), F.col("wmin"), F.col("wmax"), params.p, params.q) - bound_low(F.col("deg"), F.col("d_v"), F.col("wmin"), F.col("wmax"), params.p, params.q)
    remote = part_of("cur", parts) != part_of("next", parts)
    tight = rows.where(gap < eps)
    return tight.agg(F.count("*").alias("n_static"), F.coalesce(F.sum(F.when(remote, F.col("deg")).otherwise(0)), F.lit(0)).alias("ids"))


def approx_rate(log: DataFrame) -> DataFrame:
    """One row: biased moves drawn, and those drawn statically; a message with route ``static`` makes the next draw static."""
    last = log.agg(F.max("step")).first()[0] or 0
    return log.where((F.col("step") > 0) & (F.col("step") < last)).agg(F.count("*").alias("n_moves"), F.sum((F.col("route") == "static").cast("long")).alias("n_static"))


def switch_supersteps(steps: DataFrame, popular: DataFrame) -> DataFrame:
    """(start, round, moves, supersteps): a move that leaves a popular vertex for another kind costs one superstep more."""
    last = steps.agg(F.max("step")).first()[0] or 0
    hot = popular.select("vid")
    rows = moves(steps).join(hot.select(F.col("vid").alias("cur"), F.lit(1).alias("from_hot")), "cur", "left").join(hot.select(F.col("vid").alias("next"), F.lit(1).alias("to_hot")), "next", "left")
    asked = (F.col("from_hot").isNotNull() & F.col("to_hot").isNull() & (F.col("step") < last)).cast("long")
    return rows.groupBy("start", "round").agg(F.count("*").alias("moves"), (F.count("*") + F.sum(asked)).alias("supersteps"))


def speedup(cost: DataFrame, against: str) -> DataFrame:
    """(graph, variant, ratio): seconds of ``against`` over seconds of the variant; ``cost`` is (graph, variant, seconds)."""
    base = cost.where(F.col("variant") == against).select("graph", F.col("seconds").alias("base"))
    return cost.join(base, "graph").select("graph", "variant", (F.col("base") / F.col("seconds")).alias("ratio"))


def stage_breakdown(cost: DataFrame) -> DataFrame:
    """(graph, stage, share) of (graph, stage, seconds)."""
    return cost.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("graph"))).select("graph", "stage", "share")


def scaling_fit(cost: DataFrame) -> DataFrame:
    """One row: the slope of log seconds over log n; 1 is linear."""
    return cost.agg(F.regr_slope(F.log("seconds"), F.log("n")).alias("slope"))


def feasible(edges: DataFrame, variant: str, budget: int) -> bool:
    """Whether the memory that a variant must hold fits: all probabilities, or one superstep's lists and the graph."""
    d = degrees(edges).agg(F.sum(F.col("deg") * F.col("deg")).alias("sq"), F.count("*").alias("n"), F.sum("deg").alias("m")).first()
    if variant in ("precomputed", "trimmed"):
        return 8 * (d.sq or 0) <= budget
    return 16 * (d.m or 0) + 8 * d.n * (d.sq or 0) / max(1, d.m or 0) <= budget
