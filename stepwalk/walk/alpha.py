"""The bias of a move and transition probabilities in relational form (small graphs, baselines and oracles)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import WalkParams


def alpha(prev: Column, x: Column, is_common: Column, p: float, q: float) -> Column:
    """1/p back to the last vertex, 1 to its neighbours, 1/q elsewhere; 1 where there is no last vertex."""
    return F.when(prev.isNull(), 1.0).when(x == prev, 1.0 / p).when(is_common, 1.0).otherwise(1.0 / q)


def distance_class(edges: DataFrame) -> DataFrame:
    """(u, v, x, w, dist): for each edge u-v and each neighbour x of v, 0 if x is u, 1 if u-x is an edge, else 2."""
    uv = edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    vx = edges.select(F.col("src").alias("v"), F.col("dst").alias("x"), "w")
    ux = edges.select(F.col("src").alias("u"), F.col("dst").alias("x"), F.lit(True).alias("common"))
    both = uv.join(vx, "v").join(ux, ["u", "x"], "left")
    return both.select("u", "v", "x", "w", F.when(F.col("x") == F.col("u"), 0).when(F.col("common"), 1).otherwise(2).alias("dist"))


def transition_weights(edges: DataFrame, params: WalkParams) -> DataFrame:
    """(u, v, x, w, dist, pi): unnormalised; pi is a whole number where p, q and the weights allow."""
    scaled = params.scaled()
    back, common, other = scaled or params.factors()
    factor = F.when(F.col("dist") == 0, F.lit(back)).when(F.col("dist") == 1, F.lit(common)).otherwise(F.lit(other))
    return distance_class(edges).withColumn("pi", F.col("w") * factor)


def transition_probs(edges: DataFrame, params: WalkParams) -> DataFrame:
    """(u, v, x, w, dist, pi, prob): normalised over the neighbours of v."""
    from .pairs import transition_rows

    return transition_rows(edges, params).select("u", "v", "x", "w", "dist", "pi", (F.col("pi") / F.col("total")).alias("prob"))
