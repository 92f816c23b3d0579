"""Connected components of link frames by alternating neighbour contraction (no links ever reach the driver)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .tables import written


def components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that a link joins to another one; root is the smallest node of its component.

    Alternates two steps until nothing changes: every node hands its larger neighbours to its smallest one, then every
    node hands all its smaller neighbours to the smallest of them.  Aggregates are ``min`` only, so a hub is combined
    map-side, and each round is a written table: a lost executor costs at most one round.  Self links and repeated
    links are ignored; an empty frame gives an empty result.
    """
    edges = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    edges, before = _noted(edges, "links")
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.unionByName(low.where("m < u").select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v")
        edges, state = _noted(small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
        if state == before:
            break
        before = state
    else:
        raise RuntimeError("components did not settle")
    roots = edges.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def _noted(edges: DataFrame, label: str) -> tuple[DataFrame, tuple]:
    """The written edges and what tells them from another round's: their number and the sum of their hashes, from the write itself."""
    seen = Observation()
    total = F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))
    table = written(edges.observe(seen, F.count(F.lit(1)).alias("n"), total.alias("total")), label)
    return table, (seen.get["n"], seen.get["total"])


def joined_components(roots: DataFrame, more: DataFrame) -> DataFrame:
    """``roots`` (node, root) of links already joined, with those of further links (a, b): only roots are contracted again."""
    of = lambda name: roots.select(F.col("node").alias(f"_{name}"), F.col("root").alias(f"_root_{name}"))
    moved = more.select("a", "b")
    for name in ("a", "b"):
        moved = moved.join(of(name), F.col(name) == F.col(f"_{name}"), "left").withColumn(name, F.coalesce(f"_root_{name}", name)).drop(f"_{name}", f"_root_{name}")
    upper = written(components(moved), "upper").withColumnsRenamed({"node": "_node", "root": "_top"})
    old = roots.join(upper, F.col("root") == F.col("_node"), "left").select("node", F.coalesce("_top", "root").alias("root"))
    new = upper.join(roots, F.col("_node") == F.col("node"), "left_anti").select(F.col("_node").alias("node"), F.col("_top").alias("root"))
    return old.unionByName(new)
