"""Baselines: walks over stored probabilities, and walks over a trimmed graph."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import WalkParams, batch_rows, run_dir, setting, written
from ..graph.stats import trim
from . import alias
from .alpha import transition_probs
from .kernel import pick
from .pairs import transition_lists
from .rng import draw48

LOG = "start long, round int, vertex long, prev long, step int"


def alias_tables(edges: DataFrame, params: WalkParams) -> DataFrame:
    """(u, v, ids, accept, alias) for every edge u-v: what stored-probability walks keep, 12 bytes a neighbour."""

    def build(us: np.ndarray, v: int, ids: np.ndarray, pi: np.ndarray) -> pa.RecordBatch:
        made = [alias.build(np.asarray(row, float)) for row in pi]
        ends = pa.array(np.arange(len(us) + 1) * len(ids), pa.int32())
        lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (np.tile(ids, len(us)), np.concatenate([a for a, _ in made]), np.concatenate([x for _, x in made]).astype(np.int32))]
        return pa.RecordBatch.from_arrays([pa.array(us), pa.array(np.full(len(us), v)), *lists], ["u", "v", "ids", "accept", "alias"])

    return transition_lists(edges, params, build, "u long, v long, ids array<long>, accept array<double>, alias array<int>")


def static_tables(edges: DataFrame) -> DataFrame:
    """(v, x, w, upto, total): running sums of weights, for first moves."""
    own = Window.partitionBy("src")
    rows = edges.withColumns({"upto": F.sum("w").over(own.orderBy("dst")), "total": F.sum("w").over(own)})
    return rows.select(F.col("src").alias("v"), F.col("dst").alias("x"), "w", "upto", "total")


def _moves(edges: DataFrame, params: WalkParams, starts: DataFrame | None, later, label: str, rewrite: bool) -> DataFrame:
    """The loop of both samplers.  ``later(now)`` gives (start, round, vertex, prev) after a biased move.

    ``rewrite`` keeps the paths in the walker rows and writes them all anew at every move, as the earlier solution does.
    """
    spark, path = edges.sparkSession, run_dir(edges.sparkSession, label)
    vids = starts.select("vid").distinct() if starts is not None else edges.select(F.col("src").alias("vid")).distinct()
    state = vids.select(F.col("vid").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(params.walks_per_vertex - 1))).alias("round"), F.col("vid").alias("vertex"), F.lit(None).cast("long").alias("prev"))
    if rewrite:
        state = state.withColumn("path", F.array("vertex"))
    static = static_tables(edges)
    schema = LOG.replace(", step int", "") + (", path array<long>" if rewrite else "")
    state.write.parquet(f"{path}/step=0")
    for move in range(1, params.length + 1):
        now = spark.read.schema(schema).parquet(f"{path}/step={move - 1}").withColumn("draw", draw48(params.seed, "round", "start", move, params.rng))
        if move == 1:
            target = F.col("draw") % F.col("total") if params.scaled() else F.col("draw") / F.lit(float(1 << 48)) * F.col("total")
            moved = now.join(static, F.col("vertex") == F.col("v")).where((target < F.col("upto")) & (target >= F.col("upto") - F.col("w")))
        else:
            moved = later(now)
        extra = [F.array_append("path", F.col("x")).alias("path")] if rewrite else []
        moved.select("start", "round", F.col("x").alias("vertex"), F.col("vertex").alias("prev"), *extra).write.parquet(f"{path}/step={move}")
    if rewrite:
        last = spark.read.schema(schema).parquet(f"{path}/step={params.length}")
        return last.select("start", "round", F.posexplode("path").alias("step", "vertex"))
    return spark.read.schema(LOG).parquet(path).select("start", "round", "step", "vertex")


def _laid_out(stored: DataFrame, label: str) -> DataFrame:
    """A table bucketed by v, so that a move shuffles walkers only; rows that are dealt by v already are not moved."""
    spark, path = stored.sparkSession, run_dir(stored.sparkSession, label)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    name = path.rsplit("/", 1)[1].replace("-", "_")
    stored.write.bucketBy(parts, "v").option("path", path).saveAsTable(name)
    return spark.table(name)


def _picked(batches):
    """Places drawn from stored masses."""
    for b in batches:
        ends = np.asarray(b.column("pi").offsets)
        mass = np.asarray(b.column("pi").values)[ends[0] : ends[-1]]
        at = pick(mass, np.diff(ends), np.asarray(b.column("draw"))) - (ends[:-1] - ends[0])
        yield pa.RecordBatch.from_arrays([b.column(c) for c in ("start", "round", "vertex", "prev")] + ([b.column("path")] if "path" in b.schema.names else []) + [pa.array(at.astype(np.int32))], [n for n in b.schema.names if n not in ("draw", "pi")] + ["k"])


def walk_precomputed(edges: DataFrame, params: WalkParams, sampler: str = "cdf", starts: DataFrame | None = None, rewrite: bool = False, most_bytes: int | None = None) -> DataFrame:
    """(start, round, step, vertex) over probabilities that are all stored first, a list for each edge walked over.

    ``cdf`` keeps the masses that running sums are made of and gives the same walks as drawing on demand; ``alias`` keeps alias tables.  With
    ``most_bytes`` a graph whose probabilities need more is refused.
    """
    if most_bytes is not None:
        need = edges.groupBy("src").count().agg(F.sum(8 * F.col("count") * F.col("count"))).first()[0] or 0
        if need > most_bytes:
            raise MemoryError(f"stored probabilities take {need} bytes, more than {most_bytes}")
    edges = written(edges, "edges")
    if sampler not in ("cdf", "alias"):
        raise ValueError("sampler is cdf or alias")
    near = _laid_out(edges.groupBy(F.col("src").alias("v")).agg(F.array_sort(F.collect_list("dst")).alias("ids")).repartition(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "v"), "near")
    if sampler == "cdf":
        whole = params.scaled() is not None and not edges.schema["w"].dataType.typeName() in ("double", "float")

        def masses(us: np.ndarray, v: int, ids: np.ndarray, pi: np.ndarray) -> pa.RecordBatch:
            ends = pa.array(np.arange(len(us) + 1) * len(ids), pa.int32())
            return pa.RecordBatch.from_arrays([pa.array(us), pa.array(np.full(len(us), v)), pa.ListArray.from_arrays(ends, pa.array(pi.ravel()))], ["u", "v", "pi"])

        stored = _laid_out(transition_lists(edges, params, masses, f"u long, v long, pi array<{'long' if whole else 'double'}>"), "stored")

        def later(now: DataFrame) -> DataFrame:
            met = now.join(stored, (F.col("prev") == F.col("u")) & (F.col("vertex") == F.col("v"))).select(*now.columns, "pi")
            kept = met.drop("draw", "pi")
            found = met.mapInArrow(_picked, kept.withColumn("k", F.lit(0)).schema)
            return found.join(near, F.col("vertex") == F.col("v")).withColumn("x", F.get("ids", F.col("k")))
    else:
        stored = _laid_out(alias_tables(edges, params).drop("ids"), "alias")
        size = F.size("ids")
        first = F.least((F.col("draw") / F.lit(float(1 << 48)) * size).cast("int"), size - 1)
        second = draw48(params.seed + 1, "round", "start", "draw") / F.lit(float(1 << 48))

        def later(now: DataFrame) -> DataFrame:
            met = now.join(stored, (F.col("prev") == F.col("u")) & (F.col("vertex") == F.col("v"))).drop("u", "v").join(near, F.col("vertex") == F.col("v")).withColumns({"k": first, "r": second})
            at = F.when(F.col("r") < F.get("accept", F.col("k")), F.col("k")).otherwise(F.get("alias", F.col("k")))
            return met.withColumn("x", F.get("ids", at))
    with setting(edges.sparkSession, "spark.sql.requireAllClusterKeysForCoPartition", "false"), batch_rows(edges.sparkSession, 4096):
        return _moves(edges, params, starts, later, "precomputed", rewrite)


def walk_trimmed(edges: DataFrame, params: WalkParams, k: int = 30, sampler: str = "cdf", starts: DataFrame | None = None, rewrite: bool = True) -> DataFrame:
    """Stored-probability walks over the ``k`` heaviest edges per vertex, paths rewritten at every move."""
    return walk_precomputed(trim(edges, k), params, sampler, starts, rewrite)


def first_order_walk(edges: DataFrame, params: WalkParams, starts: DataFrame | None = None) -> DataFrame:
    """Weighted walks without memory: no list is ever shipped."""
    from .engine import Engine

    engine = Engine.of_edges(edges)
    try:
        return engine.walk(params.but(p=1.0, q=1.0), starts=starts).steps()
    finally:
        engine.close()


def reference_walk(edges: list[tuple[int, int, int]], params: WalkParams, starts: list[int], round_: int = 0) -> dict[int, list[int]]:
    """Plain Python, whole factors: for tests."""
    from .rng import draws

    near: dict[int, list[tuple[int, int]]] = {}
    for u, v, w in sorted(edges):
        near.setdefault(u, []).append((v, w))
    ids = {u: {v for v, _ in n} for u, n in near.items()}
    back, common, other = params.scaled()
    out = {}
    for s in starts:
        path = [s]
        for draw in draws(params.seed, round_, s, range(1, params.length + 1)):
            options = near.get(path[-1], [])
            if not options:
                break
            prev = path[-2] if len(path) > 1 else None
            mass = [w * (1 if prev is None else back if x == prev else common if x in ids.get(prev, ()) else other) for x, w in options]
            r, upto = draw % sum(mass), 0
            for (x, _), m in zip(options, mass, strict=True):
                upto += m
                if upto > r:
                    path.append(x)
                    break
        out[s] = path
    return out


__all__ = ["alias_tables", "first_order_walk", "reference_walk", "static_tables", "transition_probs", "walk_precomputed", "walk_trimmed"]
