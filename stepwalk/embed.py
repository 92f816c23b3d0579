"""From walks to vectors: sentences, context pairs, skip-gram."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import Word2Vec
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .config import written
from .walk.engine import paths_of


def walk_sentences(steps: DataFrame) -> DataFrame:
    """(start, round, path): vertices as words."""
    return paths_of(steps).select("start", "round", F.col("path").cast("array<string>").alias("path"))


def context_pairs(steps: DataFrame, window: int = 5) -> DataFrame:
    """(center, context) for every two vertices of one walk at most ``window`` moves apart."""
    a = steps.select("start", "round", "step", F.col("vertex").alias("center"))
    a = a.withColumn("other", F.explode(F.sequence(F.col("step") - window, F.col("step") + window))).where("other <> step AND other >= 0")
    b = steps.select("start", "round", F.col("step").alias("other"), F.col("vertex").alias("context"))
    return a.join(b, ["start", "round", "other"]).select("center", "context")


def embed(steps: DataFrame, dim: int = 64, window: int = 5, epochs: int = 1, engine: str = "mllib", seed: int = 42, **options) -> DataFrame:
    """(vid, vec).  ``mllib`` keeps the vocabulary and model on the driver; ``blocks`` trains vertex blocks in tasks."""
    if engine == "blocks":
        return embed_blocks(steps, dim, window, epochs, seed=seed, **options)
    model = Word2Vec(vectorSize=dim, windowSize=window, maxIter=epochs, minCount=0, seed=seed, numPartitions=1, inputCol="path", outputCol="v", **options).fit(walk_sentences(steps))
    return model.getVectors().select(F.col("word").cast("long").alias("vid"), vector_to_array("vector", "float32").alias("vec"))


def embed_blocks(steps: DataFrame, dim: int = 64, window: int = 5, epochs: int = 2, blocks: int = 2, negatives: int = 5, rate: float = 0.05, seed: int = 42) -> DataFrame:
    """Negative-sampling skip-gram where no task holds more than two blocks of vertices.

    Pairs are dealt to a grid (block of center, block of context).  An epoch runs ``blocks`` rounds; in round r the cells
    (i, i + r) touch disjoint blocks, so they train side by side.  Vectors are tables between rounds.
    """
    spark = steps.sparkSession
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")
    pairs = written(context_pairs(steps, window).withColumns({"bi": block("center"), "bj": block("context")}), "pairs")
    vids = steps.select(F.col("vertex").alias("vid")).distinct()

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [np.random.default_rng([seed, int(v) & 0x7FFFFFFF]).normal(0, 0.5 / dim**0.5, dim) for v in b.column("vid").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("vid"), pa.array(rows, pa.list_(pa.float64())), pa.array([[0.0] * dim] * len(rows), pa.list_(pa.float64()))], ["vid", "x", "y"])

    state = written(vids.mapInArrow(first, "vid long, x array<double>, y array<double>").withColumn("block", block("vid")), "vectors")

    def train(key: tuple[pa.Scalar, ...], cell: pa.Table, vectors: pa.Table) -> pa.Table:
        side, vid = np.asarray(vectors.column("side").to_pylist()), np.asarray(vectors.column("vid"))
        value = np.asarray(vectors.column("value").combine_chunks().flatten()).reshape(len(vid), -1).copy() if len(vid) else np.zeros((0, dim))
        cx, cy = np.flatnonzero(side == "x"), np.flatnonzero(side == "y")
        cx, cy = cx[np.argsort(vid[cx])], cy[np.argsort(vid[cy])]
        if cell.num_rows and len(cx) and len(cy):
            a, b = np.searchsorted(vid[cx], np.asarray(cell.column("center"))), np.searchsorted(vid[cy], np.asarray(cell.column("context")))
            random = np.random.default_rng([seed, key[0].as_py()])
            order = random.permutation(len(a))
            for k in range(0, len(order), 1024):
                own = order[k : k + 1024]
                i = np.repeat(a[own], 1 + negatives)
                j = np.stack([b[own], *random.integers(0, len(cy), (negatives, len(own)))], 1).ravel()
                t = np.tile([1.0] + [0.0] * negatives, len(own))
                x, y = value[cx[i]], value[cy[j]]
                g = rate * (t - 1 / (1 + np.exp(-np.clip((x * y).sum(1), -30, 30))))[:, None]
                np.add.at(value, cx[i], g * y)
                np.add.at(value, cy[j], g * x)
        return pa.table({"vid": pa.array(vid, pa.int64()), "side": pa.array(side.tolist(), pa.string()), "value": pa.array(list(value), pa.list_(pa.float64()))})

    for _ in range(epochs):
        for r in range(blocks):
            cells = pairs.where(F.pmod(F.col("bj") - F.col("bi"), F.lit(blocks)) == r).select("bi", "center", "context")
            xs = state.select(F.col("block").alias("bi"), "vid", F.lit("x").alias("side"), F.col("x").alias("value"))
            ys = state.select(F.pmod(F.col("block") - r, F.lit(blocks)).alias("bi"), "vid", F.lit("y").alias("side"), F.col("y").alias("value"))
            done = cells.groupBy("bi").cogroup(xs.unionByName(ys).groupBy("bi")).applyInArrow(train, "vid long, side string, value array<double>")
            wide = done.groupBy("vid").agg(F.max(F.when(F.col("side") == "x", F.col("value"))).alias("x"), F.max(F.when(F.col("side") == "y", F.col("value"))).alias("y"))
            state = written(wide.withColumn("block", block("vid")), "vectors")
    return state.select("vid", F.col("x").cast("array<float>").alias("vec"))


def cosine(a, b):
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def similar(vectors: DataFrame, vid: int, k: int = 10) -> DataFrame:
    """(vid, similarity): the nearest of one vertex; ties by id."""
    one = vectors.where(F.col("vid") == vid).select(F.col("vec").alias("_v"))
    rows = vectors.where(F.col("vid") != vid).join(F.broadcast(one))
    return rows.select("vid", cosine("vec", "_v").alias("similarity")).orderBy(F.desc("similarity"), "vid").limit(k)


def edge_features(vectors: DataFrame, pairs: DataFrame, op: str = "product") -> DataFrame:
    """``pairs`` (a, b, ...) with ``features``: mean, product, absolute or squared difference of the two vectors."""
    how = {"mean": lambda p, q: (p + q) / 2, "product": lambda p, q: p * q, "abs": lambda p, q: F.abs(p - q), "square": lambda p, q: (p - q) * (p - q)}[op]
    side = lambda n: vectors.select(F.col("vid").alias(n), F.col("vec").alias(f"_{n}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").withColumn("features", F.zip_with("_a", "_b", how)).drop("_a", "_b")
