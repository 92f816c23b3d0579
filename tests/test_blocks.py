"""Walks over packed blocks: the same walks as the row routes, and between two vertices the shorter list travels."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from stepwalk.config import WalkParams, written
from stepwalk.graph import blocks, build, stats
from stepwalk.walk import engine
from stepwalk.walk.engine import APPROX, BASE, CACHE, LOCAL, Engine

PARAMS = WalkParams(0.5, 2.0, length=4, walks_per_vertex=1)


@pytest.fixture
def small(monkeypatch):
    monkeypatch.setattr(engine, "HEAVY_FROM", 4)
    monkeypatch.setattr(engine, "BLOCK_EDGES", 900)
    monkeypatch.setattr(engine, "CHUNK_IDS", 500)


def _steps(walk) -> list:
    return sorted(map(tuple, walk.steps().collect()))


def test_long_lists_are_not_state(spark, sf, small):
    """The walk's table held the last vertex's list for every walker, however long; booked messages are as they were."""
    edges = written(build.entity_edges(spark, sf), "entity")
    run = Engine.of_edges(edges, parts=3)
    walk, want = run.walk(PARAMS, BASE), run.walk(PARAMS, LOCAL)
    assert _steps(walk) == _steps(want)
    deg = stats.degrees(edges).select(F.col("vid").alias("vertex"), "deg")
    state = spark.read.parquet(walk.path).join(deg, "vertex")
    assert state.where(F.size("prev_ids") > F.greatest(F.lit(4), "deg")).isEmpty()
    assert not state.where("asked").isEmpty() and not state.where("size(prev_ids) > 0").isEmpty()
    left = spark.read.parquet(want.path).where("step between 1 and 3").join(deg.withColumnRenamed("vertex", "prev"), "prev")
    assert walk.log().agg(F.sum("n_ids")).first()[0] == left.agg(F.sum("deg")).first()[0]
    run.close()


def test_messages_do_not_depend_on_blocks(spark, sf, monkeypatch):
    edges = written(build.entity_edges(spark, sf), "entity")
    popular, found = stats.popular(edges, share=0.05), []
    for heavy, size, budget in ((256, 1 << 21, 96 << 20), (4, 900, 96 << 20), (256, 1 << 21, 30_000), (4, 900, 30_000)):
        monkeypatch.setattr(engine, "HEAVY_FROM", heavy)
        monkeypatch.setattr(engine, "BLOCK_EDGES", size)
        monkeypatch.setattr(engine, "HOT_BYTES", budget)
        run = Engine.of_edges(edges, parts=7)
        walk, rough = run.walk(PARAMS, CACHE, popular=popular), run.walk(PARAMS, APPROX, popular=popular, eps=0.05)
        found.append((sorted(map(tuple, walk.messages().collect())), _steps(walk), _steps(rough)))
        run.close()
    assert found[0] == found[1] and found[2] == found[3]
    assert found[0][0] != found[2][0] and found[0][1:] == found[2][1:]


def test_parallel_edges_and_broken_weights(spark, sf, small):
    """An edge that is there twice counts twice; weights need not be whole."""
    user = build.user_edges(spark, sf).where("src < 40")
    for edges in (user.unionByName(user.where("dst % 3 = 0")), user.withColumn("w", F.col("w") * 0.5)):
        edges = written(edges, "odd")
        run = Engine.of_edges(edges, parts=3)
        params = PARAMS.but(directed=True)
        assert _steps(run.walk(params, BASE)) == _steps(run.walk(params, LOCAL))
        run.close()


def test_pairs_counted_in_blocks(spark):
    rows = spark.range(5000).select(F.when(F.col("id") % 97 > 0, F.col("id") % 31 - 9).alias("a"), F.when(F.col("id") % 89 > 0, (F.col("id") % 7) * 10**12).alias("b"))
    want = rows.groupBy("a", "b").agg(F.count("*").alias("w"))
    for n in (1, 5, 64):
        found = blocks.counted(rows, n)
        assert found.exceptAll(want).isEmpty() and want.exceptAll(found).isEmpty()


def test_blocks_find_far_apart_ids():
    """Neighbour ids that span all of 63 bits."""
    dst = np.array([-(1 << 62), 5, 1 << 62, 5, 1 << 62])
    body = {"n": 5, "m": 2, "vids": blocks.squeezed(np.array([3, 9])), "deg": blocks.squeezed(np.array([3, 2])), "ids": blocks.squeezed(np.diff(dst, prepend=0)), "ws": blocks.squeezed(np.ones(5, np.int64))}
    block = blocks.Block(body, np.int64)
    assert block.ids.tolist() == dst.tolist() and block.slot(np.array([9, 4])).tolist() == [1, -1]
    which, where = block.find(np.array([0, 1, 1, -1]), np.array([1 << 62, 5, 6, 5]))
    assert which.tolist() == [0, 1] and where.tolist() == [2, 3]
    offsets = np.array([0, 3, 3, 5])
    assert blocks.undeltas(blocks.deltas(dst, offsets), offsets).tolist() == dst.tolist()


def test_popular_counts_degrees_once(spark, sf):
    """The edges were counted anew for each of four readings of the degrees."""
    edges = written(build.entity_edges(spark, sf), "entity")
    found = stats.popular(edges, share=0.05)
    assert not any("/entity-" in f for f in found.inputFiles())
    deg = sorted(((r.deg, -r.vid) for r in stats.degrees(edges).collect()), reverse=True)
    assert sorted((r.deg, -r.vid) for r in found.collect()) == sorted(deg[: -(-len(deg) * 5 // 100)])
