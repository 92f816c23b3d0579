from __future__ import annotations

import pytest

from stepwalk.graph import build, model, stats, synth
from stepwalk.sources import edgelists

from .compare import connect, same


def frame(spark, rows, schema="src long, dst long, w long"):
    return spark.createDataFrame(rows, schema)


@pytest.mark.parametrize("name", sorted(build.GRAPHS))
def test_builders_match_sql(spark, sf, name):
    same(connect(sf), build.GRAPHS[name](spark, sf), build.SQL[name])


def test_dirty_edges_are_quarantined(spark):
    rows = [(1, 2, 1.0), (1, None, 1.0), (2, 3, 0.0), (2, 3, -1.0), (2, 3, float("nan")), (2, 3, None), (4, 4, 1.0), (2, 1, 2.0)]
    dirty = frame(spark, rows, "src long, dst long, w double")
    good, bad = model.check_edges(dirty)
    assert good.count() == 3 and bad.count() == 5
    found = {tuple(r) for r in model.normalize(dirty).collect()}
    assert found == {(1, 2, 3.0), (2, 1, 3.0)}
    assert model.normalize(dirty, keep_loops=True).where("src = 4").count() == 1
    assert model.normalize(dirty.limit(0)).count() == 0


def test_stats_of_small_graphs(spark):
    ring = model.normalize(frame(spark, [(i, (i + 1) % 8, 1) for i in range(8)]))
    m = stats.prob_memory(ring).first()
    assert m.bytes == 8 * 8 * 4 == m.floor_bytes
    assert stats.triangles(ring).first()[0] == 0
    clique = model.normalize(frame(spark, [(a, b, 1) for a in range(6) for b in range(a)]))
    assert stats.triangles(clique).first()[0] == 20
    two = ring.unionByName(model.normalize(frame(spark, [(100, 101, 1)])))
    assert {r.root for r in stats.components(two).collect()} == {0, 100}
    five = model.normalize(frame(spark, [(1, 2, 1), (2, 3, 1), (1, 3, 2), (3, 4, 1), (4, 5, 3)]))
    assert stats.plateau(five) == pytest.approx(2.2)
    assert stats.prob_memory(five).first().bytes == 176
    assert stats.plan_storage(five, 176) == "precompute" and stats.plan_storage(five, 175) == "on_demand"


def test_popular_budgets(spark):
    star = model.normalize(frame(spark, [(0, i, 1) for i in range(1, 21)] + [(50, i, 1) for i in range(1, 6)]))
    assert [r.vid for r in stats.popular(star, degree=5).orderBy("vid").collect()] == [0, 50]
    assert [r.vid for r in stats.popular(star, hot_bytes=8 * 20 + 8 * 4).collect()] == [0]
    assert stats.popular(star, hot_bytes=10**9).count() == stats.degrees(star).count()
    assert stats.popular(star, share=0.05).count() == 2


def test_trim_keeps_heaviest_with_ties_by_id(spark):
    star = model.normalize(frame(spark, [(0, i, 5 if i < 3 else 1) for i in range(1, 9)]))
    kept = sorted(r.dst for r in stats.trim(star, 4).where("src = 0").collect())
    assert kept == [1, 2, 3, 4]
    assert stats.trim(star, 4, symmetric=True).count() == 8
    assert {r.retained for r in stats.trim_retention(star, 4).where("deg = 8").collect()} == {0.5}


def test_chunks_keep_all_neighbours(spark):
    star = model.normalize(frame(spark, [(0, i, 1) for i in range(1, 50)]))
    adj = model.adjacency(star, chunk=10)
    assert adj.where("vid = 0").count() == 5
    assert model.unchunked(adj).exceptAll(star).count() == 0


def test_recursive_matrix_shares():
    spec = synth.skew(22, 5)
    assert spec.a == pytest.approx(1 / 12) and spec.d == pytest.approx(5 / 12)
    assert synth.solve_shares(22, 100, 5000) == pytest.approx(0.597, abs=1e-3)
    assert [round(synth.expected_last_degree(synth.wec(k))) for k in (20, 22, 24, 26)] == pytest.approx([1374, 1786, 2321, 3017], abs=2)


def test_edge_list_files(spark, tmp_path):
    edges = frame(spark, [(1, 2, 3), (2, 1, 3)])
    for kind in ("text", "csv"):
        edgelists.write_edges(edges, f"{tmp_path}/{kind}", kind)
    assert sorted(map(tuple, edgelists.read_csv(spark, f"{tmp_path}/csv")[0].collect())) == [(1, 2, 3), (2, 1, 3)]
    with open(tmp_path / "more.txt", "w") as f:
        f.write("# note\n1 2\n\n3 x\n4 5 6\n7\n")
    good, bad = edgelists.read_text(spark, str(tmp_path / "more.txt"))
    assert sorted(map(tuple, good.collect())) == [(1, 2, 1), (4, 5, 6)]
    assert sorted(r.row for r in bad.collect()) == ["3 x", "7"]
