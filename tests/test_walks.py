from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from stepwalk import accounting, embed, evaluate
from stepwalk.config import WalkParams, written
from stepwalk.graph import build, model, stats
from stepwalk.walk import baselines, engine
from stepwalk.walk.engine import APPROX, BASE, CACHE, LAZY, LOCAL, SWITCH, Engine, Variant

LOW, FAR = WalkParams(0.5, 2.0, length=6, walks_per_vertex=1), WalkParams(2.0, 0.5, length=6, walks_per_vertex=1)


def rows(frame):
    return sorted(map(tuple, frame.select("start", "round", "step", "vertex").collect()))


@pytest.fixture(scope="module")
def user(spark, sf):
    return written(build.user_edges(spark, sf), "user")


@pytest.fixture(scope="module")
def popular(user):
    return stats.popular(user, share=0.2)


def plain(edges, params):
    listed = [tuple(r) for r in edges.collect()]
    found = []
    for r in range(params.walks_per_vertex):
        paths = baselines.reference_walk(listed, params, sorted({e[0] for e in listed}), r)
        found += [(s, r, k, v) for s, path in paths.items() for k, v in enumerate(path)]
    return sorted(found)


@pytest.mark.parametrize("params", [LOW, FAR])
@pytest.mark.parametrize("parts", [1, 4])
def test_all_exact_routes_give_the_plain_walk(user, popular, params, parts):
    want = plain(user, params)
    run = Engine.of_edges(user, parts=parts)
    for variant in (BASE, LOCAL, SWITCH, CACHE, LAZY):
        assert rows(run.walk(params, variant, popular=popular).steps()) == want, variant
    assert rows(run.walk(params, APPROX, popular=popular, eps=0.0).steps()) == want
    run.close()


def test_other_engines_give_the_plain_walk(user):
    want = plain(user, LOW)
    assert rows(engine.walk_resident(user, LOW)) == want
    assert rows(engine.walk_resident(user, LOW, most_bytes=1)) == want
    assert rows(baselines.walk_precomputed(user, LOW)) == want
    assert rows(engine.walk_chunked(model.adjacency(user, chunk=4), LOW).steps()) == want
    assert rows(baselines.walk_trimmed(user, LOW, k=100)) == want


def test_rounds_equal_one_run_and_restart(spark, user, tmp_path):
    params = LOW.but(walks_per_vertex=2)
    want = plain(user, params)
    run = Engine.of_edges(user, parts=2)
    for k in (1, 3):
        walks = engine.walk_rounds(run, params, k, path=f"file://{tmp_path}/k{k}")
        assert sorted(x for w in walks for x in rows(w.steps())) == want
    import shutil

    kept = (tmp_path / "k3" / "group=0").stat().st_mtime_ns
    shutil.rmtree(tmp_path / "k3" / "group=1")
    again = engine.walk_rounds(run, params, 3, path=f"file://{tmp_path}/k3")
    assert sorted(x for w in again for x in rows(w.steps())) == want
    assert (tmp_path / "k3" / "group=0").stat().st_mtime_ns == kept


def test_first_order_and_floats(user):
    params = WalkParams(length=5, walks_per_vertex=1)
    assert rows(baselines.first_order_walk(user, params)) == plain(user, params)
    odd = WalkParams(0.3, 1.7, length=5, walks_per_vertex=1)
    assert rows(Engine.of_edges(user, parts=3).walk(odd).steps()) == rows(engine.walk_resident(user, odd))


def test_directed_sinks_end_walks(spark):
    chain = spark.createDataFrame([(i, i + 1, 1) for i in range(4)], "src long, dst long, w long")
    steps = Engine.of_edges(chain, parts=2).walk(LOW.but(length=10, directed=True)).steps()
    assert steps.groupBy("start").count().orderBy("start").collect() == [(0, 5), (1, 4), (2, 3), (3, 2)]
    assert rows(engine.walk_resident(chain, LOW.but(length=10))) == rows(steps)


def test_empty_graph(spark):
    none = spark.createDataFrame([], "src long, dst long, w long")
    assert Engine.of_edges(none, parts=2).walk(LOW).steps().count() == 0
    assert engine.walk_resident(none, LOW).count() == 0


def test_moves_are_edges_and_counts_fit(user):
    walk = Engine.of_edges(user, parts=3).walk(LOW)
    moves = accounting.moves(walk.steps())
    assert moves.select(F.col("cur").alias("src"), F.col("next").alias("dst")).join(user, ["src", "dst"], "left_anti").count() == 0
    n = stats.degrees(user).count()
    assert walk.steps().count() == n * (LOW.length + 1)
    sent = {r.step: r.n_ids for r in walk.messages().where("kind = 'list'").collect()}
    assert sent == {r.step: r.n_ids for r in accounting.message_curve(walk.steps(), user).collect()}


def test_switch_costs_half_again_on_a_star(spark):
    star = model.normalize(spark.createDataFrame([(0, i, 1) for i in range(1, 41)], "src long, dst long, w long"))
    hub = stats.popular(star, degree=10)
    params = LOW.but(length=8)
    walk = Engine.of_edges(star, parts=2).walk(params, SWITCH, popular=hub)
    found = {r.start: r.supersteps for r in accounting.switch_supersteps(walk.steps(), hub).collect()}
    hops = {r.start: r.hops for r in walk.log().where("step = 8").collect()}
    assert found == hops
    assert hops[1] == 8 + 3 and hops[0] == 8 + 4 == 1.5 * 8  # half again on a path that alternates
    assert rows(walk.steps()) == plain(star, params)
    log = walk.log().collect()
    asked = [r for r in log if r.route == "ask"]
    assert asked and all(r.n_ids == 1 for r in asked)
    assert sorted((r.start, r.step - 1, r.replied) for r in log if r.replied) == sorted((r.start, r.step, 1) for r in asked)  # a leaf's list
    kinds = {r.kind: r.n_ids for r in walk.messages().groupBy("kind").agg(F.sum("n_ids").alias("n_ids")).collect()}
    assert kinds["reply"] == kinds["ask"] == len(asked)


def test_switch_sends_the_short_list(spark, sf, monkeypatch):
    from stepwalk.graph import build

    edges = written(build.supply_edges(spark, sf), "supply")
    hub, degree = stats.popular(edges, share=0.05), {r.vid: r.deg for r in stats.degrees(edges).collect()}
    monkeypatch.setattr(engine, "MOST_ASKED", 20)
    run = Engine.of_edges(edges, parts=3)
    walk = run.walk(LOW, SWITCH, popular=hub)
    assert rows(walk.steps()) == rows(run.walk(LOW).steps())
    at = {(r.start, r.round, r.step): r for r in walk.log().collect()}
    hot = {r.vid for r in hub.collect()}
    assert sum(r.route == "ask" for r in at.values()) > 50
    for (s, r, k), x in at.items():
        if x.route == "ask":
            assert x.vertex not in hot and at[s, r, k - 1].vertex in hot
            assert at[s, r, k + 1].replied == degree[x.vertex]
        elif (s, r, k + 1) in at:
            assert at[s, r, k + 1].replied == 0


def test_walkers_at_popular_vertices_join_nothing(spark, sf):
    edges = written(build.entity_edges(spark, sf), "entity")
    hub = stats.popular(edges, share=0.1)
    run, params = Engine.of_edges(edges, parts=3), LOW.but(walks_per_vertex=3)
    want = rows(run.walk(params).steps())
    for variant in (CACHE, APPROX):
        walk = run.walk(params, variant, popular=hub, eps=0.0)
        assert rows(walk.steps()) == want
        last = spark.read.parquet(walk.path).where("step < 6 and step > 0")
        hot = {r.vid for r in hub.collect()}
        assert all((r.vertex in hot) == r.at_hot for r in last.select("vertex", "at_hot").distinct().collect())
        assert last.where("route = 'ref' and prev_ids is not null").count() == 0
    loose = run.walk(params, APPROX, popular=hub, eps=1.0)
    static = accounting.approx_rate(loose.log()).first().n_static
    assert static > 0 and rows(loose.steps()) == rows(engine.walk_resident(edges, params, popular=hub, eps=1.0))
    odd = WalkParams(0.3, 1.7, length=5, walks_per_vertex=1)
    assert rows(run.walk(odd, CACHE, popular=hub).steps()) == rows(run.walk(odd).steps())


def test_lazy_cache_sends_each_list_once(spark, user, popular):
    walk = Engine.of_edges(user, parts=4).walk(LOW, LAZY, popular=popular)
    saved = accounting.cache_saved(walk.steps(), user, popular, 4).first()
    refs = walk.log().where("route = 'ref'").count()
    assert saved.n_refs == refs and 0 < saved.n_first <= min(refs, 4 * popular.count())
    assert saved.ids_with <= saved.ids_without


def test_approximation_rate_grows_with_epsilon(spark, user, popular):
    run = Engine.of_edges(user.withColumn("w", F.lit(1).cast("long")), parts=2)
    rates = [accounting.approx_rate(run.walk(LOW, APPROX, popular=popular, eps=e).log()).first().n_static for e in (0.0, 0.05, 1.0)]
    assert rates[0] == 0 and rates[0] <= rates[1] <= rates[2] and rates[2] > 0
    pairs = evaluate.approx_error(user, popular, LOW, 1.0)
    assert pairs.where("max_error > max_allowed + 1e-9").count() == 0


def test_bipartite_walks_meet_no_common_neighbour(spark, sf):
    from stepwalk.walk.alpha import distance_class

    assert distance_class(build.supply_edges(spark, sf)).where("dist = 1").count() == 0


def test_illegal_variants(user):
    for bad in ({"cache": "eager"}, {"local": True, "approx": True}, {"switch": True, "local": True}, {"local": True, "cache": "now"}):
        with pytest.raises(ValueError):
            Variant(**bad)
    with pytest.raises(ValueError):
        Engine.of_edges(user, parts=2).walk(LOW, CACHE)
    with pytest.raises(MemoryError):
        baselines.walk_precomputed(user, LOW, most_bytes=10)
    with pytest.raises(ValueError):
        Engine.of_edges(user, parts=2).walk(LOW, CACHE, popular=stats.popular(user, degree=1), hot_bytes=8)


def test_no_exchange_above_the_placed_adjacency(spark, sf):
    edges = written(build.supply_edges(spark, sf), "supply")
    run = Engine.of_edges(edges, parts=4)
    run.adj.count()
    now = run.adj.select(F.col("vid").alias("start"), F.col("vid").alias("vertex")).repartition(3)
    lines = run._attach(now.hint("merge"), BASE, None, True)._jdf.queryExecution().executedPlan().toString().splitlines()
    at = next(k for k, x in enumerate(lines) if "InMemoryTableScan" in x and "ids#" in x)
    assert not any("Exchange" in x for x in lines[at - 2 : at])


def test_local_reads_shuffle_walkers_only(spark, sf):
    edges = written(build.supply_edges(spark, sf), "supply")
    run = Engine.of_edges(edges, parts=4)
    now = spark.read.parquet(run.walk(LOW.but(length=1), LOCAL).path + "/step=1").withColumn("draw", F.lit(5))
    kept = {k: spark.conf.get(k) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.enabled")}
    try:
        for k, v in (("spark.sql.autoBroadcastJoinThreshold", "-1"), ("spark.sql.adaptive.enabled", "false")):
            spark.conf.set(k, v)
        with engine.setting(spark, "spark.sql.requireAllClusterKeysForCoPartition", "false"):
            plan = run._attach(now, LOCAL, None, False)._jdf.queryExecution().executedPlan().toString()
    finally:
        for k, v in kept.items():
            spark.conf.set(k, v)
    above = [x for x in plan.splitlines() if "Exchange hashpartitioning" in x and "REPARTITION_BY_NUM" in x and "_at" in x]
    assert len(above) == 1 and "ENSURE_REQUIREMENTS" not in plan.split("InMemoryRelation")[0]


def test_rejection_draws_the_same_distribution(user):
    params = LOW.but(length=40, walks_per_vertex=30)
    found = evaluate.walk_distance(engine.walk_resident(user, params, reject=True), user, LOW).where("n >= 80").agg(F.avg("tv"), F.count("*")).first()
    exact = evaluate.walk_distance(engine.walk_resident(user, params), user, LOW).where("n >= 80").agg(F.avg("tv")).first()
    assert found[1] > 10 and abs(found[0] - exact[0]) < 0.02


def test_sentences_pairs_and_scores(spark, user):
    steps = engine.walk_resident(user, LOW)
    assert embed.walk_sentences(steps).first().path[0]
    n = stats.degrees(user).count()
    assert embed.context_pairs(steps, 2).count() == n * (2 * 6 + 2 * 5)
    t = spark.createDataFrame([(1, 0), (2, 1), (3, 1)], "vid long, label int")
    p = spark.createDataFrame([(1, 0), (2, 0), (3, 1)], "vid long, label int")
    assert evaluate.f1(p, t).first()[0] == pytest.approx(2 / 3)
    assert evaluate.f1(p, t, "macro").first()[0] == pytest.approx(2 / 3)
    vectors = embed.embed(steps, dim=8)
    assert vectors.count() == n
    assert embed.embed(steps, dim=8, engine="blocks", epochs=1).count() == n
    assert embed.similar(vectors, 1, 3).count() == 3


def test_unbiased_walks_visit_by_degree(user):
    steps = engine.walk_resident(user, WalkParams(length=60, walks_per_vertex=20))
    assert evaluate.stationary_gap(steps, user).first().tv < 0.05


def test_small_p_returns_more(user):
    back = lambda p: accounting.moves(engine.walk_resident(user, p)).where("next = prev").count()
    few, many = WalkParams(4.0, 1.0, length=20, walks_per_vertex=4), WalkParams(0.25, 1.0, length=20, walks_per_vertex=4)
    assert back(many) > 2 * back(few)
