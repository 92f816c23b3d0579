"""Findings of round 2."""

from __future__ import annotations

import numpy as np
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector
from pyspark.sql import functions as F

from stepwalk import evaluate
from stepwalk.config import WalkParams, written
from stepwalk.graph import build, stats, synth
from stepwalk.plans import catalog
from stepwalk.walk import alpha, baselines, engine, pairs


def _vectors(spark, n=300, dim=4):
    unit = lambda k: (F.pmod(F.xxhash64(F.col("id"), F.lit(k)), F.lit(2000)) / 1000.0 - 1).cast("float")
    rows = spark.range(n).select(F.col("id").alias("vid"), F.array(*[unit(k) for k in range(dim)]).alias("vec"))
    own = F.when(F.col("vec")[0] + 0.4 * F.col("vec")[1] > 0.1 * F.col("vec")[2], F.array(F.lit(1))).otherwise(F.array(F.lit(0)))
    own = F.when(F.col("vec")[3] > 0.5, F.array_append(own, F.lit(7))).otherwise(own)
    return rows, rows.select("vid", F.when(F.pmod("vid", F.lit(9)) == 0, F.array(F.lit(0))).otherwise(own).alias("labels"))


def test_labels_fitted_together_equal_single_regressions(spark):
    vectors, labels = _vectors(spark)
    train = vectors.join(labels, "vid").select(F.col("vec").cast("array<double>").alias("features"), "labels")
    coefficients, intercepts = evaluate.fit_labels(train, [0, 1, 7])
    for k, name in enumerate((0, 1, 7)):
        one = train.select(array_to_vector("features").alias("features"), F.array_contains("labels", name).cast("double").alias("label"))
        model = LogisticRegression(maxIter=200, regParam=1e-3, tol=1e-10).fit(one)
        assert np.allclose(coefficients[k], model.coefficients.toArray(), atol=1e-3) and abs(intercepts[k] - model.intercept) < 1e-3


def test_scores_ship_no_fitted_model(spark, capsys):
    vectors, labels = _vectors(spark)
    found, truth = evaluate.classify(vectors, labels, 0.5)
    assert evaluate.f1(found, truth).first().f1 > 0.8
    vectors.select(evaluate.linear_scores([[1.0, 2.0, 0.0, -1.0]], [0.5], "vec")).explain()
    assert "UDF" not in capsys.readouterr().out
    assert not hasattr(evaluate, "vector_to_array")


def test_link_auc(spark):
    vectors, _ = _vectors(spark)
    pairs = vectors.select(F.col("vid").alias("a"), (F.col("vid") + 1).alias("b"), F.col("vec").alias("features"), (F.col("vec")[0] > 0).cast("int").alias("label"))
    assert evaluate.link_auc(pairs) > 0.99


READERS = {"sql_draws": "events", "synth_planted_edges": "customer"} | {f"synth_{n}_degrees": "events" for n in ("er", "wec", "skew1", "skew2", "skew3", "skew4", "skew5")}


def test_given_tables_are_read(spark, sf):
    for name, of in READERS.items():
        files = catalog.queries()[name](spark, sf).inputFiles()
        assert any(f"/{of}.parquet" in f for f in files), name


def test_planted_runs_are_planted_graphs(spark):
    """Ids 0 to 199 of a table give the graph that is drawn without a table; other runs are not linked to them."""
    alone = {tuple(r) for r in synth.planted(spark, n=200, groups=4)[0].collect()}
    rows = {tuple(r) for r in synth.planted(spark, n=200, groups=4, vertices=spark.range(500).withColumnRenamed("id", "vid"))[0].collect()}
    assert {r for r in rows if r[0] < 200} == alone
    assert all(a // 200 == b // 200 for a, b, _ in rows) and {a // 200 for a, _, _ in rows} == {0, 1, 2}


def test_cache_beyond_its_budget_keeps_what_fits(spark, sf, monkeypatch):
    """Popular lists beyond the budget: the same walks, with the others' lists shipped."""
    edges = written(build.user_edges(spark, sf), "user")
    popular, params = stats.popular(edges, degree=1), WalkParams(0.5, 2.0, length=4, walks_per_vertex=1)
    steps = lambda walk: sorted(map(tuple, walk.steps().collect()))
    run = engine.Engine.of_edges(edges, parts=3)
    some = stats.popular(edges, share=0.3)
    exact, rough = steps(run.walk(params, engine.BASE)), steps(run.walk(params, engine.APPROX, popular=some, eps=1.5))
    assert exact != rough
    for budget in (0, 3000):
        monkeypatch.setattr(engine, "HOT_BYTES", budget)
        assert steps(run.walk(params, engine.APPROX, popular=some, eps=1.5)) == rough
        walk = run.walk(params, engine.CACHE, popular=popular)
        assert steps(walk) == exact
        kinds = {r.kind: r.n_msgs for r in walk.messages().where("step = 2").collect()}
        assert kinds.get("list", 0) > 0 and (budget == 0) == ("ref" not in kinds)
    run.close()


def test_transition_rows_in_blocks_equal_the_joins(spark, sf, monkeypatch):
    monkeypatch.setattr(pairs, "BLOCK_EDGES", 40)
    monkeypatch.setattr(pairs, "CHUNK", 16)
    edges = written(build.user_edges(spark, sf).where("src < 9 or dst % 2 = 0"), "uneven")
    params = WalkParams(0.5, 2.0)
    names = ["u", "v", "x", "w", "dist", "pi"]
    rows = pairs.transition_rows(edges, params)
    want = sorted(map(tuple, alpha.transition_weights(edges, params).select(*names).collect()))
    assert sorted(map(tuple, rows.select(*names).collect())) == want
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Window" not in plan
    assert all(r.total == sum(t[5] for t in want if t[:2] == (r.u, r.v)) for r in rows.limit(20).collect())


def test_stored_probabilities_are_lists_by_edge(spark, sf):
    edges = written(build.user_edges(spark, sf), "user")
    tables = baselines.alias_tables(edges, WalkParams(0.5, 2.0))
    assert "Window" not in (plan := tables._jdf.queryExecution().executedPlan().toString()) and "Join" not in plan
    assert tables.count() == edges.count()
