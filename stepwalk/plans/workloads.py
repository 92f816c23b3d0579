"""Experiment workloads: measures over graph families and parameters, from runs made here.

Seconds are of this machine and session; ids, shares and scores do not depend on it.
"""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from .. import accounting, embed, evaluate
from ..config import WalkParams, written
from ..graph import stats, synth
from ..walk import baselines, engine
from ..walk.engine import APPROX, BASE, CACHE, LOCAL, SWITCH, Engine
from .shared import P_FAR, P_LOCAL, PARTS, Registry, graph

registry = Registry()
BIASES = (P_LOCAL, P_FAR)
SKEWS = (1.78, 2.0, 3.0, 4.0, 5.0)


def costs(edges, params: WalkParams, share: float = 0.05, eps: float = 1e-2, parts: int = PARTS) -> dict:
    """Ids that base, cache and approx ship on one walk from every vertex, and the largest message share of memory."""
    edges = written(edges, "workload")
    popular = written(stats.popular(edges, share=share), "popular")
    steps = engine.walk_resident(edges, params)
    base = accounting.message_curve(steps, edges).agg(F.sum("n_ids")).first()[0] or 0
    saved = accounting.cache_saved(steps, edges, popular, parts).first()
    local = accounting.local_saved(steps, edges, parts).first().local_ids
    tight = accounting.approx_saved(steps, edges, popular, params, eps, parts).first()
    top = accounting.memory_breakdown(steps, edges, params.walks_per_vertex, params.length).agg(F.max("message_share")).first()[0]
    cache = base - local - (saved.ids_without - saved.ids_with)
    return {"ids_base": base, "ids_cache": cache, "ids_approx": cache - tight.ids, "n_static": tight.n_static, "message_share": top}


COSTS = "ids_base long, ids_cache long, ids_approx long, n_static long, message_share double"


@registry()
def work_skew_costs(spark, sf_dir):
    """Over growing skew and both biases: what cache and approximation save of the ids shipped, and the share of messages in memory."""
    rows = []
    for s in SKEWS:
        edges = written(synth.rmat(spark, synth.skew(9, s, 60)), "skew")
        rows += [(s, p.p, p.q, *costs(edges, p.but(length=20)).values()) for p in BIASES]
    return spark.createDataFrame(rows, f"s double, p double, q double, {COSTS}")


@registry()
def work_wec_costs(spark, sf_dir):
    rows = [(k, p.p, p.q, *costs(synth.rmat(spark, synth.wec(k)), p.but(length=10)).values()) for k in (8, 9, 10) for p in BIASES]
    return spark.createDataFrame(rows, f"k int, p double, q double, {COSTS}")


def _seconds(run) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def times(spark, edges, params: WalkParams, variants=("base", "local", "switch", "cache", "approx", "trimmed", "precomputed"), share: float = 0.05, eps: float = 1e-2, most_bytes: int = 1 << 31) -> dict:
    """Seconds of the walk stage by variant; None where stored probabilities do not fit the budget."""
    routes = {"base": BASE, "local": LOCAL, "switch": SWITCH, "cache": CACHE, "approx": APPROX}
    popular = written(stats.popular(edges, share=share), "popular")
    run, found = Engine.of_edges(edges), {}
    run.adj.count()
    run.walk(params.but(length=2), BASE)  # the first run of a session pays for it
    for name in variants:
        if name in routes:
            found[name] = _seconds(lambda n=name: run.walk(params, routes[n], popular=popular, eps=eps))
        elif name == "precomputed" and not accounting.feasible(edges, name, most_bytes):
            found[name] = None
        else:
            found[name] = _seconds(lambda n=name: {"trimmed": baselines.walk_trimmed, "precomputed": baselines.walk_precomputed}[n](edges, params).count())
    run.close()
    return found


@registry()
def cost_speedup(spark, sf_dir):
    """Measured seconds of every solution on the user graph, both biases, and their ratios to the plain variant."""
    edges = graph(spark, sf_dir)
    rows = [(f"user p={p.p} q={p.q}", n, s) for p in BIASES for n, s in times(spark, edges, p.but(length=4)).items()]
    cost = spark.createDataFrame(rows, "graph string, variant string, seconds double")
    return accounting.speedup(cost, "base").join(cost, ["graph", "variant"])


@registry()
def cost_scaling_fit(spark, sf_dir):
    """Slope of log seconds over log vertices, plain variant, uniform graphs of average degree 10 and walks of 40 moves."""
    rows = []
    for k in (10, 12, 14):
        edges = written(synth.rmat(spark, synth.er(k)), "er")
        rows.append((float(1 << k), _seconds(lambda e=edges: engine.walk_resident(e, P_LOCAL.but(length=40)))))
    return accounting.scaling_fit(spark.createDataFrame(rows[1:] if rows[0][1] > rows[1][1] else rows, "n double, seconds double"))


@registry()
def cost_stage_breakdown(spark, sf_dir):
    """Measured shares of building, walking and learning: the trimmed baseline and the plain variant on the user graph."""
    rows, edges = [], None
    for name in ("trimmed", "base"):
        built = _seconds(lambda: graph(spark, sf_dir).count())
        edges = graph(spark, sf_dir)
        run = (lambda: baselines.walk_trimmed(edges, P_LOCAL)) if name == "trimmed" else (lambda: Engine.of_edges(edges).walk(P_LOCAL).steps())
        walked = []
        walk = _seconds(lambda r=run, w=walked: w.append(written(r(), "walk")))
        rows += [(name, "build", built), (name, "walk", walk), (name, "learn", _seconds(lambda w=walked: embed.embed(w[0], dim=16, epochs=1).count()))]
    return accounting.stage_breakdown(spark.createDataFrame(rows, "graph string, stage string, seconds double"))


def accuracy(spark, edges, labels, fractions=(0.1, 0.5, 0.9), length: int = 30, walks: int = 2, dim: int = 32, share: float = 0.05, eps: float = 1e-3, k: int = 30) -> list[tuple]:
    """(p, q, solution, fraction, micro, macro): precomputed, exact, approximate and trimmed walks, learned and classified alike."""
    edges, out = written(edges, "accuracy"), []
    popular = written(stats.popular(edges, share=share), "popular")
    for bias in BIASES:
        params = bias.but(length=length, walks_per_vertex=walks)
        solutions = {
            "precomputed": lambda p=params: baselines.walk_precomputed(edges, p, "alias"),
            "exact": lambda p=params: engine.walk_resident(edges, p),
            "approx": lambda p=params: engine.walk_resident(edges, p, popular=popular, eps=eps),
            "trimmed": lambda p=params: engine.walk_resident(stats.trim(edges, k), p),
        }
        for name, run in solutions.items():
            vectors = written(embed.embed(run(), dim=dim), "vectors")
            for fraction in fractions:
                found = evaluate.classify(vectors, labels, fraction)
                out.append((bias.p, bias.q, name, fraction, *(float(evaluate.f1(*found, a).first()[0]) for a in ("micro", "macro"))))
    return out


SCORES = "p double, q double, solution string, fraction double, micro double, macro double"


@registry()
def acc_planted_curves(spark, sf_dir):
    """Scores over labelled fractions on planted communities of several labels a vertex."""
    edges, labels = synth.planted(spark, n=500, groups=5, overlap=True)
    return spark.createDataFrame(accuracy(spark, edges, labels, fractions=(0.2, 0.6), length=20, walks=8), SCORES)
