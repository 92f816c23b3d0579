"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from stepwalk import accounting
from stepwalk.config import WalkParams, written
from stepwalk.graph import stats, synth
from stepwalk.graph.build import GRAPHS
from stepwalk.plans import workloads
from stepwalk.walk import baselines, engine
from stepwalk.walk.engine import APPROX, BASE, CACHE, LOCAL, SWITCH, Engine


def timed(found: dict[str, float], name: str, run):
    began = time.perf_counter()
    out = run()
    found[name] = round(time.perf_counter() - began, 3)
    print(f"{name}: {found[name]} s", file=sys.stderr, flush=True)
    return out


def shipped(walk) -> int:
    """Ids in lists that travel: with walkers, or back to the vertex that asked for them."""
    return int(walk.log().agg(F.sum(F.when(F.col("route").isin("list", "ask"), F.col("n_ids")).otherwise(0) + F.col("replied"))).first()[0] or 0)


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("stepwalk-bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "10g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    figures: dict[str, float] = {}
    graphs = {}
    written(GRAPHS["user"](spark, sf_dir), "warm").count()
    for name in ("user", "copart", "entity"):
        graphs[name] = timed(seconds, f"build_{name}", lambda n=name: written(GRAPHS[n](spark, sf_dir), n))
    long = WalkParams(0.5, 2.0, length=80, walks_per_vertex=1)
    for name in ("user", "copart", "entity"):
        steps = timed(seconds, f"resident80_{name}", lambda n=name: engine.walk_resident(graphs[n], long))
        figures[f"moves_per_s_{name}"] = round(steps.where("step > 0").count() / seconds[f"resident80_{name}"])
    far = timed(seconds, "resident80_entity_far", lambda: engine.walk_resident(graphs["entity"], long.but(p=2.0, q=0.5)))
    figures["moves_per_s_entity_far"] = round(far.where("step > 0").count() / seconds["resident80_entity_far"])

    # The routes over supersteps: few moves, as a local machine pays a fixed price for each; ids shipped are the measure.
    short, edges = WalkParams(0.5, 2.0, length=5, walks_per_vertex=1), graphs["copart"]
    popular = written(stats.popular(edges, share=0.05), "popular")
    run = Engine.of_edges(edges)
    run.adj.count()
    for name, variant in (("base", BASE), ("local", LOCAL), ("switch", SWITCH), ("cache", CACHE), ("approx", APPROX)):
        walk = timed(seconds, f"copart5_{name}", lambda v=variant: run.walk(short, v, popular=popular, eps=1e-2))
        figures[f"ids_shipped_copart5_{name}"] = shipped(walk)
    run.close()
    user = graphs["user"]
    timed(seconds, "user5_trimmed", lambda: baselines.walk_trimmed(user, short).count())
    timed(seconds, "user5_base", lambda: Engine.of_edges(user).walk(short).steps().count())

    # A cache starved of memory: the share of popular vertices it may hold.
    run = Engine.of_edges(edges)
    run.adj.count()
    for share in (0.01, 0.25):
        few = written(stats.popular(edges, share=share), "popular")
        walk = timed(seconds, f"copart5_cache_{share}", lambda f=few: run.walk(short, CACHE, popular=f))
        figures[f"ids_shipped_copart5_cache_{share}"] = shipped(walk)
    run.close()

    # Families of graphs, several walks from every vertex: what cache and approximation save in ids and seconds.
    def family(label: str, spec, share: float, r: int) -> None:
        made = timed(seconds, f"build_{label}", lambda: written(synth.rmat(spark, spec), "family"))
        hub = written(stats.popular(made, share=share), "popular")
        run = Engine.of_edges(made)
        run.adj.count()
        ids = {}
        for name, variant in (("base", BASE), ("cache", CACHE), ("approx", APPROX)):
            walk = timed(seconds, f"{label}_{name}", lambda v=variant: run.walk(short.but(walks_per_vertex=r), v, popular=hub, eps=1e-2))
            ids[name] = shipped(walk)
            figures[f"ids_share_{label}_{name}"] = round(ids[name] / ids["base"], 4)
            figures[f"speedup_{label}_{name}"] = round(seconds[f"{label}_base"] / seconds[f"{label}_{name}"], 3)
        run.close()

    for s in (1.78, 2.0, 3.0, 4.0, 5.0):
        family(f"skew{s:g}", synth.skew(12, s), 0.25, 16)
    for k in (10, 11):
        family(f"wec{k}", synth.wec(k), 0.05, 8)
    # Scaling of the plain walk with the number of vertices; stored probabilities need 8 bytes for each of the squared degrees.
    sizes = []
    for k in (10, 12, 14):
        made = written(synth.rmat(spark, synth.er(k)), "er")
        timed(seconds, f"er{k}_resident80", lambda m=made: engine.walk_resident(m, long))
        sizes.append((float(1 << k), seconds[f"er{k}_resident80"]))
        figures[f"stored_mb_er{k}"] = round((stats.prob_memory(made).first()[0] or 0) / 1e6, 2)
    figures["er_slope"] = round(float(accounting.scaling_fit(spark.createDataFrame(sizes, "n double, seconds double")).first()[0]), 3)
    figures["stored_mb_entity"] = round((stats.prob_memory(graphs["entity"]).first()[0] or 0) / 1e6, 1)
    for r in workloads.cost_stage_breakdown(spark, sf_dir).collect():
        figures[f"stage_share_{r.graph}_{r.stage}"] = round(r.share, 4)
    value = round(sum(seconds.values()), 3)
    print(json.dumps({"metric": "headline_total", "value": value, "unit": "sec", "queries": seconds, "figures": figures, "sf": sf_dir}))
    spark.stop()


if __name__ == "__main__":
    main()
