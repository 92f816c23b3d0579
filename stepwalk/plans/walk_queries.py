"""Queries on walks, their costs, accuracy and the vectors learned from them."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import accounting, embed, evaluate
from ..config import WalkParams, written
from ..graph import model, stats, synth
from ..graph.build import SQL
from ..sources.tables import table
from ..walk import baselines, engine
from ..walk.engine import APPROX, BASE, CACHE, LAZY, LOCAL, SWITCH
from . import oracle
from .shared import P_FAR, P_LOCAL, P_PLAIN, PARTS, Registry, graph, parts_for, walked

registry = Registry()
EPS = 1e-2
ENTITY = "entity"


def _steps(name: str, params: WalkParams, variant=BASE, share: float | None = None, approx: float | None = None, of: str = "user") -> None:
    def query(spark, sf_dir):
        edges = graph(spark, sf_dir, of)
        popular = stats.popular(edges, share=share) if share is not None else None
        run = engine.Engine.of_edges(edges, parts=parts_for(edges))
        try:
            return run.walk(params, variant, popular=popular, eps=approx or 0.0).steps()
        finally:
            run.close()

    registry.add(name, query, oracle.walk_sql(of, params, approx=approx))


_steps("walk_base_local_bias", P_LOCAL)
_steps("walk_base_far_bias", P_FAR)
_steps("walk_base_entity", P_FAR, of=ENTITY)
_steps("walk_local", P_LOCAL, LOCAL)
_steps("walk_switch", P_LOCAL, SWITCH, 0.05)
_steps("walk_cache_eager", P_FAR, CACHE, 0.05)
_steps("walk_cache_lazy", P_FAR, LAZY, 0.05)
_steps("walk_approx", P_LOCAL, APPROX, 0.05, 2e-2)
_steps("walk_approx_zero", P_LOCAL, APPROX, 0.05, 0.0)
_steps("walk_approx_entity", P_LOCAL, APPROX, 0.05, EPS, ENTITY)


@registry(oracle.walk_sql("user", P_LOCAL.but(length=1)))
def walk_static_first_step(spark, sf_dir):
    return walked(spark, sf_dir, params=P_LOCAL.but(length=1))[1].steps()


@registry(oracle.walk_sql("user", P_PLAIN))
def walk_first_order(spark, sf_dir):
    return baselines.first_order_walk(graph(spark, sf_dir), P_PLAIN)


@registry(oracle.walk_sql("user", P_LOCAL.but(walks_per_vertex=2)))
def walk_rounds(spark, sf_dir):
    run = engine.Engine.of_edges(graph(spark, sf_dir), parts=PARTS)
    out = None
    for part in engine.walk_rounds(run, P_LOCAL.but(walks_per_vertex=2), 2):
        out = part.steps() if out is None else out.unionByName(part.steps())
    return out


@registry(oracle.walk_sql("user", P_LOCAL))
def walk_precomputed_cdf(spark, sf_dir):
    return baselines.walk_precomputed(graph(spark, sf_dir), P_LOCAL)


@registry()
def walk_precomputed_alias(spark, sf_dir):
    return baselines.walk_precomputed(graph(spark, sf_dir), P_LOCAL, "alias")


@registry(oracle.walk_sql("user", P_LOCAL, sql=oracle.trimmed_sql("user", 30)))
def walk_trimmed(spark, sf_dir):
    return baselines.walk_trimmed(graph(spark, sf_dir), P_LOCAL)


@registry(oracle.walk_sql("user", P_LOCAL, sql=oracle.trimmed_sql("user", 30)))
def walk_trimmed_append_only(spark, sf_dir):
    return baselines.walk_trimmed(graph(spark, sf_dir), P_LOCAL, rewrite=False)


@registry(oracle.walk_sql("user", P_LOCAL))
def walk_resident(spark, sf_dir):
    return engine.walk_resident(graph(spark, sf_dir), P_LOCAL)


@registry(oracle.walk_sql("user", P_LOCAL, approx=2e-2))
def walk_resident_approx(spark, sf_dir):
    edges = graph(spark, sf_dir)
    return engine.walk_resident(edges, P_LOCAL, popular=stats.popular(edges, share=0.05), eps=2e-2)


@registry(oracle.walk_sql("copart", P_FAR))
def walk_resident_copart(spark, sf_dir):
    return engine.walk_resident(graph(spark, sf_dir, "copart"), P_FAR)


@registry(oracle.walk_sql("user", P_LOCAL.but(length=4)))
def walk_chunked(spark, sf_dir):
    return engine.walk_chunked(model.adjacency(graph(spark, sf_dir), chunk=16), P_LOCAL.but(length=4)).steps()


@registry()
def walk_reject(spark, sf_dir):
    return engine.walk_resident(graph(spark, sf_dir), P_LOCAL, reject=True)


_DAG = f"SELECT src, dst, w FROM ({SQL['user']}) WHERE src < dst"


@registry(oracle.walk_sql("user", P_LOCAL, sql=_DAG))
def walk_directed(spark, sf_dir):
    edges = written(graph(spark, sf_dir).where("src < dst"), "dag")
    return engine.Engine.of_edges(edges, parts=PARTS).walk(P_LOCAL.but(directed=True)).steps()


@registry(oracle.walk_sql("user", P_FAR, starts="SELECT DISTINCT src AS start FROM edges WHERE src % 3 = 1"))
def walk_subset(spark, sf_dir):
    edges = graph(spark, sf_dir)
    return engine.Engine.of_edges(edges, parts=PARTS).walk(P_FAR, starts=edges.where("src % 3 = 1").select(F.col("src").alias("vid"))).steps()


@registry(oracle.walk_sql("user", P_LOCAL, "SELECT start, CAST(round AS INT) AS round, string_agg(CAST(cur AS VARCHAR), ' ' ORDER BY step) AS path FROM walk GROUP BY start, round"))
def walk_paths(spark, sf_dir):
    return walked(spark, sf_dir)[1].paths().select("start", "round", F.array_join(F.col("path").cast("array<string>"), " ").alias("path"))


@registry(oracle.walk_sql("user", P_LOCAL, "SELECT a.cur AS center, b.cur AS context, count(*) AS n FROM walk a JOIN walk b ON a.start = b.start AND a.round = b.round AND b.step BETWEEN a.step - 2 AND a.step + 2 AND a.step <> b.step GROUP BY 1, 2"))
def walk_context_pairs(spark, sf_dir):
    return embed.context_pairs(walked(spark, sf_dir)[1].steps(), 2).groupBy("center", "context").agg(F.count("*").alias("n"))


@registry(oracle.walk_sql("user", P_LOCAL, "SELECT cur AS vertex, count(*) AS n FROM walk GROUP BY 1"))
def walk_corpus_counts(spark, sf_dir):
    return walked(spark, sf_dir)[1].steps().groupBy("vertex").agg(F.count("*").alias("n"))


@registry()
def walk_fast_draws(spark, sf_dir):
    return walked(spark, sf_dir, params=WalkParams(0.5, 2.0, length=6, walks_per_vertex=1, rng="xxhash64"))[1].steps()


def _cost(name: str, query, select: str, params: WalkParams = P_PLAIN, of: str = ENTITY, share: float = 0.05, approx: float | None = None) -> None:
    registry.add(name, query, oracle.walk_sql(of, params, select, share=share, approx=approx))


def _entity_walk(spark, sf_dir, params=P_PLAIN, variant=BASE, popular_share=None, eps=0.0, parts=None):
    edges = graph(spark, sf_dir, ENTITY)
    popular = stats.popular(edges, share=popular_share) if popular_share else None
    run = engine.Engine.of_edges(edges, parts=parts or parts_for(edges))
    try:
        return edges, popular, run.walk(params, variant, popular=popular, eps=eps)
    finally:
        run.close()


_LAST = P_PLAIN.length
_cost("cost_message_curve", lambda s, d: (lambda e, _, w: accounting.message_curve(w.steps(), e))(*_entity_walk(s, d)), f"SELECT CAST(step AS INT) AS step, count(*) AS n_walkers, CAST(sum(deg) AS BIGINT) AS n_ids, CAST(8 * sum(deg) AS BIGINT) AS bytes FROM walk JOIN deg ON vid = prev WHERE step > 0 AND step < {_LAST} GROUP BY step")
_cost("cost_visit_frequency", lambda s, d: (lambda e, _, w: accounting.visit_frequency(w.steps(), e, 200))(*_entity_walk(s, d)), "SELECT CAST(ceil(deg / 200) * 200 AS BIGINT) AS bucket, count(*) AS n_vertices, CAST(sum(coalesce(n, 0)) AS BIGINT) AS n_visits, sum(coalesce(n, 0)) / count(*) AS mean_visits FROM deg LEFT JOIN (SELECT cur, count(*) AS n FROM walk WHERE step > 0 GROUP BY cur) ON cur = vid GROUP BY 1")
_BASE_BYTES = f"SELECT CAST(16 * sum(deg) + 8 * count(*) * {_LAST + 1} AS BIGINT) AS b FROM deg"
_cost("cost_memory_breakdown", lambda s, d: (lambda e, _, w: accounting.memory_breakdown(w.steps(), e, 1, _LAST))(*_entity_walk(s, d)), f"SELECT CAST(step AS INT) AS step, b AS base_bytes, m AS message_bytes, m / (b + m) AS message_share FROM (SELECT step, CAST(8 * sum(deg) AS BIGINT) AS m FROM walk JOIN deg ON vid = prev WHERE step > 0 AND step < {_LAST} GROUP BY step), ({_BASE_BYTES})")
_same = f"{oracle.PART.format('prev', PARTS)} = {oracle.PART.format('cur', PARTS)}"
_cost("cost_local_saved", lambda s, d: (lambda e, _, w: accounting.local_saved(w.steps(), e, PARTS))(*_entity_walk(s, d)), f"SELECT count(*) AS n_moves, CAST(count(*) FILTER ({_same}) AS BIGINT) AS n_local, CAST(sum(deg) AS BIGINT) AS n_ids, CAST(coalesce(sum(deg) FILTER ({_same}), 0) AS BIGINT) AS local_ids FROM walk JOIN deg ON vid = prev WHERE step > 0 AND step < {_LAST}")
_cost("cost_cache_saved", lambda s, d: (lambda e, p, w: accounting.cache_saved(w.steps(), e, p, PARTS))(*_entity_walk(s, d, popular_share=0.05)), f"""SELECT count(*) AS n_refs, CAST(count(*) FILTER (n = 1) AS BIGINT) AS n_first, CAST(coalesce(sum(deg), 0) AS BIGINT) AS ids_without, CAST(coalesce(sum(deg) FILTER (n = 1), 0) AS BIGINT) AS ids_with FROM (
SELECT deg.deg, row_number() OVER (PARTITION BY prev, {oracle.PART.format('cur', PARTS)} ORDER BY step, start, round) AS n FROM walk JOIN deg ON deg.vid = prev JOIN pop ON pop.vid = prev WHERE step > 0 AND step < {_LAST} AND NOT ({_same}))""")
_cost("cost_switch_supersteps", lambda s, d: (lambda e, p, w: accounting.switch_supersteps(w.steps(), p))(*_entity_walk(s, d, popular_share=0.05)), f"""SELECT start, CAST(round AS INT) AS round, count(*) AS moves, CAST(count(*) + count(*) FILTER (a.vid IS NOT NULL AND b.vid IS NULL AND step < {_LAST}) AS BIGINT) AS supersteps
FROM walk LEFT JOIN pop a ON a.vid = prev LEFT JOIN pop b ON b.vid = cur WHERE step > 0 GROUP BY 1, 2""")
_cost("cost_approx_rate", lambda s, d: (lambda e, p, w: accounting.approx_rate(w.log()))(*_entity_walk(s, d, P_LOCAL, APPROX, 0.05, EPS)), f"SELECT count(*) FILTER (step < {P_LOCAL.length}) AS n_moves, CAST(count(*) FILTER (step > 1 AND skipped) AS BIGINT) AS n_static FROM walk WHERE step > 0", P_LOCAL, approx=EPS)


@registry(f"""WITH {oracle.edges_cte(ENTITY)}, {oracle.DEG} SELECT CAST(8 * sum(deg) AS BIGINT) AS topology, CAST(8 * sum(deg) AS BIGINT) AS weights, CAST(8 * count(*) * 81 AS BIGINT) AS vertex_values FROM deg""")
def cost_base_memory(spark, sf_dir):
    return accounting.base_memory(graph(spark, sf_dir, ENTITY), 1, 80)


@registry()
def cost_message_log(spark, sf_dir):
    edges, popular, walk = _entity_walk(spark, sf_dir, P_LOCAL, CACHE, 0.05, parts=PARTS)
    return walk.messages()


@registry(" UNION ALL ".join(f"SELECT '{g}' AS graph, 8 * sum(d * d) <= 200000000 AS precomputed FROM (SELECT count(*) AS d FROM ({SQL[g]}) GROUP BY src)" for g in ("user", "copart", "entity")))
def cost_feasible(spark, sf_dir):
    rows = [(g, accounting.feasible(graph(spark, sf_dir, g), "precomputed", 200_000_000)) for g in ("user", "copart", "entity")]
    return spark.createDataFrame(rows, "graph string, precomputed boolean")


def _predicted(spark, sf_dir):
    """A fixed prediction of quality to score: documents of at least 500 characters are good."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), (F.col("n_chars") >= 500).cast("int").alias("label"))
    truth = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("vid"), F.col("quality").alias("label"))
    return docs.join(truth.select("vid"), "vid", "left_semi"), truth


_F1 = """WITH p AS (SELECT d.doc_id AS vid, CAST(n_chars >= 500 AS INT) AS label FROM documents d JOIN labels USING (doc_id)), t AS (SELECT doc_id AS vid, quality AS label FROM labels),
c AS (SELECT label, count(*) FILTER (p AND t) AS tp, count(*) FILTER (p AND NOT t) AS fp, count(*) FILTER (t AND NOT p) AS fn FROM (
  SELECT coalesce(p.label, t.label) AS label, p.vid IS NOT NULL AS p, t.vid IS NOT NULL AS t FROM p FULL JOIN t ON p.vid = t.vid AND p.label = t.label) GROUP BY label)"""


@registry(_F1 + " SELECT round(2 * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn)), 9) AS f1 FROM c")
def acc_f1_micro(spark, sf_dir):
    return evaluate.f1(*_predicted(spark, sf_dir)).withColumn("f1", F.round("f1", 9))


@registry(_F1 + " SELECT round(avg(2 * tp / (2 * tp + fp + fn)), 9) AS f1 FROM c")
def acc_f1_macro(spark, sf_dir):
    return evaluate.f1(*_predicted(spark, sf_dir), "macro").withColumn("f1", F.round("f1", 9))


_OBSERVED = f"o AS (SELECT a.prev AS u, a.cur AS v, b.cur AS x, count(*) AS n FROM walk a JOIN walk b ON a.start = b.start AND a.round = b.round AND b.step = a.step + 1 WHERE a.prev IS NOT NULL GROUP BY 1, 2, 3), tot AS (SELECT u, v, sum(n) AS total FROM o GROUP BY 1, 2)"
_back, _common, _other = P_LOCAL.scaled()
_EXACT = f"""d AS (SELECT a.src AS u, a.dst AS v, e.dst AS x, e.w, CASE WHEN e.dst = a.src THEN {_back} WHEN c.src IS NOT NULL THEN {_common} ELSE {_other} END * e.w AS pi
FROM edges a JOIN edges e ON e.src = a.dst LEFT JOIN edges c ON c.src = a.src AND c.dst = e.dst), t AS (SELECT u, v, x, w, pi / sum(pi) OVER (PARTITION BY u, v) AS prob, w / sum(w) OVER (PARTITION BY u, v) AS static FROM d)"""


@registry("WITH RECURSIVE " + ", ".join([oracle.edges_cte("user"), oracle.DEG, oracle.popular_cte(), oracle.walk_ctes(P_LOCAL.but(walks_per_vertex=4)), _OBSERVED, _EXACT]) + """
SELECT u, v, CAST(any_value(total) AS BIGINT) AS n, round(0.5 * sum(abs(coalesce(n, 0) / total - prob)), 9) AS tv, round(sum((coalesce(n, 0) - prob * total) * (coalesce(n, 0) - prob * total) / (prob * total)), 6) AS chi_square
FROM t JOIN tot USING (u, v) LEFT JOIN o USING (u, v, x) GROUP BY u, v""")
def acc_walk_distance(spark, sf_dir):
    edges, walk = walked(spark, sf_dir, params=P_LOCAL.but(walks_per_vertex=4))
    out = evaluate.walk_distance(walk.steps(), edges, P_LOCAL)
    return out.select("u", "v", "n", F.round("tv", 9).alias("tv"), F.round("chi_square", 6).alias("chi_square"))


_low, _high = oracle.bounds_sql("du.deg", "dv.deg", "dv.wmin", "dv.wmax", 0.5, 2.0)


@registry(f"""WITH {oracle.edges_cte('user', f"SELECT src, dst, 1::BIGINT AS w FROM ({SQL['user']})")}, {oracle.DEG}, {oracle.popular_cte()}, {_EXACT}, p AS (
SELECT src AS u, dst AS v, {_low} AS low, {_high} AS high FROM edges JOIN deg du ON du.vid = src JOIN deg dv ON dv.vid = dst JOIN pop pv ON pv.vid = dst LEFT JOIN pop pu ON pu.vid = src WHERE pu.vid IS NULL)
SELECT u, v, round(max(abs(static - prob)) FILTER (x <> u), 9) AS max_error, round(max(greatest(high - static, static - low)) FILTER (x <> u), 9) AS max_allowed, round(max(abs(static - prob)) FILTER (x = u), 9) AS return_error, round(0.5 * sum(abs(static - prob)), 9) AS tv
FROM t JOIN p USING (u, v) WHERE high - low < 0.05 GROUP BY u, v""")
def acc_approx_error(spark, sf_dir):
    edges = graph(spark, sf_dir).withColumn("w", F.lit(1).cast("long"))
    out = evaluate.approx_error(edges, stats.popular(edges, share=0.05), P_LOCAL, 0.05)
    return out.select("u", "v", *[F.round(c, 9).alias(c) for c in ("max_error", "max_allowed", "return_error", "tv")])


@registry("WITH RECURSIVE " + ", ".join([oracle.edges_cte("user"), oracle.DEG, oracle.popular_cte(), oracle.walk_ctes(P_PLAIN.but(length=20)), "v AS (SELECT src AS vid, sum(w) AS ws FROM edges GROUP BY src)", "c AS (SELECT cur, count(*) AS n FROM walk WHERE step > 10 GROUP BY cur)"]) + " SELECT round(0.5 * sum(abs(coalesce(n, 0) / (SELECT sum(n) FROM c) - ws / (SELECT sum(ws) FROM v))), 9) AS tv FROM v LEFT JOIN c ON cur = vid")
def acc_stationary_gap(spark, sf_dir):
    edges = graph(spark, sf_dir)
    return evaluate.stationary_gap(engine.walk_resident(edges, P_PLAIN.but(length=20)), edges).withColumn("tv", F.round("tv", 9))


@registry()
def embed_vectors(spark, sf_dir):
    return embed.embed(engine.walk_resident(graph(spark, sf_dir), P_LOCAL.but(length=20)), dim=16)


@registry()
def embed_blocks(spark, sf_dir):
    return embed.embed(engine.walk_resident(graph(spark, sf_dir), P_LOCAL.but(length=10)), dim=16, engine="blocks", epochs=1)


@registry()
def embed_similar(spark, sf_dir):
    return embed.similar(embed_vectors(spark, sf_dir), 1, 10)


def _classified(spark, sf_dir, walk):
    edges = graph(spark, sf_dir, "doc")
    labels = table(spark, sf_dir, "documents").where("lang IS NOT NULL").select(F.col("doc_id").alias("vid"), F.array((F.crc32(F.col("lang").cast("binary")) % 1000).cast("int")).alias("labels"))
    vectors = embed.embed(walk(edges), dim=24)
    rows = [(a, float(evaluate.f1(*found, a).first()[0])) for found in [evaluate.classify(vectors, labels, 0.5)] for a in ("micro", "macro")]
    return spark.createDataFrame(rows, "average string, f1 double")


@registry()
def classify_scores(spark, sf_dir):
    return _classified(spark, sf_dir, lambda e: engine.walk_resident(e, P_LOCAL.but(length=20)))


@registry()
def classify_scores_trimmed(spark, sf_dir):
    return _classified(spark, sf_dir, lambda e: engine.walk_resident(stats.trim(e, 30), P_LOCAL.but(length=20)))


@registry()
def link_features_auc(spark, sf_dir):
    edges = graph(spark, sf_dir)
    vectors = embed.embed(engine.walk_resident(edges, P_LOCAL.but(length=20)), dim=16)
    some = edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(1).alias("label"))
    v = edges.select(F.col("src").alias("a")).distinct()
    none = v.withColumn("b", F.col("a") + 1 + F.pmod(F.xxhash64("a"), F.lit(40))).join(v.select(F.col("a").alias("b")), "b", "left_semi").join(some, ["a", "b"], "left_anti").withColumn("label", F.lit(0))
    return spark.createDataFrame([(evaluate.link_auc(embed.edge_features(vectors, some.unionByName(none))),)], "auc double")


@registry()
def synth_planted_accuracy(spark, sf_dir):
    """Micro-F1 of exact, approximate and trimmed walks on planted communities: trimming loses."""
    edges, labels = synth.planted(spark, n=500, groups=5)
    edges, params = written(edges, "planted"), P_LOCAL.but(length=30, walks_per_vertex=2)
    popular = stats.popular(edges, share=0.05)
    walks = {"exact": engine.walk_resident(edges, params), "approx": engine.walk_resident(edges, params, popular=popular, eps=1e-3), "trimmed": engine.walk_resident(stats.trim(edges), params)}
    rows = [(n, float(evaluate.f1(*evaluate.classify(embed.embed(w, dim=32), labels, 0.5)).first()[0])) for n, w in walks.items()]
    return spark.createDataFrame(rows, "variant string, f1 double")
