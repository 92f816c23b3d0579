"""DuckDB text of walks and walk measures, generated from the parameters and an edge query."""

from __future__ import annotations


from ..config import WalkParams
from ..graph.build import SQL
from ..walk.rng import draw48_sql

DEG = "deg AS (SELECT src AS vid, count(*) AS deg, min(w) AS wmin, max(w) AS wmax FROM edges GROUP BY src)"
PART = "(xor({0}, {0} >> 16) % {1})"


def edges_cte(graph: str, sql: str | None = None) -> str:
    return f"edges AS MATERIALIZED ({sql or SQL[graph]})"


def popular_cte(share: float = 0.05) -> str:
    return f"pop AS (SELECT vid FROM (SELECT vid, row_number() OVER (ORDER BY deg DESC, vid) AS n FROM deg) WHERE n <= ceil({share} * (SELECT count(*) FROM deg)))"


def bounds_sql(du: str, dv: str, wmin: str, wmax: str, p: float, q: float, form: str = "tight") -> tuple[str, str]:
    """(low, high), in the order of operations of the engine."""
    most = f"least({du} - 1, {dv} - 1)" if form == "tight" else f"least({du}, {dv} - 1)"
    none = f"({1 / p!r}::DOUBLE + ({dv} - 1) / {q!r}::DOUBLE)"
    full = f"({1 / p!r}::DOUBLE + {most} + ({dv} - 1 - {most}) / {q!r}::DOUBLE)"
    low = f"({min(1.0, 1 / q)!r}::DOUBLE * {wmin} / (greatest({none}, {full}) * {wmax}))"
    high = f"least(1.0::DOUBLE, {max(1.0, 1 / q)!r}::DOUBLE * {wmax} / (least({none}, {full}) * {wmin}))"
    return low, high


def walk_ctes(params: WalkParams, starts: str = "SELECT DISTINCT src AS start FROM edges", approx: float | None = None) -> str:
    """CTE ``walk`` (start, round, step, prev, cur, skipped); needs ``edges``, and for ``approx`` also ``deg`` and ``pop``."""
    back, common, other = params.scaled()
    draw = draw48_sql(str(params.seed), "w.round", "w.start", "w.step + 1")
    factor = f"CASE WHEN w.prev IS NULL THEN 1 WHEN e.dst = w.prev THEN {back} WHEN b.src IS NOT NULL THEN {common} ELSE {other} END"
    extra, static = "", "FALSE"
    if approx is not None:
        low, high = bounds_sql("du.deg", "dv.deg", "dv.wmin", "dv.wmax", params.p, params.q)
        extra = "LEFT JOIN deg du ON du.vid = w.prev LEFT JOIN deg dv ON dv.vid = w.cur LEFT JOIN pop pu ON pu.vid = w.prev LEFT JOIN pop pv ON pv.vid = w.cur"
        static = f"(w.prev IS NOT NULL AND pu.vid IS NULL AND pv.vid IS NOT NULL AND {high} - {low} < {approx!r})"
        if approx:
            factor = f"CASE WHEN {static} THEN 1 ELSE {factor} END"
    return f"""walk(start, round, step, prev, cur, skipped) AS (
  SELECT s.start, r.round, 0::BIGINT, NULL::BIGINT, s.start, FALSE FROM ({starts}) s, (SELECT unnest(range({params.walks_per_vertex})) AS round) r
  UNION ALL
  SELECT start, round, step + 1, cur, nxt, skip FROM (
    SELECT m.*, sum(mass) OVER (PARTITION BY start, round ORDER BY nxt) AS upto, draw % (sum(mass) OVER (PARTITION BY start, round)) AS target
    FROM (SELECT w.start, w.round, w.step, w.cur, e.dst AS nxt, {draw} AS draw, e.w * ({factor}) AS mass, {static} AS skip
          FROM walk w JOIN edges e ON e.src = w.cur LEFT JOIN edges b ON b.src = w.prev AND b.dst = e.dst {extra} WHERE w.step < {params.length}) m
  ) WHERE upto > target AND upto - mass <= target
)"""


def walk_sql(graph: str, params: WalkParams, select: str = "SELECT start, CAST(round AS INT) AS round, CAST(step AS INT) AS step, cur AS vertex FROM walk", starts: str | None = None, approx: float | None = None, share: float = 0.05, sql: str | None = None) -> str:
    ctes = [edges_cte(graph, sql), DEG, popular_cte(share)]
    return "WITH RECURSIVE " + ",\n".join([*ctes, walk_ctes(params, *([starts] if starts else []), approx=approx)]) + "\n" + select


def trimmed_sql(graph: str, k: int) -> str:
    return f"SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS n FROM ({SQL[graph]})) WHERE n <= {k}"


def transitions_sql(graph: str, params: WalkParams, select: str, sql: str | None = None) -> str:
    """CTE ``t`` (u, v, x, w, dist, pi, total)."""
    back, common, other = params.scaled()
    by = f"CASE dist WHEN 0 THEN {back} WHEN 1 THEN {common} ELSE {other} END"
    return f"""WITH {edges_cte(graph, sql)}, {DEG}, {popular_cte()}, d AS (
  SELECT a.src AS u, a.dst AS v, e.dst AS x, e.w, CASE WHEN e.dst = a.src THEN 0 WHEN c.src IS NOT NULL THEN 1 ELSE 2 END AS dist
  FROM edges a JOIN edges e ON e.src = a.dst LEFT JOIN edges c ON c.src = a.src AND c.dst = e.dst
), t AS (SELECT *, w * {by} AS pi, sum(w * {by}) OVER (PARTITION BY u, v) AS total FROM d) {select}"""


def scale(params: WalkParams) -> int:
    """What one unit of factor 1 is in whole factors."""
    return params.scaled()[1]


__all__ = ["DEG", "PART", "bounds_sql", "edges_cte", "popular_cte", "scale", "transitions_sql", "trimmed_sql", "walk_ctes", "walk_sql"]
