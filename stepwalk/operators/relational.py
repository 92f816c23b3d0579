"""Joins, aggregates, windows, set operations and the rest that users of walks need, each beside its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph.build import GRAPHS, SQL
from ..graph.stats import bucket
from ..plans import oracle
from ..plans.shared import P_LOCAL, Registry, walked
from ..sources.tables import table

registry = Registry()
add = registry.add

USER, ENTITY = SQL["user"], SQL["entity"]


def edges(s, d, name="user") -> DataFrame:
    return GRAPHS[name](s, d)


def events(s, d) -> DataFrame:
    return table(s, d, "events")


def lines(s, d) -> DataFrame:
    return table(s, d, "lineitem")


def degree(s, d, name="user") -> DataFrame:
    return edges(s, d, name).groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))


def on_edges(select: str, name: str = "user") -> str:
    return f"WITH {oracle.edges_cte(name)}, {oracle.DEG} {select}"


def on_walk(select: str) -> str:
    return oracle.walk_sql("user", P_LOCAL, select)


def steps(s, d) -> DataFrame:
    return walked(s, d)[1].steps()


# Filters and projections.
add("op_filter_weight", lambda s, d: edges(s, d).where("w >= 2"), on_edges("SELECT src, dst, w FROM edges WHERE w >= 2"))
add("op_filter_time_slice", lambda s, d: lines(s, d).where("l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'").select("l_partkey", "l_suppkey"), "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'")
add("op_filter_in", lambda s, d: events(s, d).where(F.col("event_type").isin("view", "purchase")).select("event_id", "event_type"), "SELECT event_id, event_type FROM events WHERE event_type IN ('view', 'purchase')")
add("op_filter_like", lambda s, d: table(s, d, "part").where(F.col("p_name").like("%ring%") | F.col("p_brand").rlike("^Brand#1[0-9]$")).select("p_partkey", "p_name"), "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%ring%' OR regexp_matches(p_brand, '^Brand#1[0-9]$')")
add("op_filter_between", lambda s, d: edges(s, d).where(F.col("src").between(10, 20)), on_edges("SELECT src, dst, w FROM edges WHERE src BETWEEN 10 AND 20"))
add("op_filter_null_safe", lambda s, d: events(s, d).where(F.when(F.col("user_id") % 3 != 0, F.col("user_id") % 3).eqNullSafe(F.when(F.col("event_id") % 2 == 0, F.lit(1)))).select("event_id"), "SELECT event_id FROM events WHERE (CASE WHEN user_id % 3 <> 0 THEN user_id % 3 END) IS NOT DISTINCT FROM (CASE WHEN event_id % 2 = 0 THEN 1 END)")
add("op_case_when", lambda s, d: edges(s, d).select("src", "dst", F.when(F.col("w") == 1, "weak").when(F.col("w") < 4, "medium").otherwise("strong").alias("kind")), on_edges("SELECT src, dst, CASE WHEN w = 1 THEN 'weak' WHEN w < 4 THEN 'medium' ELSE 'strong' END AS kind FROM edges"))
add("op_project_expr", lambda s, d: lines(s, d).selectExpr("l_orderkey", "l_linenumber + 1 AS nth", "round(l_extendedprice * (1 - l_discount), 4) AS net"), "SELECT l_orderkey, l_linenumber + 1 AS nth, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
add("op_cast_types", lambda s, d: lines(s, d).select("l_orderkey", F.col("l_quantity").cast("long").alias("q"), F.col("l_extendedprice").cast("decimal(18,4)").alias("price"), F.col("l_returnflag").try_cast("int").alias("none")), "SELECT l_orderkey, CAST(l_quantity AS BIGINT) AS q, CAST(l_extendedprice AS DECIMAL(18,4)) AS price, TRY_CAST(l_returnflag AS INT) AS none FROM lineitem")

# Joins.
add("op_join_inner", lambda s, d: events(s, d).select("event_id", F.col("user_id").alias("src")).join(degree(s, d).withColumnRenamed("vid", "src"), "src").select("event_id", "src", "deg"), on_edges("SELECT event_id, user_id AS src, deg FROM events JOIN deg ON vid = user_id"))
add("op_join_broadcast", lambda s, d: edges(s, d, "entity").join(F.broadcast(degree(s, d, "entity").where("deg >= 500").select(F.col("vid").alias("dst"), "deg")), "dst").select("src", "dst", "deg"), on_edges("SELECT src, dst, deg FROM edges JOIN deg ON vid = dst WHERE deg >= 500", "entity"))
_ORDERS = "SELECT l_orderkey, l_linenumber, l_partkey, o_custkey FROM lineitem JOIN orders ON o_orderkey = l_orderkey"
for _hint in ("merge", "shuffle_hash"):
    add(f"op_join_{'sort_merge' if _hint == 'merge' else _hint}", lambda s, d, h=_hint: lines(s, d).join(table(s, d, "orders").hint(h), F.col("o_orderkey") == F.col("l_orderkey")).select("l_orderkey", "l_linenumber", "l_partkey", "o_custkey"), _ORDERS)


# Queries whose name ends in _all are the whole of those without the ending, which are slices by id.
_PROBE = "SELECT a.src AS prev, a.dst AS cur, b.dst AS x, c.src IS NOT NULL AS is_common FROM edges a JOIN edges b ON b.src = a.dst LEFT JOIN edges c ON c.src = a.src AND c.dst = b.dst"


def _probe(s, d, of="true"):
    e = edges(s, d)
    a, b = e.where(of).select(F.col("src").alias("prev"), F.col("dst").alias("cur")), e.select(F.col("src").alias("cur"), F.col("dst").alias("x"))
    c = e.select(F.col("src").alias("prev"), F.col("dst").alias("x"), F.lit(True).alias("hit"))
    return a.join(b, "cur").join(c, ["prev", "x"], "left").select("prev", "cur", "x", F.col("hit").isNotNull().alias("is_common"))


add("op_join_left_probe", lambda s, d: _probe(s, d, "src <= 20"), on_edges(_PROBE + " WHERE a.src <= 20"))
add("op_join_left_probe_all", _probe, on_edges(_PROBE))


_SLICE = "SELECT l_partkey AS vid, count(*) AS n FROM lineitem WHERE {} GROUP BY 1"
_EARLY, _LATE = "l_shipdate < TIMESTAMP '1998-01-01' AND l_partkey % 2 = 0", "l_shipdate >= TIMESTAMP '1998-01-01' AND l_partkey % 3 = 0"


def _full(name, early, late):
    def query(s, d):
        side = lambda where, n: lines(s, d).where(where).groupBy(F.col("l_partkey").alias("vid")).agg(F.count("*").alias(n))
        return side(early, "a").join(side(late, "b"), "vid", "full").select("vid", (F.coalesce("b", F.lit(0)) - F.coalesce("a", F.lit(0))).alias("change"))

    add(name, query, f"SELECT coalesce(a.vid, b.vid) AS vid, coalesce(b.n, 0) - coalesce(a.n, 0) AS change FROM ({_SLICE.format(early)}) a FULL JOIN ({_SLICE.format(late)}) b ON a.vid = b.vid")


_full("op_join_full", _EARLY, _LATE)
_full("op_join_full_all", _EARLY.split(" AND ")[0], _LATE.split(" AND ")[0])

add("op_join_semi", lambda s, d: edges(s, d).join(events(s, d).where("event_type = 'purchase' AND value > 30").select(F.col("user_id").alias("src")), "src", "left_semi"), on_edges("SELECT src, dst, w FROM edges WHERE src IN (SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 30)"))
add("op_join_anti", lambda s, d: edges(s, d).join(events(s, d).where("event_type = 'purchase' AND value > 30").select(F.col("user_id").alias("src")), "src", "left_anti"), on_edges("SELECT src, dst, w FROM edges WHERE NOT EXISTS (SELECT 1 FROM events WHERE user_id = src AND event_type = 'purchase' AND value > 30)"))


@registry(on_edges("SELECT e.src, e.dst FROM edges e JOIN deg a ON a.vid = e.src JOIN deg b ON b.vid = e.dst AND a.deg < b.deg", "entity"))
def op_join_theta(s, d):
    g = degree(s, d, "entity")
    rows = edges(s, d, "entity").join(g.select(F.col("vid").alias("src"), F.col("deg").alias("da")), "src")
    return rows.join(g.select(F.col("vid").alias("dst"), F.col("deg").alias("db")), "dst").where("da < db").select("src", "dst")


@registry(on_edges("SELECT vid, hi AS bucket FROM deg JOIN (SELECT unnest(range(20, 1420, 20)) AS hi) ON deg > hi - 20 AND deg <= hi", "entity"))
def op_join_range(s, d):
    """Degrees to the bucket that holds them: the range is turned into an equality on the bucket's number."""
    ends = s.range(20, 1420, 20).select(F.col("id").alias("hi"))
    return degree(s, d, "entity").withColumn("hi", bucket(20)).join(ends, "hi").select("vid", F.col("hi").alias("bucket"))


@registry("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE AND a.user_id <> b.user_id")
def op_join_interval(s, d):
    """Events within ten minutes of each other: each row meets its own ten-minute slot and the next, by equality."""
    a = events(s, d).select(F.col("event_id").alias("first_id"), F.col("ts").alias("ta"), F.col("user_id").alias("ua"))
    b = events(s, d).select(F.col("event_id").alias("second_id"), F.col("ts").alias("tb"), F.col("user_id").alias("ub"))
    slot = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / 600_000_000)
    a = a.withColumn("slot", F.explode(F.array(slot("ta"), slot("ta") + 1)))
    b = b.withColumn("slot", slot("tb"))
    return a.join(b, "slot").where("tb > ta AND tb <= ta + INTERVAL 10 MINUTES AND ua <> ub").select("first_id", "second_id")


@registry("SELECT v.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON v.user_id = p.user_id AND v.ts >= p.ts")
def op_join_asof(s, d):
    """The last purchase at or before each view, by one sorted pass per user."""
    rows = events(s, d).where(F.col("event_type").isin("view", "purchase"))
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") != "purchase", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(order)
    return rows.withColumn("purchase_id", last).where("event_type = 'view'").select("event_id", "purchase_id")


@registry(on_edges("SELECT a.vid AS a, b.vid AS b FROM deg a CROSS JOIN deg b WHERE a.vid <= 15 AND b.vid <= 15 AND a.vid < b.vid"))
def op_join_cross(s, d):
    """Candidate pairs of a stated, small set of users."""
    v = degree(s, d).where("vid <= 15")
    return v.select(F.col("vid").alias("a")).crossJoin(v.select(F.col("vid").alias("b"))).where("a < b")


_TRIANGLE = "SELECT a.src AS x, a.dst AS y, b.dst AS z FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = a.src AND c.dst = b.dst WHERE a.src < a.dst AND a.dst < b.dst"


def _triangle(s, d, of="true"):
    up = edges(s, d).where("src < dst").select("src", "dst")
    first, second, third = up.where(of).toDF("x", "y"), up.toDF("y", "z"), up.toDF("x", "z")
    return first.join(second, "y").join(third, ["x", "z"]).select("x", "y", "z")


add("op_join_self_triangle", lambda s, d: _triangle(s, d, "src <= 10"), on_edges(_TRIANGLE + " AND a.src <= 10"))
add("op_join_self_triangle_all", _triangle, on_edges(_TRIANGLE))


# Aggregates.
add("op_agg_hash", lambda s, d: edges(s, d).groupBy("src").agg(F.sum("w").alias("s"), F.avg("w").alias("a"), F.min("w").alias("lo"), F.max("w").alias("hi")), on_edges("SELECT src, CAST(sum(w) AS BIGINT) AS s, avg(w) AS a, min(w) AS lo, max(w) AS hi FROM edges GROUP BY src"))
add("op_agg_distinct", lambda s, d: lines(s, d).groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("n")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
add("op_agg_filter", lambda s, d: events(s, d).groupBy("user_id").agg(F.count(F.when(F.col("event_type") == "view", 1)).alias("views"), F.sum(F.when(F.col("value") > 10, 1).otherwise(0)).alias("big")), "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, CAST(sum(CASE WHEN value > 10 THEN 1 ELSE 0 END) AS BIGINT) AS big FROM events GROUP BY 1")
add("op_agg_stats", lambda s, d: edges(s, d, "entity").groupBy("src").agg(F.round(F.stddev("w"), 6).alias("sd"), F.round(F.var_pop("w"), 6).alias("vp")), on_edges("SELECT src, round(stddev_samp(w), 6) AS sd, round(var_pop(w), 6) AS vp FROM edges GROUP BY src", "entity"))
add("op_agg_percentile", lambda s, d: degree(s, d, "entity").agg(F.expr("percentile(deg, 0.9)").alias("p90"), F.median("deg").alias("p50")), on_edges("SELECT quantile_cont(deg, 0.9) AS p90, median(deg) AS p50 FROM deg", "entity"))
add("op_agg_collect", lambda s, d: edges(s, d).groupBy("src").agg(F.array_join(F.array_sort(F.collect_list("dst")).cast("array<string>"), " ").alias("nbrs")), on_edges("SELECT src, string_agg(CAST(dst AS VARCHAR), ' ' ORDER BY dst) AS nbrs FROM edges GROUP BY src"))
add("op_agg_max_by", lambda s, d: edges(s, d).groupBy("src").agg(F.max_by("dst", F.struct("w", "dst")).alias("best")), on_edges("SELECT src, dst AS best FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst DESC) AS n FROM edges) WHERE n = 1"))
add("op_agg_approx_distinct", lambda s, d: steps(s, d).agg(F.approx_count_distinct("vertex").alias("n")))
_CUBE = "SELECT {} FROM (SELECT CAST(cur // 50 AS BIGINT) AS kind, CAST(step AS INT) AS step FROM walk) GROUP BY {}"
add("op_agg_rollup", lambda s, d: steps(s, d).withColumn("kind", F.floor(F.col("vertex") / 50)).rollup("kind", "step").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("g")), on_walk(_CUBE.format("kind, step, count(*) AS n, CAST(grouping_id(kind, step) AS BIGINT) AS g", "ROLLUP (kind, step)")))
add("op_agg_cube", lambda s, d: steps(s, d).withColumn("kind", F.floor(F.col("vertex") / 50)).cube("kind", "step").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("g")), on_walk(_CUBE.format("kind, step, count(*) AS n, CAST(grouping_id(kind, step) AS BIGINT) AS g", "CUBE (kind, step)")))
add("op_agg_grouping_sets", lambda s, d: steps(s, d).withColumn("kind", F.floor(F.col("vertex") / 50)).groupingSets([[F.col("kind")], [F.col("step")]], F.col("kind"), F.col("step")).agg(F.count("*").alias("n")), on_walk(_CUBE.format("kind, step, count(*) AS n", "GROUPING SETS ((kind), (step))")))
add("op_agg_pivot", lambda s, d: steps(s, d).withColumn("kind", F.floor(F.col("vertex") / 50)).groupBy("kind").pivot("step", [0, 1, 2]).agg(F.count("start")).toDF("kind", "s0", "s1", "s2"), on_walk("SELECT CAST(cur // 50 AS BIGINT) AS kind, nullif(count(*) FILTER (step = 0), 0) AS s0, nullif(count(*) FILTER (step = 1), 0) AS s1, nullif(count(*) FILTER (step = 2), 0) AS s2 FROM walk GROUP BY 1"))
add("op_agg_regression", lambda s, d: degree(s, d, "entity").groupBy("deg").agg(F.count("*").alias("n")).agg(F.round(F.regr_slope(F.log("n"), F.log("deg")), 9).alias("slope")), on_edges("SELECT round(regr_slope(ln(n), ln(deg)), 9) AS slope FROM (SELECT deg, count(*) AS n FROM deg GROUP BY deg)", "entity"))

# Windows.


def by_weight():
    return Window.partitionBy("src").orderBy(F.desc("w"), "dst")


def by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


for _name, _f, _sql, _over in (
    ("row_number", F.row_number, "row_number()", "all"), ("rank", F.rank, "rank()", "ties"), ("dense_rank", F.dense_rank, "dense_rank()", "ties"), ("ntile", lambda: F.ntile(8), "ntile(8)", "deg"),
    ("percent_rank", F.percent_rank, "percent_rank()", "ties"), ("cume_dist", F.cume_dist, "cume_dist()", "ties"),
):
    if _over == "all":
        add(f"op_win_{_name}", lambda s, d, f=_f: edges(s, d).select("src", "dst", f().over(by_weight()).alias("n")), on_edges(f"SELECT src, dst, CAST({_sql} OVER (PARTITION BY src ORDER BY w DESC, dst) AS INT) AS n FROM edges"))
    else:
        _cast = "DOUBLE" if _name in ("percent_rank", "cume_dist") else "INT"
        add(f"op_win_{_name}", lambda s, d, f=_f, o=_over: degree(s, d).select("vid", "deg", f().over(Window.orderBy("deg") if o == "ties" else Window.orderBy("deg", "vid")).alias("n")), on_edges(f"SELECT vid, deg, CAST({_sql} OVER (ORDER BY deg{'' if _over == 'ties' else ', vid'}) AS {_cast}) AS n FROM deg"))
add("op_win_lag_lead", lambda s, d: events(s, d).select("event_id", F.lag("event_type").over(by_user()).alias("before"), F.lead("event_type", 2).over(by_user()).alias("later")), "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type, 2) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
add("op_win_first_last", lambda s, d: (lambda w: steps(s, d).select("start", "step", F.first("vertex").over(w).alias("first_v"), F.last("vertex").over(w).alias("last_v")))(Window.partitionBy("start", "round").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), on_walk("SELECT start, CAST(step AS INT) AS step, first_value(cur) OVER w AS first_v, last_value(cur) OVER w AS last_v FROM walk WINDOW w AS (PARTITION BY start, round ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"))
add("op_win_running_sum", lambda s, d: edges(s, d).select("src", "dst", F.sum("w").over(Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)).alias("upto")), on_edges("SELECT src, dst, CAST(sum(w) OVER (PARTITION BY src ORDER BY dst ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto FROM edges"))
add("op_win_rows_frame", lambda s, d: steps(s, d).select("start", "step", F.sum("vertex").over(Window.partitionBy("start", "round").orderBy("step").rowsBetween(-2, 2)).alias("near")), on_walk("SELECT start, CAST(step AS INT) AS step, CAST(sum(cur) OVER (PARTITION BY start, round ORDER BY step ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS near FROM walk"))
add("op_win_range_frame", lambda s, d: degree(s, d).select("vid", F.count("*").over(Window.orderBy("deg").rangeBetween(-5, 5)).alias("n")), on_edges("SELECT vid, count(*) OVER (ORDER BY deg RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS n FROM deg"))

# Order and limits.
add("op_topk_global", lambda s, d: degree(s, d, "entity").orderBy(F.desc("deg"), "vid").limit(20), on_edges("SELECT vid, deg FROM deg ORDER BY deg DESC, vid LIMIT 20", "entity"))
add("op_topk_group", lambda s, d: edges(s, d).withColumn("n", F.row_number().over(by_weight())).where("n <= 3").select("src", "dst", "w"), on_edges("SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS n FROM edges) WHERE n <= 3"))
add("op_sort_multi", lambda s, d: degree(s, d).orderBy(F.desc("deg"), F.asc("vid")), on_edges("SELECT vid, deg FROM deg ORDER BY deg DESC, vid"))
add("op_limit_offset", lambda s, d: degree(s, d).orderBy(F.desc("deg"), "vid").offset(10).limit(10), on_edges("SELECT vid, deg FROM deg ORDER BY deg DESC, vid LIMIT 10 OFFSET 10"))

# Sets: parts bought in two spans of time.
_A, _B = "SELECT l_partkey AS vid FROM lineitem WHERE l_shipdate < TIMESTAMP '1996-01-01'", "SELECT l_partkey AS vid FROM lineitem WHERE l_shipdate >= TIMESTAMP '2001-01-01'"


def spans(s, d) -> tuple[DataFrame, DataFrame]:
    v = F.col("l_partkey").alias("vid")
    return lines(s, d).where("l_shipdate < TIMESTAMP '1996-01-01'").select(v), lines(s, d).where("l_shipdate >= TIMESTAMP '2001-01-01'").select(v)


for _name, _sql, _f in (
    ("union", "UNION ALL", lambda a, b: a.union(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    add(f"op_set_{_name}", lambda s, d, f=_f: f(*spans(s, d)), f"{_A} {_sql} {_B}")
add("op_set_union_by_name", lambda s, d: (lambda a, b: a.withColumn("span", F.lit(1)).unionByName(b.withColumn("late", F.lit(True)), allowMissingColumns=True))(*spans(s, d)), f"SELECT vid, 1 AS span, NULL::BOOLEAN AS late FROM ({_A}) UNION ALL SELECT vid, NULL, TRUE FROM ({_B})")
add("op_distinct", lambda s, d: spans(s, d)[0].distinct(), f"SELECT DISTINCT vid FROM ({_A})")


@registry(on_edges("SELECT src, dst, w FROM edges WHERE CAST('0x' || substr(md5(concat_ws(':', 7, 0, src, dst)), 1, 12) AS BIGINT) < 28147497671065"))
def op_sample_hash(s, d):
    """A tenth of the edges by a counter-based draw: the same at any layout."""
    from ..walk.rng import SPAN, draw48

    return edges(s, d).where(draw48(7, 0, "src", "dst") < SPAN // 10)


# Rows and arrays.
_ADJ = "adj AS (SELECT src AS vid, list(dst ORDER BY dst) AS ids FROM edges GROUP BY src)"


def adjacent(s, d) -> DataFrame:
    return edges(s, d).groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list("dst")).alias("ids"))


def on_adjacent(select: str) -> str:
    return f"WITH {oracle.edges_cte('user')}, {_ADJ} {select}"


add("op_unpivot", lambda s, d: edges(s, d).groupBy("src").agg(F.min("w").alias("lo"), F.max("w").alias("hi")).unpivot("src", ["lo", "hi"], "kind", "w"), on_edges("SELECT vid AS src, unnest(['lo', 'hi']) AS kind, unnest([wmin, wmax]) AS w FROM deg"))
add("op_explode", lambda s, d: adjacent(s, d).select("vid", F.explode("ids").alias("id")), on_adjacent("SELECT vid, unnest(ids) AS id FROM adj"))
add("op_explode_outer", lambda s, d: adjacent(s, d).select("vid", F.explode_outer(F.filter("ids", lambda x: x > 120)).alias("id")), on_adjacent("SELECT vid, id FROM adj LEFT JOIN LATERAL (SELECT unnest(list_filter(ids, lambda x: x > 120)) AS id) ON TRUE"))
add("op_posexplode", lambda s, d: adjacent(s, d).select("vid", F.posexplode("ids").alias("pos", "id")), on_adjacent("SELECT vid, CAST(unnest(range(len(ids))) AS INT) AS pos, unnest(ids) AS id FROM adj"))


def _sql_view(text: str):
    def query(s, d):
        edges(s, d).createOrReplaceTempView("edges")
        return s.sql(text)

    return query


for _name, _text in (
    ("op_lateral", "SELECT a.src, t.dst FROM (SELECT DISTINCT src FROM edges WHERE src <= 20) a, LATERAL (SELECT dst FROM edges b WHERE b.src = a.src AND b.w >= 2) t"),
    ("op_lateral_all", "SELECT a.src, t.dst FROM (SELECT DISTINCT src FROM edges) a, LATERAL (SELECT dst FROM edges b WHERE b.src = a.src AND b.w >= 2) t"),
    ("op_cte", "WITH d AS (SELECT src, count(*) AS deg FROM edges GROUP BY src) SELECT deg, count(*) AS n FROM d GROUP BY deg"),
    ("op_subquery_exists", "SELECT src, dst FROM edges a WHERE EXISTS (SELECT 1 FROM edges b WHERE b.src = a.dst AND b.w >= 4)"),
    ("op_subquery_scalar", "SELECT src, dst, w FROM edges WHERE w > (SELECT avg(w) FROM edges)"),
    ("op_subquery_correlated", "SELECT src, dst, w FROM edges a WHERE w = (SELECT max(w) FROM edges b WHERE b.src = a.src)"),
):
    add(_name, _sql_view(_text), f"WITH {oracle.edges_cte('user')}{', ' + _text[5:] if _text.startswith('WITH ') else ' ' + _text}")
