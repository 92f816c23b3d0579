"""Scalar, array, map and JSON functions on the given tables, each beside its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..embed import cosine
from ..operators.relational import adjacent, edges, events, on_adjacent, on_edges
from ..plans.shared import Registry
from ..sources.tables import table
from ..walk.rng import draw48

registry = Registry()
add = registry.add


def docs(s, d):
    return table(s, d, "documents")


def pages(s, d):
    return table(s, d, "pages")


def orders(s, d):
    return table(s, d, "orders")


add("fn_str_tokens", lambda s, d: docs(s, d).select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word")).where("word <> ''").groupBy("word").agg(F.count("*").alias("n")), "SELECT word, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\\p{L}]+')) AS word FROM documents) WHERE word <> '' GROUP BY word")
add("fn_str_regex", lambda s, d: pages(s, d).select("page_id", F.regexp_extract("url", r"/(\d+)", 1).alias("number"), F.regexp_replace("url", r"\d", "#").alias("masked")), r"SELECT page_id, regexp_extract(url, '/(\d+)', 1) AS number, regexp_replace(url, '\d', '#', 'g') AS masked FROM pages")
add("fn_str_concat", lambda s, d: table(s, d, "part").select("p_partkey", F.concat_ws("|", "p_brand", "p_type", F.col("p_size").cast("string")).alias("tag"), F.concat(F.upper("p_name"), F.lit("!")).alias("name")), "SELECT p_partkey, concat_ws('|', p_brand, p_type, CAST(p_size AS VARCHAR)) AS tag, concat(upper(p_name), '!') AS name FROM part")
add("fn_str_pad_trim", lambda s, d: table(s, d, "customer").select("c_custkey", F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("code"), F.trim(F.concat(F.lit("  "), F.col("c_mktsegment"), F.lit(" "))).alias("segment"), F.substring("c_name", 1, 4).alias("head")), "SELECT c_custkey, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS code, trim('  ' || c_mktsegment || ' ') AS segment, substr(c_name, 1, 4) AS head FROM customer")
add("fn_str_md5", lambda s, d: pages(s, d).select("page_id", F.md5(F.col("url").cast("binary")).alias("h"), F.char_length("html").cast("long").alias("n")), "SELECT page_id, md5(url) AS h, CAST(length(html) AS BIGINT) AS n FROM pages")
add("fn_str_url", lambda s, d: pages(s, d).select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
add("fn_date_trunc", lambda s, d: events(s, d).groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n")), "SELECT date_trunc('hour', ts) AS hour, count(*) AS n FROM events GROUP BY 1")
add("fn_date_diff", lambda s, d: orders(s, d).select("o_orderkey", F.datediff(F.lit("2001-12-31").cast("date"), F.col("o_orderdate")).alias("days")), "SELECT o_orderkey, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2001-12-31') AS INT) AS days FROM orders")
add("fn_date_parts", lambda s, d: orders(s, d).select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("dow"), F.quarter("o_orderdate").alias("q")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(dayofweek(o_orderdate) + 1 AS INT) AS dow, CAST(quarter(o_orderdate) AS INT) AS q FROM orders")
add("fn_date_interval", lambda s, d: orders(s, d).select("o_orderkey", F.expr("o_orderdate + INTERVAL 3 MONTHS").alias("due"), F.expr("o_orderdate - INTERVAL 36 HOURS").alias("before")), "SELECT o_orderkey, o_orderdate + INTERVAL 3 MONTH AS due, o_orderdate - INTERVAL 36 HOUR AS before FROM orders")
add("fn_math_basic", lambda s, d: events(s, d).select("event_id", F.floor("value").alias("f"), F.ceil("value").alias("c"), F.round(F.col("value") / 3, 6).alias("r"), F.greatest("value", F.lit(10.0)).alias("g"), F.abs(F.col("value") - 20).alias("a")), "SELECT event_id, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c, round(value / 3, 6) AS r, greatest(value, 10.0) AS g, abs(value - 20) AS a FROM events")
add("fn_math_log_pow", lambda s, d: edges(s, d).select("src", "dst", F.round(F.log("w"), 9).alias("l"), F.round(F.pow("w", F.lit(0.75)), 9).alias("p"), F.round(F.exp(-F.col("w")), 9).alias("e"), F.round(F.sqrt("w"), 9).alias("r")), on_edges("SELECT src, dst, round(ln(w), 9) AS l, round(pow(w, 0.75), 9) AS p, round(exp(-w), 9) AS e, round(sqrt(w), 9) AS r FROM edges"))
add("fn_math_mod", lambda s, d: edges(s, d).select("src", "dst", F.pmod(F.col("src") - F.col("dst"), F.lit(7)).alias("m"), F.expr("src div 10").alias("t")), on_edges("SELECT src, dst, ((src - dst) % 7 + 7) % 7 AS m, src // 10 AS t FROM edges"))
add("fn_math_conv", lambda s, d: edges(s, d).select("src", "dst", draw48(42, 0, "src", "dst").alias("draw"), F.hex("src").alias("h")), on_edges("SELECT src, dst, CAST('0x' || substr(md5(concat_ws(':', 42, 0, src, dst)), 1, 12) AS BIGINT) AS draw, to_hex(src) AS h FROM edges"))
add("fn_math_decimal", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("decimal(38,2)").alias("total")), "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DECIMAL(38,2)) AS total FROM lineitem GROUP BY 1")

_text = lambda column: F.array_join(column.cast("array<string>"), " ")
_list = lambda sql: f"array_to_string({sql}, ' ')"


def _array(name: str, expression, sql: str) -> None:
    add(f"fn_arr_{name}", lambda s, d: adjacent(s, d).select("vid", expression().alias("x")), on_adjacent(f"SELECT vid, {sql} AS x FROM adj"))


_array("sort", lambda: _text(F.sort_array("ids", asc=False)), _list("list_reverse_sort(ids)"))
_array("transform", lambda: _text(F.transform("ids", lambda v: v * 2 + 1)), _list("list_transform(ids, lambda v: v * 2 + 1)"))
_array("filter", lambda: _text(F.filter("ids", lambda v: v % 5 == 0)), _list("list_filter(ids, lambda v: v % 5 = 0)"))
_array("aggregate", lambda: F.aggregate("ids", F.lit(0).cast("long"), lambda a, v: a + v), "CAST(list_sum(ids) AS BIGINT)")
_array("zip", lambda: _text(F.zip_with("ids", F.reverse("ids"), lambda a, b: a * 1000 + b)), _list("list_transform(list_zip(ids, list_reverse(ids)), lambda p: p[1] * 1000 + p[2])"))
_array("setops", lambda: _text(F.array_sort(F.array_union(F.array_except("ids", F.sequence(F.lit(1), F.lit(50)).cast("array<long>")), F.array_intersect("ids", F.array(*[F.lit(v).cast("long") for v in (3, 5, 8)]))))), _list("list_sort(list_filter(ids, lambda v: v > 50 OR v < 1 OR v IN (3, 5, 8)))"))
_array("slice", lambda: _text(F.slice("ids", 2, 3)), _list("list_slice(ids, 2, 4)"))
_array("flatten", lambda: _text(F.flatten(F.array("ids", F.slice("ids", 1, 1)))), _list("flatten([ids, list_slice(ids, 1, 1)])"))
_array("contains", lambda: F.array_contains("ids", F.lit(7).cast("long")) | (F.array_position("ids", F.lit(9).cast("long")) > 0), "list_contains(ids, 7) OR list_contains(ids, 9)")


def _map(s, d):
    return edges(s, d).groupBy("src").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("dst", "w")))).alias("m"))


add("fn_map_build", lambda s, d: _map(s, d).select("src", F.size("m").cast("long").alias("n"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, v: a + v).alias("s")), on_edges("SELECT src, count(*) AS n, CAST(sum(w) AS BIGINT) AS s FROM edges GROUP BY src"))
add("fn_map_lookup", lambda s, d: _map(s, d).select("src", F.try_element_at("m", F.lit(3).cast("long")).alias("w3")), on_edges("SELECT src, max(w) FILTER (dst = 3) AS w3 FROM edges GROUP BY src"))
add("fn_struct_fields", lambda s, d: edges(s, d).groupBy("src").agg(F.max(F.struct("w", "dst")).alias("m")).select("src", F.col("m.w").alias("w"), F.col("m").getField("dst").alias("dst")), on_edges("SELECT src, w, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst DESC) AS n FROM edges) WHERE n = 1"))
add("fn_json_get", lambda s, d: events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
add("fn_json_parse", lambda s, d: events(s, d).select(F.from_json("props", "k long").alias("p")).groupBy((F.col("p.k") % 10).alias("digit")).agg(F.count("*").alias("n")), "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS digit, count(*) AS n FROM events GROUP BY 1")


@registry("SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def fn_vec_cosine(s, d):
    e = table(s, d, "embeddings").select("vec_id", "embedding")
    other = e.select(F.col("vec_id").alias("b"), F.col("embedding").alias("y"))
    return e.join(other, F.col("b") == F.col("vec_id") + 1).select(F.col("vec_id").alias("a"), "b", F.round(cosine("embedding", "y"), 6).alias("c"))
