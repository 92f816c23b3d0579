"""Graphs on the given tables, each with the SQL that makes the same edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import written
from ..sources.tables import table
from .blocks import counted

# The tag of each entity kind; an id is tag * 10^12 + key.
CUSTOMER, PART, SUPPLIER, NATION = (k * 10**12 for k in (1, 2, 3, 4))
WORD_BASE = 10**12


def both_ways(pairs: DataFrame) -> DataFrame:
    """(a, b, w) once per edge -> edges in both directions."""
    there = pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")
    return there.unionByName(pairs.select(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))


def ordered_lag(rows: DataFrame, bucket, order: list[str], value: str) -> DataFrame:
    """``rows`` with ``before``: the value of the row before in global order, without one task seeing all rows.

    Rows are ordered within time buckets; a bucket's first row takes the last value of the nearest earlier bucket, from a
    table of one row per bucket.
    """
    rows = rows.withColumn("_bucket", bucket)
    within = Window.partitionBy("_bucket").orderBy(*order)
    rows = rows.withColumn("before", F.lag(value).over(within)).withColumn("_first", F.row_number().over(within) == 1)
    last = rows.groupBy("_bucket").agg(F.max_by(value, F.struct(*order)).alias("_last"))
    last = last.withColumn("_carry", F.lag("_last").over(Window.orderBy("_bucket"))).drop("_last")
    out = rows.join(last, "_bucket")
    return out.withColumn("before", F.when(F.col("_first"), F.col("_carry")).otherwise(F.col("before"))).drop("_bucket", "_first", "_carry")


def user_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of consecutive events; weight: how often."""
    events = table(spark, sf_dir, "events").select("ts", "event_id", "user_id")
    rows = ordered_lag(events, F.date_trunc("day", "ts"), ["ts", "event_id"], "user_id")
    pairs = rows.where("before <> user_id").select(F.least("before", "user_id").alias("a"), F.greatest("before", "user_id").alias("b"))
    return both_ways(pairs.groupBy("a", "b").agg(F.count("*").alias("w")))


def copart_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of one order; weight: orders."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = lines.select("l_orderkey", F.col("l_partkey").alias("b"))
    pairs = lines.withColumnRenamed("l_partkey", "a").join(other, "l_orderkey").where("a < b")
    return both_ways(pairs.groupBy("a", "b").agg(F.count("*").alias("w")))


def supply_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts and their suppliers; weight: line items."""
    lines = table(spark, sf_dir, "lineitem").select((F.col("l_partkey") + PART).alias("a"), (F.col("l_suppkey") + SUPPLIER).alias("b"))
    return both_ways(lines.groupBy("a", "b").agg(F.count("*").alias("w")))


def entity_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, w) of customers, parts, suppliers and nations; weight: line items (1 to a nation).

    Pairs are mostly there once, so they are counted in packed blocks: as rows they would be shuffled at full width.
    """
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    rows = lines.join(orders.hint("shuffle_hash"), "l_orderkey").select((F.col("o_custkey") + CUSTOMER).alias("c"), (F.col("l_partkey") + PART).alias("p"), (F.col("l_suppkey") + SUPPLIER).alias("s"))
    pairs = rows.select(F.explode(F.array(F.struct(F.col("c").alias("a"), F.col("p").alias("b")), F.struct(F.col("p").alias("a"), F.col("s").alias("b")), F.struct(F.col("c").alias("a"), F.col("s").alias("b")))).alias("e"))
    found = counted(pairs.select("e.a", "e.b"), max(64, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    one = F.lit(1).cast("long").alias("w")
    nation = lambda name, key, of, tag: table(spark, sf_dir, name).select((F.col(key) + tag).alias("a"), (F.col(of).cast("long") + NATION).alias("b"), one)
    return found.unionByName(nation("customer", "c_custkey", "c_nationkey", CUSTOMER)).unionByName(nation("supplier", "s_suppkey", "s_nationkey", SUPPLIER))


def entity_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return both_ways(entity_pairs(spark, sf_dir))


def doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, word, n): runs of at least two letters in lower case."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word"))
    return docs.where(F.char_length("word") >= 2).groupBy("doc_id", "word").agg(F.count("*").alias("n"))


def doc_edges(spark: SparkSession, sf_dir: str, most: int = 20) -> DataFrame:
    """Documents that share words of 2 to ``most`` documents; weight: shared words.  Rarity bounds the pairs of a word."""
    words = doc_words(spark, sf_dir).select("doc_id", "word")
    rare = words.groupBy("word").agg(F.count("*").alias("df")).where(F.col("df").between(2, most)).select("word")
    words = written(words.join(rare, "word"), "rare-words")
    other = words.select("word", F.col("doc_id").alias("b"))
    pairs = words.withColumnRenamed("doc_id", "a").join(other, "word").where("a < b")
    return both_ways(pairs.groupBy("a", "b").agg(F.count("*").alias("w")))


def ranked_ids(values: DataFrame, column: str, parts: int = 32) -> DataFrame:
    """``values`` (distinct) with ``vid``: 1, 2, ... in sorted order.

    Ranges are ranked in parallel; what reaches the driver is one count per range.
    """
    ranged = values.repartitionByRange(parts, column).sortWithinPartitions(column)
    ranged = written(ranged.withColumn("_range", F.spark_partition_id()), "ranges")
    counts = sorted((r[0], r[1]) for r in ranged.groupBy("_range").count().collect())
    begin, rows = 0, []
    for number, n in counts:
        rows.append((number, begin))
        begin += n
    offsets = values.sparkSession.createDataFrame(rows or [(0, 0)], "_range int, _begin long")
    within = Window.partitionBy("_range").orderBy(column)
    return ranged.withColumn("_n", F.row_number().over(within)).join(F.broadcast(offsets), "_range").select(*values.columns, (F.col("_n") + F.col("_begin")).alias("vid"))


def docword_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and their words; weight: occurrences; words are numbered in sorted order from 10^12 on."""
    words = written(doc_words(spark, sf_dir), "doc-words")
    ids = ranked_ids(words.select("word").distinct(), "word")
    pairs = words.join(ids, "word").select(F.col("doc_id").alias("a"), (F.col("vid") + WORD_BASE).alias("b"), F.col("n").alias("w"))
    return both_ways(pairs)


def vec_edges(spark: SparkSession, sf_dir: str, k: int = 10, block: int = 2048) -> DataFrame:
    """Vectors and their ``k`` nearest by cosine, made undirected, weight 1: blocks of vectors meet pairwise as matrix products."""
    import numpy as np
    import pyarrow as pa

    rows = table(spark, sf_dir, "embeddings").where("embedding IS NOT NULL").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    n_blocks = max(1, -(-rows.count() // block))
    rows = rows.withColumn("blk", F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks)).cast("int"))

    def near(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = np.asarray(left.column("vec_id")), np.asarray(right.column("vec_id"))
        if not len(a) or not len(b):
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "sim": pa.array([], pa.float64())})
        x, y = (np.asarray(t.column("x").combine_chunks().flatten()).reshape(t.num_rows, -1) for t in (left, right))
        x, y = (m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300) for m in (x, y))
        sims = x @ y.T
        sims[a[:, None] == b[None, :]] = -np.inf
        order = np.lexsort((np.broadcast_to(b, sims.shape), -sims), axis=1)[:, : min(k, len(b))]
        best = np.take_along_axis(sims, order, 1)
        src, dst, sim = np.repeat(a, order.shape[1]), b[order].ravel(), best.ravel()
        keep = np.isfinite(sim)
        return pa.table({"src": src[keep], "dst": dst[keep], "sim": sim[keep]})

    every = F.sequence(F.lit(0), F.lit(n_blocks - 1))
    left = rows.select("vec_id", "x", "blk", F.explode(every).alias("other")).groupBy("blk", "other")
    right = rows.select(F.col("vec_id").alias("vec_id"), F.col("x").alias("x"), F.col("blk").alias("other"), F.explode(every).alias("blk")).groupBy("blk", "other")
    found = left.cogroup(right).applyInArrow(near, "src long, dst long, sim double")
    rank = Window.partitionBy("src").orderBy(F.desc("sim"), "dst")
    best = found.withColumn("n", F.row_number().over(rank)).where(F.col("n") <= k)
    pairs = best.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    return both_ways(pairs.withColumn("w", F.lit(1).cast("long")))


def page_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts and path segments of page urls, numbered in sorted order; weight: pages."""
    url = table(spark, sf_dir, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"), F.explode(F.split(F.parse_url("url", F.lit("PATH")), "/")).alias("segment"))
    pairs = url.where("segment <> ''").groupBy("host", "segment").agg(F.count("*").alias("w"))
    pairs = written(pairs, "host-segments")
    hosts = ranked_ids(pairs.select("host").distinct(), "host").withColumnRenamed("vid", "a")
    segments = ranked_ids(pairs.select("segment").distinct(), "segment").withColumnRenamed("vid", "b")
    return both_ways(pairs.join(hosts, "host").join(segments, "segment").select("a", (F.col("b") + WORD_BASE).alias("b"), "w"))


GRAPHS = {"user": user_edges, "copart": copart_edges, "supply": supply_edges, "entity": entity_edges, "doc": doc_edges, "docword": docword_edges, "vec": vec_edges, "page": page_edges}
#: Once per edge (a, b, w), for graphs that are written so and read both ways.
PAIRS = {"entity": entity_pairs}

_BOTH = "SELECT a AS src, b AS dst, w FROM pairs UNION ALL SELECT b, a, w FROM pairs"
_DOC_WORDS = "SELECT doc_id, word, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{L}]+')) AS word FROM documents) WHERE length(word) >= 2 GROUP BY doc_id, word"

# DuckDB: each a query of (src, dst, w).
SQL = {
    "user": f"""WITH pairs AS (
  SELECT least(before, user_id) AS a, greatest(before, user_id) AS b, count(*) AS w
  FROM (SELECT user_id, lag(user_id) OVER (ORDER BY ts, event_id) AS before FROM events) WHERE before <> user_id GROUP BY 1, 2) {_BOTH}""",
    "copart": f"""WITH l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem), pairs AS (
  SELECT x.l_partkey AS a, y.l_partkey AS b, count(*) AS w FROM l x JOIN l y USING (l_orderkey) WHERE x.l_partkey < y.l_partkey GROUP BY 1, 2) {_BOTH}""",
    "supply": f"""WITH pairs AS (SELECT l_partkey + {PART} AS a, l_suppkey + {SUPPLIER} AS b, count(*) AS w FROM lineitem GROUP BY 1, 2) {_BOTH}""",
    "entity": f"""WITH t AS (
  SELECT o_custkey + {CUSTOMER} AS c, l_partkey + {PART} AS p, l_suppkey + {SUPPLIER} AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey
), pairs AS (
  SELECT a, b, count(*) AS w FROM (SELECT c AS a, p AS b FROM t UNION ALL SELECT p, s FROM t UNION ALL SELECT c, s FROM t) GROUP BY 1, 2
  UNION ALL SELECT c_custkey + {CUSTOMER}, c_nationkey::BIGINT + {NATION}, 1 FROM customer
  UNION ALL SELECT s_suppkey + {SUPPLIER}, s_nationkey::BIGINT + {NATION}, 1 FROM supplier) {_BOTH}""",
    "doc": f"""WITH dw AS ({_DOC_WORDS}), rare AS (SELECT word FROM dw GROUP BY word HAVING count(*) BETWEEN 2 AND 20), r AS (SELECT doc_id, word FROM dw JOIN rare USING (word)),
pairs AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS w FROM r x JOIN r y USING (word) WHERE x.doc_id < y.doc_id GROUP BY 1, 2) {_BOTH}""",
    "docword": f"""WITH dw AS ({_DOC_WORDS}), ids AS (SELECT word, row_number() OVER (ORDER BY word) + {WORD_BASE} AS b FROM (SELECT DISTINCT word FROM dw)),
pairs AS (SELECT doc_id AS a, b, n AS w FROM dw JOIN ids USING (word)) {_BOTH}""",
    "vec": f"""WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings), s AS (
  SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.x, b.x) DESC, b.vec_id) AS n FROM e a JOIN e b ON a.vec_id <> b.vec_id),
pairs AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b, 1::BIGINT AS w FROM s WHERE n <= 10) {_BOTH}""",
    "page": f"""WITH u AS (SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, unnest(string_split(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '/')) AS segment FROM pages),
hs AS (SELECT host, segment, count(*) AS w FROM u WHERE segment <> '' GROUP BY 1, 2),
pairs AS (SELECT h.n AS a, g.n + {WORD_BASE} AS b, w FROM hs JOIN (SELECT host, row_number() OVER (ORDER BY host) AS n FROM (SELECT DISTINCT host FROM hs)) h USING (host)
JOIN (SELECT segment, row_number() OVER (ORDER BY segment) AS n FROM (SELECT DISTINCT segment FROM hs)) g USING (segment)) {_BOTH}""",
}
