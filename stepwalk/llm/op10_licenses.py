"""License scan by ordered signature rules, in DataFrame functions only.

A case-blind pattern gates documents, words that rules need gate rules, and only then a rule's own pattern runs.  Matches
become intervals of words.  An interval inside one of higher priority (or of equal priority that starts no later and ends
no earlier) is suppressed; base phrases are reported whatever suppresses them.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .license_rules import TRIGGERS, gate, rules
from .tables import row_key, table

# A word of the original text (case kept) and of the lower-cased one; letters that are lowered.
RAW_WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LEVELS = (1, 2, 3, 4)


def words_between_spaces(text: Column) -> Column:
    words = F.regexp_extract_all(F.translate(text, UPPER, LOWER), F.lit(RAW_WORD), F.lit(0))
    return F.concat(F.lit(" "), F.array_join(words, " "), F.lit(" "))


def _spaces(text: Column) -> Column:
    return F.char_length(text) - F.char_length(F.replace(text, F.lit(" "), F.lit("")))


def gated_text(text: Column) -> Column:
    """Whether a rule may match: some trigger stands in the text (lower-cased once, a plain search each), then the gate's pattern."""
    some = F.transform(F.array(F.lower(text)), lambda low: reduce(or_, [F.contains(low, F.lit(t)) for t in TRIGGERS]))
    return F.element_at(some, 1) & text.rlike(gate())


def detections(gated: DataFrame) -> DataFrame:
    """(key, label, base, priority, sure, start, end) for ``gated`` (key, norm) with unique keys; word positions from 0, end excluded."""
    spark = gated.sparkSession
    listed = rules()
    words = sorted({r[2] for r in listed})
    rows = ", ".join(f"({n}, '{label}', '{word}', '{pattern}', {priority}, {sure}D, {base})" for n, label, word, pattern, priority, sure, base in listed)
    frame = spark.sql(f"SELECT * FROM VALUES {rows} AS r(rule, label, word, pattern, priority, sure, base)")
    held = F.filter(F.array(*[F.lit(w) for w in words]), lambda w: F.contains(F.col("norm"), w))
    tried = gated.select("key", "norm", F.explode(held).alias("word")).join(F.broadcast(frame), "word").where(F.expr("rlike(norm, pattern)"))
    gaps = F.transform(F.split("norm", F.col("pattern"), -1), _spaces)
    hits = F.transform(F.regexp_extract_all("norm", F.col("pattern"), F.lit(0)), _spaces)
    each = tried.select("key", "rule", "label", "base", "priority", "sure", F.posexplode(F.arrays_zip(gaps.alias("gap"), hits.alias("hit"))).alias("n", "both"))
    each = each.select("key", "rule", "label", "base", "priority", "sure", "n", F.col("both.gap").alias("gap"), F.col("both.hit").alias("hit"))
    order = Window.partitionBy("key", "rule").orderBy("n")
    upto = F.sum("gap").over(order) + F.coalesce(F.sum("hit").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return each.withColumn("start", upto).where("hit is not null").withColumn("end", F.col("start") + F.col("hit")).drop("gap", "hit", "n")


def surviving(found: DataFrame) -> DataFrame:
    """Detections with ``kept``: false where an interval of at least the same priority contains them."""
    before = Window.partitionBy("key").orderBy("start", F.desc("end"), F.desc("priority"), "rule").rowsBetween(Window.unboundedPreceding, -1)
    reach = {f"reach{k}": F.max(F.when(F.col("priority") >= k, F.col("end"))).over(before) for k in LEVELS}
    at_least = F.coalesce(*[F.when(F.col("priority") == k, F.col(f"reach{k}")) for k in LEVELS], F.lit(-1))
    return found.withColumns(reach).withColumn("kept", at_least < F.col("end")).drop(*reach)


def scan(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: n_words, n_base, first_word, last_word, base_labels, labels, score.

    Null text counts as empty; documents without a detection have no places, empty labels and score 0; repeated rows each
    get their row; a null id is kept; extra columns are ignored; an empty table gives no row.  Only gated documents are
    shuffled with their text; results join back by a hash of id and text.  The rule table (a few hundred rows, whatever
    the data) is broadcast.
    """
    source = docs.select(F.col(id_column).alias("doc_id"), F.coalesce(F.col(text_column), F.lit("")).alias("text"))
    source = source.withColumn("key", row_key("doc_id", "text"))
    counted = source.select("doc_id", "key", F.regexp_count("text", F.lit(RAW_WORD)).cast("long").alias("n_words"))
    gated = source.where(gated_text(F.col("text"))).select("key", "text").dropDuplicates(["key"]).select("key", words_between_spaces(F.col("text")).alias("norm"))
    found = surviving(detections(gated))
    base = F.col("base")
    joined = lambda labels: F.array_join(F.array_sort(labels), ",")
    per = found.groupBy("key").agg(
        F.count(F.when(base, 1)).alias("n_base"), F.min(F.when(base, F.col("start"))).alias("first_word"), F.max(F.when(base, F.col("start"))).alias("last_word"),
        joined(F.collect_set(F.when(base, F.col("label")))).alias("base_labels"), joined(F.collect_set(F.when(base | F.col("kept"), F.col("label")))).alias("labels"),
        F.max(F.when(base | F.col("kept"), F.col("sure"))).alias("score"),
    )
    out = counted.join(per, "key", "left")
    fill = lambda name, value: F.coalesce(name, F.lit(value)).alias(name)
    return out.select("doc_id", "n_words", F.coalesce("n_base", F.lit(0).cast("long")).alias("n_base"), F.col("first_word").cast("long"), F.col("last_word").cast("long"), fill("base_labels", ""), fill("labels", ""), fill("score", 0.0))


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
