"""Quality rules per document, and host verdicts from their failure rates.

Each text is measured once; the measures are a written table.  Failures of each rule are counted per host (partial sums
first).  Per rule, each host's rate is shrunk by a beta prior whose parameters are the moments of all hosts' rates of that
rule, and a host with a shrunk rate of at least ``reject_rate`` in any rule loses all its documents.  The host table joins
back to the documents.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import table, with_measures, written
from .textbatch import Chunk, repeated_cover

# The characters that count as symbols.
SYMBOLS = "#*$%&|<>"
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")


def _row_sums(flags: np.ndarray, edges: np.ndarray) -> np.ndarray:
    return np.diff(np.concatenate([[0], np.cumsum(flags)])[edges])


def measures(chunk: Chunk) -> dict[str, np.ndarray]:
    data, at = chunk.bytes, chunk.offsets
    words = chunk.words()
    solid = np.zeros(len(data) + 1, np.int64)
    np.add.at(solid, words.start, 1)
    np.add.at(solid, words.end, -1)
    inside = np.cumsum(solid)[: len(data)] > 0
    symbol = np.isin(np.arange(256), list(SYMBOLS.encode()))
    covered = repeated_cover(words, words.hashes())
    lines, count = np.zeros(chunk.n, np.int64), (words.count > 0).astype(np.int64)
    breaks = _row_sums(data == 10, at)
    for k in np.flatnonzero(breaks):
        kept = [x for x in chunk.text(k).split(b"\n") if x.strip()]
        lines[k], count[k] = len(kept) - len(set(kept)), len(kept)
    return {
        "n_words": words.count,
        "word_chars": _row_sums(inside & ((data & 0xC0) != 0x80), at),
        "n_symbols": _row_sums(symbol[data], at),
        "n_dup_lines": lines,
        "n_repeat_words": _row_sums(covered, words.first),
        "n_lines": count,
    }


def measured(docs: DataFrame, text_column: str = "text") -> DataFrame:
    """``docs`` with its text replaced by the measures (n_lines: lines with a word)."""
    keep = [c for c in docs.columns if c != text_column]
    return with_measures(docs, measures, {m: "long" for m in MEASURES}, text_column, keep)


def base_failed(min_words: int = 50, max_repeat: int = 50) -> Column:
    return (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat * F.col("n_words"))


# What a text must keep to, each rule in whole numbers.
RULES = {
    "few_words": "n_words < 50",
    "repeated": "100 * n_repeat_words > 50 * n_words",
    "word_length": "n_words > 0 AND (word_chars < 2 * n_words OR word_chars > 15 * n_words)",
    "symbols": "10 * n_symbols > n_words",
    "dup_lines": "100 * n_dup_lines > 30 * n_lines",
}


def host_rates(marked: DataFrame, host: str = "host", rules: dict[str, str] = RULES) -> DataFrame:
    """(host, n_docs, and per rule its shrunk rate; shrunk: the highest of them): beta-binomial shrinkage, a prior for each rule.

    ``marked`` has a boolean column per rule.  With m and v the mean and variance of the hosts' raw rates, a prior's weight is
    m(1-m)/v - 1, kept between 1 and 1000 (one host, or equal rates: 1000, that is the common rate), and a shrunk rate is
    (failures + weight*m)/(documents + weight).
    """
    per = marked.groupBy(host).agg(F.count("*").alias("n_docs"), *[F.sum(F.col(r).cast("long")).alias(f"n_{r}") for r in rules])
    rate = {r: F.col(f"n_{r}") / F.col("n_docs") for r in rules}
    prior = per.agg(*[F.struct(F.avg(x).alias("m"), F.var_pop(x).alias("v")).alias(f"p_{r}") for r, x in rate.items()])
    both = per.join(F.broadcast(prior))
    for r in rules:
        m, v = F.col(f"p_{r}.m"), F.col(f"p_{r}.v")
        weight = F.greatest(F.lit(1.0), F.least(F.lit(1000.0), F.when(v > 0, m * (1 - m) / v - 1).otherwise(1000.0)))
        both = both.withColumn(f"shrunk_{r}", (F.col(f"n_{r}") + weight * m) / (F.col("n_docs") + weight))
    shrunk = [f"shrunk_{r}" for r in rules]
    return both.select(host, "n_docs", *shrunk, F.greatest(*shrunk).alias("shrunk"))


def judge(docs: DataFrame, host_column: str = "source", text_column: str = "text", reject_rate: float = 0.5, min_words: int = 50, max_repeat: int = 50, rules: dict[str, str] = RULES) -> DataFrame:
    """doc_id, the six measures, base_failed, kept, host, n_failed (rules the text fails), shrunk (its host's worst rate).

    A text is rejected if it fails the base rules itself or its host is rejected; the other rules count for hosts only.
    Null text has no words and fails; a null host is one host of its own; repeated rows count each; an empty table gives
    no row; columns of ``docs`` other than doc_id are not returned, so none can clash.  The priors are one row (an
    aggregate), so their broadcast is bounded; the host table is joined by whatever its size allows.
    """
    source = docs.select("doc_id", F.col(host_column).cast("string").alias("host"), F.col(text_column).alias("text"))
    marked = measured(source).withColumn("base_failed", base_failed(min_words, max_repeat)).withColumns({r: F.expr(x) for r, x in rules.items()})
    marked = written(marked, "measured")
    hosts = host_rates(marked, rules=rules).select(F.col("host").alias("of"), "shrunk")
    joined = marked.join(hosts, F.col("host").eqNullSafe(F.col("of")), "left")
    failed = sum((F.col(r).cast("long") for r in rules), F.lit(0).cast("long"))
    return joined.withColumn("n_failed", failed).withColumn("kept", ~F.col("base_failed") & (F.col("shrunk") < reject_rate)).drop("of", *rules)


def op8_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select("doc_id", *MEASURES, "base_failed", "kept", "host", "n_failed", F.round("shrunk", 9).alias("shrunk"))
