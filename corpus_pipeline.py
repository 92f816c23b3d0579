"""A training corpus from the documents table: quality classifier, language ID, near-duplicates, repeated passages, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next
stage's ``docs``.  All stages but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepwalk.llm.op2_packing import pack
from stepwalk.llm.op5_substring import remove_repeats
from stepwalk.llm.op6_minhash import near_duplicates
from stepwalk.llm.op7_language import identify, learn
from stepwalk.llm.op9_quality import classify, train
from stepwalk.llm.tables import held_back, table, written

TOKENIZER = "word_bpe_49k.json"
LEAST_MATCHED = 2.5
ORACLE_SQL = None


def _aside(docs: DataFrame, *names: str) -> tuple[DataFrame, list]:
    """``docs`` with columns of these names, which a stage is about to make, set aside; and what selects its columns again."""
    own = {n: f"_own_{n}" for n in names if n in docs.columns}
    return docs.withColumnsRenamed(own), [F.col(own.get(c, c)).alias(c) for c in docs.columns]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, learned from the labels table, scores 0.5 or more."""
    labels = table(spark, sf_dir, "labels").where(~held_back("doc_id", 3, 1))
    rows, own = _aside(docs, "score", "predicted")
    return classify(rows, train(docs, labels)).where("predicted = 1").select(own)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that labels teach; all stay where no label is there to learn from.

    Texts without a letter go, and texts whose best language matches fewer than ``LEAST_MATCHED`` symbols a phrase: other
    languages and letter junk (about 2 on random letters; texts in a learned language have 3.5 and more).
    """
    samples = learn(docs.where(~held_back("doc_id", 4, 2) & F.col("lang").isNotNull()).select("doc_id", "text", "lang"))
    if not samples:
        return docs
    rows, own = _aside(docs, "lang_pred", "score")
    return identify(rows, samples, least_matched=LEAST_MATCHED).where("lang_pred <> 'und'").select(own)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, also where ids are null or repeated; of rows that repeat id and text one stays."""
    kept = near_duplicates(docs).where("kept").groupBy(F.col("doc_id").alias("_id"), F.col("text_key").alias("_kept_key")).agg(F.count("*").alias("_rows"))
    kept, keyed = written(kept, "kept"), docs.withColumn("_text_key", F.xxhash64("text"))
    of = lambda rows: keyed.join(kept.where(rows), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_text_key") == F.col("_kept_key")), "left_semi")
    return of("_rows = 1").unionByName(of("_rows > 1").dropDuplicates(["doc_id", "_text_key"])).select(docs.columns)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the words of passages that occur more than once; every document stays, its text may be empty."""
    rows, own = _aside(docs, "n_words", "n_removed", "kept_text")
    made = {"text": F.col("kept_text").alias("text"), "n_chars": F.char_length("kept_text").cast("long").alias("n_chars")}
    return remove_repeats(rows).select([made.get(c, column) for c, column in zip(docs.columns, own, strict=True)])


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 2048 tokens."""
    import public_tokenizers

    return pack(docs, public_tokenizers.path(TOKENIZER))


STAGES = [("quality classifier", quality), ("language ID", language), ("MinHash near-dedup", near_copies), ("substring dedup", passages), ("packing", packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
