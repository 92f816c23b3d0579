"""Edge lists in files: readers with explicit schemas and a quarantine for rows that do not parse, and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE = "src LONG, dst LONG, w LONG"


def read_csv(spark: SparkSession, path: str, separator: str = ",", header: bool = True, comment: str = "#") -> tuple[DataFrame, DataFrame]:
    """(edges, rows that do not parse)."""
    rows = spark.read.schema(EDGE + ", _corrupt_record STRING").option("mode", "PERMISSIVE").option("header", header).option("sep", separator).option("comment", comment).csv(path)
    bad = F.col("_corrupt_record").isNotNull() | F.col("src").isNull() | F.col("dst").isNull()
    return rows.where(~bad).drop("_corrupt_record"), rows.where(bad).select(F.coalesce("_corrupt_record", F.concat_ws(separator, "src", "dst", "w")).alias("row"))


def read_text(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """Lines "u v" or "u v w" (weight 1 if absent); empty lines and lines that begin with # are skipped."""
    lines = spark.read.text(path).where("trim(value) <> '' AND NOT startswith(trim(value), '#')")
    parts = F.split(F.trim("value"), r"\s+")
    get = lambda k: F.try_element_at(parts, F.lit(k)).try_cast("long")
    rows = lines.select("value", get(1).alias("src"), get(2).alias("dst"), F.when(F.size(parts) >= 3, get(3)).otherwise(1).alias("w"))
    good = F.col("src").isNotNull() & F.col("dst").isNotNull() & F.col("w").isNotNull()
    return rows.where(good).drop("value"), rows.where(~good).select(F.col("value").alias("row"))


def write_edges(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    if kind == "text":
        edges.select(F.concat_ws(" ", "src", "dst", "w").alias("value")).write.mode("overwrite").text(path)
    elif kind == "csv":
        edges.write.mode("overwrite").option("header", True).csv(path)
    else:
        edges.write.mode("overwrite").format(kind).save(path)


def write_vectors(vectors: DataFrame, path: str) -> None:
    """Embedding text format: "vid x1 x2 ..." per line."""
    vectors.select(F.concat_ws(" ", F.col("vid").cast("string"), F.col("vec").cast("array<string>")).alias("value")).write.mode("overwrite").text(path)
