"""Reading the given tables and cutting lineage by written tables in the shared checkpoint folder."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; only where it is unset (tests, local mode) a folder of our own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        kept = spark.sparkContext.getCheckpointDir()
        if kept:
            return kept
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="stepwalk-checkpoint-")
        atexit.register(shutil.rmtree, named, True)
        spark.sparkContext.setCheckpointDir(named)
        return spark.sparkContext.getCheckpointDir()
    return named


def written(frame: DataFrame, label: str) -> DataFrame:
    """The frame as a Parquet table in the shared folder: later readers never recompute it, whichever executor is lost."""
    spark = frame.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def small_batches(spark: SparkSession, rows: int = 2000) -> None:
    """Arrow batches of at most ``rows`` texts for the Arrow stages of this session: buffers then take some megabytes a task."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= rows:
        spark.conf.set(key, str(rows))


def row_key(*columns: str):
    """A 64-bit key of a row; equal rows share it, which is harmless where replies depend on the row's values alone."""
    return F.xxhash64(*columns)


def with_measures(docs: DataFrame, compute, fields: dict[str, str], text_column: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` (all columns, or those of ``keep``) with new columns that ``compute(chunk)`` gives as arrays, in one Arrow pass.

    A column of ``docs`` that has the name of a new one is replaced.  ``fields`` maps new names to Spark types.
    """
    import pyarrow as pa
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_type

    from .textbatch import chunks

    small_batches(docs.sparkSession)
    kept = [c for c in (keep if keep is not None else docs.columns) if c not in fields]
    schema = T.StructType([docs.schema[c] for c in kept] + [T.StructField(n, T._parse_datatype_string(t)) for n, t in fields.items()])
    arrow = [to_arrow_type(schema[n].dataType) for n in fields]

    def run(batches):
        for chunk in chunks(batches, text_column):
            found = compute(chunk)
            columns = [chunk.rows.column(chunk.rows.schema.get_field_index(c)) for c in kept]
            columns += [pa.array(found[n], t) for n, t in zip(fields, arrow, strict=True)]
            yield pa.RecordBatch.from_arrays(columns, [*kept, *fields])

    read = kept if text_column in kept else [*kept, text_column]
    return docs.select(*[F.col(f"`{c}`") for c in read]).mapInArrow(run, schema)


def held_back(id_column: str, modulus: int, remainder: int):
    """Whether crc32 of the id as text has this remainder (a null id counts as the empty text)."""
    return F.crc32(F.coalesce(F.col(id_column).cast("string"), F.lit("")).cast("binary")) % modulus == remainder


def hash_sample(rows: DataFrame, group: str, per_group: int, key: str, most_groups: int = 256) -> DataFrame:
    """About ``per_group`` rows of each value of ``group``, by a hash of ``key``: the same rows at every layout of the data.

    Rows are counted first; what comes back has at most about per_group * most_groups rows, however large the input.
    """
    counts = rows.where(F.col(group).isNotNull()).groupBy(group).agg(F.count("*").alias("n")).orderBy(F.desc("n"), group).limit(most_groups).collect()
    share = F.lit(0.0)
    for r in counts:
        share = F.when(F.col(group) == F.lit(r[0]), F.lit(min(1.0, per_group / r["n"]))).otherwise(share)
    place = F.pmod(F.xxhash64(F.col(key), F.lit(7)), F.lit(1 << 30)) / float(1 << 30)
    return rows.where(place < share)
