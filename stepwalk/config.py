"""Session factory and run parameters."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid
from contextlib import contextmanager
from dataclasses import dataclass, replace
from fractions import Fraction
from math import lcm

from pyspark.sql import DataFrame, SparkSession

LOCAL_BIAS, FAR_BIAS = (0.5, 2.0), (2.0, 0.5)


def session(name: str = "stepwalk", master: str | None = None, shuffle_partitions: int | None = None, **conf: str) -> SparkSession:
    """A session with the settings that the engine expects; on a cluster, pass nothing and set them there."""
    builder = SparkSession.builder.appName(name)
    if master:
        builder = builder.master(master)
    settings = {"spark.sql.adaptive.enabled": "true", "spark.sql.session.timeZone": "UTC", "spark.serializer": "org.apache.spark.serializer.KryoSerializer", "spark.ui.showConsoleProgress": "false"}
    if shuffle_partitions:
        settings["spark.sql.shuffle.partitions"] = str(shuffle_partitions)
    for key, value in (settings | conf).items():
        builder = builder.config(key, value)
    return builder.getOrCreate()


@dataclass(frozen=True)
class WalkParams:
    """p and q bias the walk; ``length`` counts moves, so a path has one vertex more."""

    p: float = 1.0
    q: float = 1.0
    length: int = 80
    walks_per_vertex: int = 10
    seed: int = 42
    directed: bool = False
    rng: str = "md5"

    def __post_init__(self):
        if self.p <= 0 or self.q <= 0:
            raise ValueError("p and q must be positive")
        if self.rng not in ("md5", "xxhash64"):
            raise ValueError("rng is md5 or xxhash64")

    def scaled(self) -> tuple[int, int, int] | None:
        """The factors for return, common and other vertices as whole numbers; None where p or q is no simple ratio."""
        p, q = (Fraction(x).limit_denominator(1000) for x in (self.p, self.q))
        if abs(float(p) - self.p) > 1e-12 or abs(float(q) - self.q) > 1e-12:
            return None
        by = lcm(p.numerator, q.numerator)
        return int(by / p), by, int(by / q)

    def factors(self) -> tuple[float, float, float]:
        return 1 / self.p, 1.0, 1 / self.q

    def first_order(self) -> bool:
        return self.p == 1 and self.q == 1

    def but(self, **changes) -> WalkParams:
        return replace(self, **changes)


def shared_dir(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; a temporary one only where it is unset and the master is local."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = tempfile.mkdtemp(prefix="stepwalk-")
    atexit.register(shutil.rmtree, own, True)
    spark.sparkContext.setCheckpointDir(own)
    return spark.sparkContext.getCheckpointDir()


def run_dir(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def written(frame: DataFrame, label: str, codec: str = "snappy") -> DataFrame:
    """The frame as a Parquet table in the shared folder: its lineage ends there and survives lost executors."""
    path = run_dir(frame.sparkSession, label)
    frame.write.option("compression", codec).parquet(path)
    return frame.sparkSession.read.schema(frame.schema).parquet(path)


def swept(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of queries that are done: it does so when the driver's objects are collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@contextmanager
def setting(spark: SparkSession, key: str, value: str):
    """A runtime setting for the length of a block."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


@contextmanager
def batch_rows(spark: SparkSession, bytes_per_row: float, budget: int = 8 << 20):
    """Arrow batches bounded by rows of the mean size and by bytes, as rows may carry long lists."""
    rows = str(int(min(10_000, max(16, budget // max(1.0, bytes_per_row)))))
    with setting(spark, "spark.sql.execution.arrow.maxRecordsPerBatch", rows), setting(spark, "spark.sql.execution.arrow.maxBytesPerBatch", str(2 * budget)):
        yield
