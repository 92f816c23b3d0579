"""Synthetic graphs: recursive-matrix families and planted communities, from counter-based draws."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import normalize


@dataclass(frozen=True)
class Matrix:
    """2^k vertices; each edge picks one of four quadrants k times, with shares a, b, c, d."""

    k: int
    a: float
    b: float
    c: float
    d: float
    n_edges: int
    seed: int = 42

    def fitted(self, n_edges: int) -> Matrix:
        """The same family with ``n_edges`` drawn edges: as many levels as keep the average degree."""
        return replace(self, k=max(1, (n_edges // (self.n_edges >> self.k)).bit_length()), n_edges=n_edges)


def er(k: int, average: int = 10) -> Matrix:
    return Matrix(k, 0.25, 0.25, 0.25, 0.25, average << k)


def wec(k: int) -> Matrix:
    return Matrix(k, 0.18, 0.25, 0.25, 0.32, 100 << k)


def skew(k: int, s: float, average: int = 100) -> Matrix:
    """The last quadrant is ``s`` times the first."""
    return Matrix(k, 0.5 / (1 + s), 0.25, 0.25, 0.5 * s / (1 + s), average << k)


def solve_shares(k: int, average: float, largest: float) -> float:
    """c + d for which the last vertex expects ``largest`` edges."""
    return 0.5 * (largest / average) ** (1 / k)


def expected_last_degree(spec: Matrix) -> float:
    return spec.n_edges / 2**spec.k * (2 * (spec.c + spec.d)) ** spec.k


def bits_of(spec: Matrix, edge, level) -> object:
    """A draw below 2^24 for one level of one edge."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(spec.seed)), edge.cast("string"), level.cast("string")).cast("binary")), 1, 6), 16, 10).cast("long")


def rmat_raw(spark: SparkSession, spec: Matrix, ids: DataFrame | None = None) -> DataFrame:
    """(src, dst) of every drawn edge, repeats and loops included; with ``ids`` (id) these number the edges."""
    ab, abc, a = (round(x * 2**24) for x in (spec.a + spec.b, spec.a + spec.b + spec.c, spec.a))

    def descend(at, level):
        r = bits_of(spec, F.col("id"), level)
        right = ((r >= a) & (r < ab)) | (r >= abc)
        return F.struct((at["src"] * 2 + (r >= ab).cast("long")).alias("src"), (at["dst"] * 2 + right.cast("long")).alias("dst"))

    zero = F.struct(F.lit(0).cast("long").alias("src"), F.lit(0).cast("long").alias("dst"))
    drawn = spark.range(spec.n_edges) if ids is None else ids
    return drawn.select(F.aggregate(F.sequence(F.lit(0), F.lit(spec.k - 1)), zero, descend).alias("e")).select("e.src", "e.dst")


def rmat(spark: SparkSession, spec: Matrix, symmetric: bool = True, ids: DataFrame | None = None) -> DataFrame:
    """Edges without loops and repeats, weight 1."""
    return normalize(rmat_raw(spark, spec, ids).withColumn("w", F.lit(1).cast("long")), directed=not symmetric, unit=True)


def rmat_table_sql(spec: Matrix, ids: str) -> str:
    """DuckDB text of ``rmat`` of the spec fitted to a table: one drawn edge for each row of ``ids``, a query of (id)."""
    ab, abc, a = (round(x * 2**24) for x in (spec.a + spec.b, spec.a + spec.b + spec.c, spec.a))
    bit = lambda test: f"CAST(sum(CASE WHEN {test} THEN 1 << (k - 1 - l) ELSE 0 END) AS BIGINT)"
    return f"""WITH ids AS ({ids}), n AS (SELECT greatest(1, length(bin(count(*) // {spec.n_edges >> spec.k}))) AS k FROM ids), u AS (SELECT id, k, unnest(range(k)) AS l FROM ids, n),
r AS (SELECT id, k, l, CAST('0x' || substr(md5(concat_ws(':', '{spec.seed}', id, l)), 1, 6) AS BIGINT) AS r FROM u),
e AS (SELECT id, {bit(f'r >= {ab}')} AS s, {bit(f'(r >= {a} AND r < {ab}) OR r >= {abc}')} AS t FROM r GROUP BY id)
SELECT DISTINCT src, dst, 1::BIGINT AS w FROM (SELECT s AS src, t AS dst FROM e WHERE s <> t UNION ALL SELECT t, s FROM e WHERE s <> t)"""


def planted(spark: SparkSession, n: int = 800, groups: int = 8, p_in: float = 0.15, p_out: float = 0.03, shape: float = 1.5, overlap: bool = False, seed: int = 42, vertices: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(edges, labels (vid, labels)): communities by vid modulo ``groups``, Pareto propensities of mean 1, capped at 12.

    With ``overlap`` every third vertex is in the next community too.  All pairs of ``n`` vertices are drawn, so n is small.
    With ``vertices`` (vid) every run of ``n`` ids is such a graph of its own, so work grows in proportion to the vertices.
    """
    unit = lambda *key: F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), *key).cast("binary")), 1, 12), 16, 10).cast("long") / float(1 << 48)
    two = (F.col("vid") % 3 == 0) if overlap else F.lit(False)
    own = (F.col("vid") % groups).cast("int")
    v = spark.range(n).withColumnRenamed("id", "vid") if vertices is None else vertices.select("vid").distinct()
    mean = shape / (shape - 1)
    v = v.select("vid", F.expr(f"vid div {n}").alias("run"), F.when(two, F.array(own, ((own + 1) % groups).cast("int"))).otherwise(F.array(own)).alias("labels"), F.least(F.lit(12.0), F.pow(1 - unit(F.col("vid").cast("string")), F.lit(-1 / shape)) / mean).alias("theta"))
    a, b = v.toDF("a", "run", "la", "ta"), v.toDF("b", "run", "lb", "tb")
    chance = F.least(F.lit(1.0), F.col("ta") * F.col("tb") * F.when(F.size(F.array_intersect("la", "lb")) > 0, p_in).otherwise(p_out))
    pairs = a.join(b, "run").where("a < b").where(unit(F.col("a").cast("string"), F.col("b").cast("string")) < chance)
    return normalize(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1).cast("long").alias("w"))), v.select("vid", "labels")

