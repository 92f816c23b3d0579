"""Near-duplicate vectors by navigable small-world graphs per shard.

Vectors of one label (and dimension) are dealt into shards of bounded size by a hash; each shard is indexed as a graph.
Every pair of shards of a label is met once: the vectors of one are searched in the graph of the other.  Searches are
audited by full comparison: of vectors that a search found links for, and of others until the audit holds enough true links
or an eighth of the shard; while too few of its links were found, the beam widens, and beyond the shard's size the
comparison is exact.  Candidates are verified by cosine in double precision.  Links are counted and joined batch by batch,
so a meeting never holds its pairs, and returns, per vector, its links and its local component; components are then joined
over all meetings.  Each meeting also tells its audit's figures, which are pooled by label (``audit``).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .hnsw import BATCH, Graph
from .tables import table, written

SLACK = 1e-4
INDEX = "`group` string, shard int, nodes binary, copies binary, vectors binary, links binary"
MET = "`group` string, node long, links long, root long, width long, audited long, true_links long, found_links long"
AUDIT, ENOUGH = 64, 32


def scaled(vectors: np.ndarray) -> np.ndarray:
    """Each row times a power of two that brings its largest component below 1: cosines stay, squares can neither overflow nor vanish."""
    _, exponent = np.frexp(np.abs(vectors).max(axis=1, keepdims=True, initial=0))
    return np.ldexp(vectors, -exponent)


def _unit(vectors: np.ndarray) -> np.ndarray:
    return vectors / np.linalg.norm(vectors, axis=1, keepdims=True)


def _index(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
    nodes, copies = np.asarray(rows.column("node")), np.asarray(rows.column("copies"))
    order = np.argsort(nodes, kind="stable")
    flat = rows.column("vector").combine_chunks().flatten()
    vectors = _unit(scaled(np.asarray(flat).astype(np.float64).reshape(len(nodes), -1)[order]))
    nodes, copies = nodes[order], copies[order]
    graph = Graph(vectors.astype(np.float32), nodes)
    return pa.table({
        "group": [key[0].as_py()], "shard": pa.array([key[1].as_py()], pa.int32()), "nodes": [nodes.astype("<i8").tobytes()], "copies": [copies.astype("<i8").tobytes()],
        "vectors": pa.array([vectors.astype("<f8").tobytes()], pa.binary()), "links": pa.array([graph.links.astype("<i4").tobytes()], pa.binary()),
    })


def _loaded(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    nodes = np.frombuffer(row["nodes"], "<i8")
    return nodes, np.frombuffer(row["copies"], "<i8"), np.frombuffer(row["vectors"], "<f8").reshape(len(nodes), -1)


class Links:
    """Counts and components of a meeting's links, taken in batch by batch."""

    def __init__(self, left: np.ndarray, right: np.ndarray, copies_left: np.ndarray, copies_right: np.ndarray):
        self.n = len(left)
        self.label = np.concatenate([left, right])
        self.rank = np.empty(len(self.label), np.int64)
        self.rank[np.argsort(self.label, kind="stable")] = np.arange(len(self.label))  # labels stand on both sides where a shard meets itself
        self.copies = copies_left.astype(np.float64), copies_right.astype(np.float64)
        self.count = np.zeros(len(left) + len(right))
        self.parent = np.arange(len(self.label))

    def root(self, x: np.ndarray) -> np.ndarray:
        while True:
            up = self.parent[x]
            if (up == x).all():
                return x
            x = self.parent[up]

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        """Links from left rows ``a`` to right rows ``b``, each pair once."""
        self.count[: self.n] += np.bincount(a, self.copies[1][b], self.n)
        self.count[self.n :] += np.bincount(b, self.copies[0][a], len(self.label) - self.n)
        self.join(a, self.n + b)

    def join(self, u: np.ndarray, v: np.ndarray) -> None:
        while len(u):
            u, v = self.root(u), self.root(v)
            apart = u != v
            u, v = u[apart], v[apart]
            swap = self.rank[u] > self.rank[v]
            low, high = np.where(swap, v, u), np.where(swap, u, v)
            self.parent[high] = low  # of several writes one stays; the rest are joined in the next pass
            u, v = low, high

    def least(self) -> np.ndarray:
        return self.label[self.root(np.arange(len(self.label)))]


def pairs_of(graph: Graph, unit: np.ndarray, ask: np.ndarray, rows: np.ndarray, least: float, width: int):
    """Batches (query, node) of pairs with a cosine of at least ``least``, as the graph finds them; double precision decides."""
    for k in range(0, len(rows), BATCH):
        own = rows[k : k + BATCH]
        q, b = graph.within(ask[own].astype(np.float32), least - SLACK, width)
        sure = np.empty(len(q), bool)
        for at in range(0, len(q), 1 << 16):
            some = slice(at, at + (1 << 16))
            sure[some] = np.einsum("nd,nd->n", ask[own[q[some]]], unit[b[some]]) >= least
        yield own[q[sure]], b[sure]


def exact_pairs(unit: np.ndarray, ask: np.ndarray, rows: np.ndarray, least: float):
    for k in range(0, len(rows), BATCH):
        own = rows[k : k + BATCH]
        q, b = np.nonzero(ask[own] @ unit.T >= least)
        yield own[q], b


def true_links(unit: np.ndarray, ask: np.ndarray, rows: np.ndarray, least: float, same: bool) -> np.ndarray:
    """Links of each row by full comparison, itself left out."""
    count = np.zeros(len(ask), np.int64)
    for q, b in exact_pairs(unit, ask, rows, least):
        count += np.bincount(q[(q != b) if same else slice(None)], minlength=len(ask))
    return count[rows]


def width_for(graph: Graph, unit: np.ndarray, ask: np.ndarray, least: float, recall: float, same: bool, width: int = 48) -> tuple[int, int, int, int]:
    """(beam width that passes the audit, rows audited, their true links, those found).

    Rows are audited in an order that a hash-like stride fixes: ``AUDIT`` at first, then twice as many, until they hold
    ``ENOUGH`` true links or are an eighth of all.  Where these hold none at all, rows that the search itself finds links
    for are audited as well.
    """
    n = len(ask)
    order = (np.arange(n) * 7919) % n if n % 7919 else np.arange(n)
    size = min(AUDIT, n)
    while True:
        rows = np.sort(order[:size])
        truth = true_links(unit, ask, rows, least, same)
        if truth.sum() >= ENOUGH or size >= max(AUDIT, n // 8) or size >= n:
            break
        size = min(n, size * 2)

    def found(rows: np.ndarray, width: int) -> np.ndarray:
        count = np.zeros(n, np.int64)
        for q, b in pairs_of(graph, unit, ask, rows, least, width):
            count += np.bincount(q[(q != b) if same else slice(None)], minlength=n)
        return count[rows]

    while width < len(unit):
        if not truth.sum():
            rest = order[size:]
            some = rest[found(rest, width) > 0][:AUDIT]
            rows, truth = some, true_links(unit, ask, some, least, same) if len(some) else np.zeros(0, np.int64)
        got = found(rows, width)
        if got.sum() >= recall * truth.sum():
            return width, len(rows), int(truth.sum()), int(got.sum())
        width *= 2
    return len(unit), len(rows), int(truth.sum()), int(truth.sum())


def meet(graph: Graph, nodes, copies, unit, other, other_copies, ask, least: float, recall: float, same: bool) -> tuple[Links, tuple[int, int, int, int]]:
    """Links between the graph's shard (right) and another or the same one (left)."""
    width, *audit = width_for(graph, unit, ask, least, recall, same)
    links, rows = Links(other, nodes, other_copies, copies), np.arange(len(ask))
    found = pairs_of(graph, unit, ask, rows, least, width) if width < len(unit) else exact_pairs(unit, ask, rows, least)
    if not same:
        for q, b in found:
            links.add(q, b)
        return links, (width, *audit)
    seen = np.zeros((len(ask), -(-len(unit) // 8)), np.uint8)  # a bit a pair: what one side found counts for both
    for q, b in found:
        apart = q != b
        q, b = np.concatenate([q[apart], b[apart]]), np.concatenate([b[apart], q[apart]])
        np.bitwise_or.at(seen, (q, b >> 3), (1 << (b & 7)).astype(np.uint8))
    for k in range(0, len(seen), BATCH):
        q, b = np.nonzero(np.unpackbits(seen[k : k + BATCH], axis=1, count=len(unit), bitorder="little"))
        links.add(q + k, b)
    links.join(rows, links.n + rows)
    return links, (width, *audit)


def _meet(least: float, recall: float):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({n: pa.array([], pa.string() if n == "group" else pa.int64()) for n in MET_NAMES})
        base = left.to_pylist()[0]
        nodes, copies, unit = _loaded(base)
        graph = Graph(unit.astype(np.float32), nodes, links=np.frombuffer(base["links"], "<i4").reshape(len(nodes), -1))
        other, other_copies, ask = _loaded(right.to_pylist()[0])
        same = base["i"] == base["j"]
        links, audit = meet(graph, nodes, copies, unit, other, other_copies, ask, least, recall, same)
        size = len(other) if same else len(links.label)
        columns = [np.concatenate([other, nodes])[:size], np.rint(links.count[:size]).astype(np.int64), links.least()[:size]]
        told = [np.where(np.arange(size) == 0, x, 0) for x in audit]  # once a meeting
        return pa.table(dict(zip(MET_NAMES, [pa.array([base["group"]] * size, pa.string()), *columns, *told], strict=True)))

    return run


MET_NAMES = ("group", "node", "links", "root", "width", "audited", "true_links", "found_links")


def audit(met: DataFrame) -> DataFrame:
    """(group, widest beam, rows audited, true links, found links, recall) over all meetings of a label."""
    sums = [F.sum(c).alias(c) for c in ("audited", "true_links", "found_links")]
    return met.groupBy("group").agg(F.max("width").alias("widest"), *sums).withColumn("recall", F.when(F.col("true_links") > 0, F.col("found_links") / F.col("true_links")))


def near_vectors(vectors: DataFrame, least: float = 0.93, recall: float = 0.999, shard_size: int = 8192, id_column: str = "vec_id", vector_column: str = "embedding", label_column: str = "label", audits: list | None = None) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept.

    Only vectors of equal, non-null label and equal dimension are compared.  Vectors that are null, empty, zero or hold a
    null or a non-finite component link with nothing, as do rows with a null id; they are components of their own.
    Equal vectors of a label are one class (each is the others' link), so a vector that a third of all rows share is
    indexed once and its rows are given their class's figures.  ``audits`` gets the frame of audited recall by label.  Repeated rows count as vectors of their own under one id; an empty table gives no row; extra columns
    are ignored.
    """
    rows = vectors.select(F.col(id_column).cast("long").alias("vec_id"), F.col(vector_column).cast("array<double>").alias("vector"), F.col(label_column).cast("string").alias("label"))
    bad = F.exists("vector", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    usable = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & (F.size("vector") > 0) & ~F.coalesce(bad, F.lit(True)) & F.exists("vector", lambda v: v != 0)
    rows = rows.withColumn("usable", F.coalesce(usable, F.lit(False)))
    keyed = rows.where("usable").withColumns({"k1": F.xxhash64("label", "vector"), "k2": F.xxhash64("vector", "label", F.lit(1))})
    group = F.concat_ws(":", F.size("vector").cast("string"), "label")
    classes = keyed.groupBy("k1", "k2").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies"), F.first("vector").alias("vector"), F.first(group).alias("group"))
    classes = written(classes, "vectors")
    shards = classes.groupBy("group").agg(F.ceil(F.count("*") / shard_size).cast("int").alias("shards"))
    shards = written(shards, "shards")
    dealt = classes.join(shards, "group").withColumn("shard", F.pmod(F.xxhash64("node"), F.col("shards")).cast("int"))
    index = written(dealt.groupBy("group", "shard").applyInArrow(_index, INDEX), "index")
    pairs = shards.select("group", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("i"), "shards")
    pairs = pairs.select("group", "i", F.explode(F.sequence("i", F.col("shards") - 1)).alias("j"))
    left = index.withColumnRenamed("shard", "i").join(pairs, ["group", "i"])
    fresh = lambda frame: frame.select(*[F.col(c).alias(c) for c in frame.columns])
    right = fresh(index.drop("links").withColumnRenamed("shard", "j")).join(fresh(pairs), ["group", "j"])
    right = fresh(right)
    met = left.groupBy("group", "i", "j").cogroup(right.groupBy("group", "i", "j")).applyInArrow(_meet(least, recall), MET)
    met = written(met, "met")
    if audits is not None:
        audits.append(audit(met))
    roots = components(met.select(F.col("node").alias("a"), F.col("root").alias("b")))
    counted = met.groupBy("node").agg(F.sum("links").alias("links"))
    of = classes.select("k1", "k2", "node", "copies").join(counted, "node", "left").join(roots, "node", "left")
    of = of.select("k1", "k2", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "node").alias("component_id"))
    out = keyed.select("vec_id", "k1", "k2").join(of, ["k1", "k2"]).select("vec_id", "n_links", "component_id")
    alone = rows.where("not usable").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op4_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))
