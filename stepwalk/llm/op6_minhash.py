"""Near-duplicate detection by weighted minwise signatures (BagMinHash).

A text is the multiset of its five-word shingles.  The weight of a shingle is cut into dyadic levels [0,1), [1,2), [2,4), ...;
every (shingle, level) owns a Poisson process whose rate is the level's length, whose points carry a time, a position in
the level and a slot.  A text keeps, per slot, the earliest point that lies below the shingle's weight.  Two texts agree in
a slot with a probability equal to their weighted Jaccard similarity.  Only first points are made for every shingle;
further ones only while they can still be earlier than a text's latest slot.

Bands of the signature give candidates, and every link is verified by multiset overlap.  Texts of equal multisets are one
class before anything else.  Links of a bucket go through a centre, its member that meets most others in all its buckets:
all members are first compared with it, which also gives their differences from it (units missing, units added).  If two members x and y share k differences,

    overlap(x, y) = (n - a_x - a_y + k) / (n + b_x + b_y - k)

where the centre has n units, x misses a_x of them and adds b_x.  So a member that does not link with the centre can link
with another only if they share many differences, at least a_x + t*b_x - (1-t)*n of x's own for a threshold t.  Sorting
differences that several members hold by rarity, one of the rarest few of both must be shared (all but k - 1 of each): those
few are joined, and only what they find is compared.  No link that could join two components is left unseen, and no pairs of a bucket are made.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .components import components, joined_components
from .tables import small_batches, table, written
from .textbatch import U64, Words, chunks, let_go, mix, runs, uint64_blob

SHINGLE = 5
BANDS, ROWS = 32, 5


def shingles(words: Words, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every shingle; a text of fewer words has one, of all its words."""
    hashes = words.hashes()
    first, window = words.windows(hashes, size)
    rows, found = [words.doc[first]], [window]
    for n in range(1, size):
        short = words.count == n
        if short.any():
            at, part = words.windows(hashes, n)
            own = short[words.doc[at]]
            rows.append(words.doc[at][own])
            found.append(part[own])
    return np.concatenate(rows), np.concatenate(found)


def bags(rows: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (row, hash) in order, with counts."""
    order = np.lexsort((hashes, rows))
    rows, hashes = rows[order], hashes[order]
    new = np.ones(len(rows), bool)
    new[1:] = (rows[1:] != rows[:-1]) | (hashes[1:] != hashes[:-1])
    at = np.flatnonzero(new)
    return rows[at], hashes[at], np.diff(np.append(at, len(rows)))


def _unit(bits: np.ndarray) -> np.ndarray:
    return ((bits >> U64(11)).astype(np.float64) + 0.5) / float(1 << 53)


def signatures(rows: np.ndarray, hashes: np.ndarray, counts: np.ndarray, n: int, slots: int = BANDS * ROWS) -> np.ndarray:
    """Times of the earliest point per slot, (n, slots); infinite where a row has no shingle."""
    top = np.ceil(np.log2(np.maximum(counts, 1))).astype(np.int64)
    times = top + 1
    own = np.repeat(np.arange(len(rows)), times)
    level = np.arange(len(own)) - np.repeat(np.cumsum(times) - times, times)
    low = np.where(level == 0, 0, 1 << np.maximum(level - 1, 0)).astype(np.float64)
    rate = np.where(level == 0, 1, 1 << np.maximum(level - 1, 0)).astype(np.float64)
    share = np.minimum(1.0, (counts[own] - low) / rate)
    row, seed = rows[own], mix(hashes[own] + level.astype(U64) * U64(0x632BE59BD9B4E019))
    out = np.full(n * slots, np.inf)
    latest = np.full(n, np.inf)
    time, made, take = np.zeros(len(row)), 0, 1
    while len(row):
        draw = mix(seed[:, None] + np.arange(made + 1, made + take + 1).astype(U64)[None, :] * U64(0x9E3779B97F4A7C15))
        point = np.cumsum(np.concatenate([time[:, None], -np.log(_unit(draw)) / rate[:, None]], axis=1), axis=1)[:, 1:]  # one by one: the same bits however many
        place = mix(draw + U64(0xA0761D6478BD642F))
        good = (point < latest[row][:, None]) & (_unit(mix(place + U64(0xE7037ED1A0B428DB))) < share[:, None])
        slot = (place % U64(slots)).astype(np.int64)
        np.minimum.at(out, (row[:, None] * slots + slot)[good], point[good])
        latest = out.reshape(n, slots).max(axis=1)
        time, made = point[:, -1], made + take
        live = time < latest[row]
        row, seed, rate, share, time = row[live], seed[live], rate[live], share[live], time[live]
        take = int(np.clip((1 << 18) // max(1, len(row)), 1, 32))
    return out.reshape(n, slots)


def band_hashes(signature: np.ndarray, bands: int = BANDS, each: int = ROWS) -> np.ndarray:
    bits = signature.view(U64).reshape(-1, bands, each)
    out = np.broadcast_to(np.arange(bands).astype(U64) * U64(0x589965CC75374CC3), bits.shape[:2]).copy()
    for k in range(each):
        out = mix(out ^ bits[:, :, k])
    return out


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    let_go()
    for chunk in chunks(batches):
        rows, hashes = shingles(chunk.words())
        rows, hashes, counts = bags(rows, hashes)
        band = band_hashes(signatures(rows, hashes, counts, chunk.n))
        weight = np.bincount(rows, counts, chunk.n).astype(np.int64)
        edge = np.searchsorted(rows, np.arange(chunk.n + 1))
        sums = [np.concatenate([np.zeros(1, U64), np.cumsum(mix(hashes ^ U64(s)) * counts.astype(U64))]) for s in (1, 2)]
        first, second = ((s[edge[1:]] - s[edge[:-1]]).view(np.int64) for s in sums)
        columns = [chunk.rows.column(chunk.rows.schema.get_field_index(c)) for c in ("doc_id", "text_key")]
        columns += [pa.array(first), pa.array(second), pa.array(weight), pa.array([uint64_blob(b) if w else None for b, w in zip(band, weight, strict=True)], pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, ["doc_id", "text_key", "c1", "c2", "weight", "bands"])


def _spread_bands(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        if b.num_rows:
            band = np.frombuffer(b"".join(b.column("bands").to_pylist()), "<i8")
            node = np.repeat(np.asarray(b.column("node")), len(band) // b.num_rows)
            yield pa.RecordBatch.from_arrays([pa.array(band), pa.array(node)], ["band", "node"])


def units(rows: np.ndarray, hashes: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bags as sets: (row, hash of shingle and 1..count), by row and hash."""
    rows = np.repeat(rows, counts)
    every = mix(np.repeat(hashes, counts) + runs(counts).astype(U64) * U64(0x8CB92BA72F3D8DD7))
    order = np.lexsort((every, rows))
    return rows[order], every[order]


def _bag_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for chunk in chunks(batches):
        rows, every = units(*bags(*shingles(chunk.words())))
        edge = np.searchsorted(rows, np.arange(chunk.n + 1))
        body = [uint64_blob(every[a:b]) for a, b in zip(edge[:-1], edge[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([chunk.rows.column(0), chunk.rows.column(1), pa.array(body, pa.binary())], ["node", "salts", "bag"])


def overlap(a: np.ndarray, b: np.ndarray) -> float:
    """Similarity of two bags as sorted units."""
    both = _held(a, b).sum()
    return float(both / max(1, len(a) + len(b) - both))


def _held(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which of b are in a."""
    if not len(a):
        return np.zeros(len(b), bool)
    at = np.searchsorted(a, b)
    at[at == len(a)] = 0
    return a[at] == b


COMPARED = "a long, b long, similarity double"
DIFFERENT = COMPARED + ", n long, missing long, added long, differences binary"


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        pairs = zip(batch.column("bag_a").to_pylist(), batch.column("bag_b").to_pylist(), strict=True)
        found = [overlap(np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")) for x, y in pairs]
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(found, pa.float64())], ["a", "b", "similarity"])


def _differ(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for x, y in zip(batch.column("bag_a").to_pylist(), batch.column("bag_b").to_pylist(), strict=True):
            x, y = np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")
            missing, added = x[~_held(y, x)], y[~_held(x, y)]
            both = len(x) - len(missing)
            rows.append((both / max(1, len(x) + len(y) - both), len(x), len(missing), len(added), uint64_blob(np.concatenate([missing, ~added]))))
        if rows:
            kinds = (pa.float64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            columns = [batch.column("a"), batch.column("b"), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))]
            yield pa.RecordBatch.from_arrays(columns, ["a", "b", "similarity", "n", "missing", "added", "differences"])


MOST_PER_SALT = 20_000


def _salts(members):
    return F.ceil(members / MOST_PER_SALT).cast("int")


def compared(pairs: DataFrame, bag: DataFrame, differences: bool = False) -> DataFrame:
    """Pairs (a, b, salt) with their overlap, and how b differs from a.

    A node ``a`` of very many pairs (the centre of a large group) is no single join key: its pairs are dealt over ``salt``,
    and its bag goes to as many salts as ``bag`` (node, bag, salts) says.
    """
    of_a = bag.select(F.col("node").alias("a"), F.col("bag").alias("bag_a"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    of_b = bag.select(F.col("node").alias("b"), F.col("bag").alias("bag_b"))
    both = pairs.join(of_b, "b").join(of_a, ["a", "salt"]).select("a", "b", "bag_a", "bag_b")
    return both.mapInArrow(_differ, DIFFERENT) if differences else both.mapInArrow(_compare, COMPARED)


def _each_difference(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["centre", "node", "root", "n", "missing", "added"]
    for b in batches:
        blobs = b.column("differences").to_pylist()
        size = np.array([len(x) // 8 for x in blobs], np.int64)
        at = pa.array(np.repeat(np.arange(b.num_rows), size))
        if len(at):
            yield pa.RecordBatch.from_arrays([*(b.column(c).take(at) for c in names), pa.array(np.frombuffer(b"".join(blobs), "<i8"))], [*names, "unit"])


def sharing_differences(star: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) of a centre's members in other components that may link, from ``star`` (centre, centre_root, node, root, n, missing, added, differences)."""
    mixed = star.groupBy("centre").agg(F.max(F.col("root") != F.col("centre_root")).alias("mixed"), F.count("*").alias("members")).where("mixed AND members > 1").select("centre")
    inside = star.join(mixed, "centre")
    names = ["centre", "node", "root", "n", "missing", "added"]
    units_ = inside.select(*names, "differences").mapInArrow(_each_difference, ", ".join(f"{c} long" for c in [*names, "unit"]))
    often = units_.groupBy("centre", "unit").agg(F.count("*").alias("often")).where("often > 1")
    of = Window.partitionBy("centre", "node")
    ranked = {"share": F.count("*").over(of), "rank": F.row_number().over(of.orderBy("often", "unit"))}
    shared = written(units_.join(often, ["centre", "unit"]).withColumns(ranked), "differences")
    needed = F.ceil(F.col("missing") + threshold * F.col("added") - (1 - threshold) * F.col("n") - 1e-9)
    few = F.col("missing") + F.col("added") - needed + 1 - (F.col("missing") + F.col("added") - F.col("share"))
    rare = shared.join(star.where("root <> centre_root").select("centre", "node"), ["centre", "node"], "left_semi")
    rare = rare.where((F.col("rank") <= few) & (needed > 0))
    other = shared.select("centre", "unit", *[F.col(c).alias(f"_{c}") for c in ("node", "root", "missing", "added", "share", "rank")])
    both = (threshold * (F.col("n") + F.col("added") + F.col("_added")) - F.col("n") + F.col("missing") + F.col("_missing")) / (1 + threshold) - 1e-9
    can = (F.col("rank") + both <= F.col("share") + 1) & (F.col("_rank") + both <= F.col("_share") + 1)
    sizes = similar_sizes(F.col("n") - F.col("missing") + F.col("added"), F.col("n") - F.col("_missing") + F.col("_added"), threshold)
    pairs = rare.join(other, (rare.centre == other.centre) & (rare.unit == other.unit) & (F.col("root") != F.col("_root")) & can & sizes)
    return pairs.select(F.least("node", "_node").alias("a"), F.greatest("node", "_node").alias("b")).distinct()


def similar_sizes(a, b, threshold: float):
    """Overlap is at most the ratio of the sizes, so other pairs cannot link."""
    return F.least(a, b) >= F.lit(threshold) * F.greatest(a, b)


def near_duplicates(docs: DataFrame, threshold: float = 0.8, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: doc_id, class_id (smallest id with the same shingles), component_id (smallest id reachable by links), kept, text_key.

    Links join texts whose weighted Jaccard similarity of five-word shingles is at least ``threshold``.  A text of one to
    four words is one shingle.  Texts without a word (null included) link with nothing and are kept.  Rows are judged by
    their texts, so rows that repeat an id with other texts have verdicts of their own; of a component the row of the
    smallest id (among those of its smallest ``text_key``, a hash of the text) is kept, and a row that repeats it exactly.
    Null ids come after all others: a component without any id has a negative number from its smallest text_key.  An empty
    table gives no row; extra columns are ignored.

    Links run between classes, which have numbers of their own: nothing but the last step looks at document ids.
    """
    small_batches(docs.sparkSession)
    source = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).alias("text"), F.xxhash64(text_column).alias("text_key"))
    sketch = written(source.mapInArrow(_sketch, "doc_id long, text_key long, c1 long, c2 long, weight long, bands binary"), "sketch")
    worded = sketch.where("weight > 0")
    row = F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), F.col("text_key").alias("key"))
    named = lambda x: F.coalesce(f"{x}.id", -1 - F.pmod(F.col(f"{x}.key"), F.lit(1 << 61)))
    classes = worded.groupBy("c1", "c2").agg(F.min(row).alias("first"), F.first("bands").alias("bands"))
    classes = written(classes.withColumn("node", F.monotonically_increasing_id()), "classes")
    banded = classes.select("node", "bands").mapInArrow(_spread_bands, "band long, node long")
    buckets = banded.groupBy("band").agg(F.count("*").alias("n")).where("n > 1")
    members = written(banded.join(buckets, "band"), "members")
    known = members.groupBy("node").agg(F.sum("n").alias("met"))
    scored = members.select("band", "node").join(known, "node")
    centres = scored.groupBy("band").agg(F.max(F.struct(F.col("met"), (-F.col("node")).alias("minus"))).alias("x")).select("band", (-F.col("x.minus")).alias("centre"))
    star = members.join(centres, "band").where("node <> centre").select(F.col("centre").alias("a"), F.col("node").alias("b"), "n")
    star = star.groupBy("a", "b").agg(F.max("n").alias("n")).withColumn("salt", F.pmod(F.xxhash64("b"), _salts(F.col("n"))).cast("int"))
    star = written(star, "star")

    involved = star.select(F.col("a").alias("node"), _salts(F.col("n")).alias("salts")).unionByName(star.select(F.col("b").alias("node"), F.lit(1).alias("salts")))
    involved = involved.groupBy("node").agg(F.max("salts").alias("salts")).join(classes, "node")
    involved = involved.select("node", "salts", F.col("first.id").alias("_id"), F.col("first.key").alias("_key"))
    texts = source.join(involved.hint("merge"), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key"))).select("node", "salts", "text").dropDuplicates(["node"])
    bag = written(texts.mapInArrow(_bag_rows, "node long, salts int, bag binary"), "bags")
    checked = written(compared(star, bag, differences=True), "compared")
    links = checked.where(F.col("similarity") >= threshold).select("a", "b")
    roots = written(components(links), "roots")
    root_of = lambda name: roots.select(F.col("node").alias(f"_{name}"), F.col("root").alias(f"_root_{name}"))
    known = checked.withColumnsRenamed({"a": "centre", "b": "node"})
    for name in ("centre", "node"):
        known = known.join(root_of(name), F.col(name) == F.col(f"_{name}"), "left").withColumn(f"_root_{name}", F.coalesce(f"_root_{name}", name)).drop(f"_{name}")
    known = known.withColumnsRenamed({"_root_centre": "centre_root", "_root_node": "root"})
    pairs = written(sharing_differences(known, threshold), "pairs")
    more = written(compared(pairs.withColumn("salt", F.lit(0)), bag).where(F.col("similarity") >= threshold).select("a", "b"), "verified")
    if not more.isEmpty():
        roots = written(joined_components(roots, more), "roots")

    linked = classes.select("node", "first").join(roots, "node")
    best = linked.groupBy("root").agg(F.min("first").alias("best"))
    best = linked.join(best, "root").select("node", "best")
    of = classes.select("c1", "c2", "node", "first").join(best, "node", "left").select("c1", "c2", "first", F.coalesce("best", "first").alias("best"))
    out = worded.join(of, ["c1", "c2"]).select("doc_id", named("first").alias("class_id"), named("best").alias("component_id"), row.eqNullSafe(F.col("best")).alias("kept"), "text_key")
    alone = F.coalesce("doc_id", -1 - F.pmod("text_key", F.lit(1 << 61)))
    empty = sketch.where("weight = 0").select("doc_id", alone.alias("class_id"), alone.alias("component_id"), F.lit(True).alias("kept"), "text_key")
    return out.unionByName(empty)


def op6_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
