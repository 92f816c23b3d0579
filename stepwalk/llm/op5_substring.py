"""Removal of repeated passages by difference-cover anchors.

With a cover D of the residues modulo P (every difference occurs between two of its members), any two equal stretches of
at least ``window`` words hold, at some common offset below P, positions that are both in the cover.  So only windows of
``window - P + 1`` words that begin at cover positions are hashed and shuffled.  An anchor that occurs elsewhere is then
extended: all full windows around it are hashed, and those found twice decide.  What is shuffled are packed arrays of
hashes with the row's key; an anchor found twice within a batch travels once per batch, so a passage that a third of all
rows share makes as many records as there are batches.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .tables import parts, row_key, small_batches, table
from .textbatch import U64, Words, chunks, mix, uint64_blob

# Perfect difference sets (modulus, residues); every non-zero residue is a difference of two members.
COVERS = {7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (0, 1, 4, 14, 16), 31: (0, 1, 3, 8, 12, 18), 57: (0, 1, 3, 13, 32, 36, 43, 52)}


def cover_for(window: int) -> tuple[int, tuple[int, ...]]:
    """The largest listed period whose anchors keep at least a third of the window (1, with every position, for short windows)."""
    fit = [p for p in COVERS if window - p + 1 >= max(2, window / 3)]
    return (max(fit), COVERS[max(fit)]) if fit else (1, (0,))


BLOBS = "bucket long, hashes binary, keys binary"
BLOB_SCHEMA = pa.schema([("bucket", pa.int64()), ("hashes", pa.binary()), ("keys", pa.binary())])


def _dealt(bucket: np.ndarray, hashes: np.ndarray, keys: np.ndarray, kind: str) -> pa.RecordBatch:
    """A row per bucket with the packed hashes and keys that belong there."""
    order = np.argsort(bucket, kind="stable")
    bucket, hashes, keys = bucket[order], hashes[order].astype(kind), keys[order]
    at = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(bucket)]])
    cut = list(zip(at[:-1], at[1:], strict=True))
    columns = [pa.array(bucket[at[:-1]], pa.int64()), pa.array([hashes[a:b].tobytes() for a, b in cut], pa.binary()), pa.array([uint64_blob(keys[a:b]) for a, b in cut], pa.binary())]
    return pa.RecordBatch.from_arrays(columns, ["bucket", "hashes", "keys"])


def dealt_to(keys: np.ndarray, groups: int) -> np.ndarray:
    """The group of each row key: the same as ``pmod`` of the signed key in Spark, whatever the number of groups."""
    return keys.view(np.int64) % groups


def _packed(keys: np.ndarray, hashes: np.ndarray, buckets: int, kind: str) -> Iterator[pa.RecordBatch]:
    """What a chunk sends: each hash once.

    A hash that occurs once here goes out with its row's key, which may get it back.  One that occurs more often is known
    to be repeated: it goes out once without a key, and its rows get their replies at once, dealt by the rows' keys.
    """
    if not len(hashes):
        return
    order = np.argsort(hashes, kind="stable")
    hashes, keys = hashes[order], keys[order]
    new = np.ones(len(hashes), bool)
    new[1:] = hashes[1:] != hashes[:-1]
    first = np.flatnonzero(new)
    size = np.diff(np.append(first, len(hashes)))
    own, one = keys[first], hashes[first]
    yield _dealt(dealt_to(one >> U64(33), buckets), one, np.where(size > 1, U64(0), own), kind)
    twice = np.repeat(size > 1, size)
    if twice.any():
        keys, hashes = keys[twice], hashes[twice]
        yield _dealt(buckets + dealt_to(keys, buckets), hashes, keys, kind)


def _replies(buckets: int, dests: int, kind: str):
    """Of one bucket: the hashes that another record has as well, with their rows' keys, dealt by the keys."""

    def run(group: pa.Table) -> pa.Table:
        hashes, keys = _joined(group, kind)
        if group.column("bucket")[0].as_py() < buckets:
            order = np.argsort(hashes, kind="stable")
            hashes, keys = hashes[order], keys[order]
            same = hashes[1:] == hashes[:-1]
            again = np.zeros(len(hashes), bool)
            again[1:] |= same
            again[:-1] |= same
            again &= keys != 0
            hashes, keys = hashes[again], keys[again]
        if not len(hashes):
            return pa.table({"bucket": pa.array([], pa.int64()), "hashes": pa.array([], pa.binary()), "keys": pa.array([], pa.binary())})
        return pa.Table.from_batches([_dealt(dealt_to(keys, dests), hashes, keys, kind)])

    return run


def _joined(rows: pa.Table, kind: str) -> tuple[np.ndarray, np.ndarray]:
    hashes = np.concatenate([np.zeros(0, kind), *[np.frombuffer(x, kind) for x in rows.column("hashes").to_pylist()]])
    keys = np.concatenate([np.zeros(0, "<u8"), *[np.frombuffer(x, "<u8") for x in rows.column("keys").to_pylist()]])
    return hashes, keys


class _Replied:
    """Whether a row, by its key, got a hash back."""

    def __init__(self, rows: pa.Table, kind: str):
        hashes, keys = _joined(rows, kind)
        self.kind, self.pairs = kind, np.sort(self._pair(keys, hashes))

    @staticmethod
    def _pair(keys: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        return mix(keys.astype(U64) * U64(0x9E3779B97F4A7C15) ^ mix(hashes.astype(U64) + U64(1)))

    def __call__(self, keys: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        if not len(self.pairs):
            return np.zeros(len(hashes), bool)
        sought = self._pair(keys, hashes.astype(self.kind))
        at = np.searchsorted(self.pairs, sought)
        at[at == len(self.pairs)] = 0
        return self.pairs[at] == sought


def _anchors(words: Words, size: int, period: int, cover: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first word, hash) of the windows at cover positions, counted within their row; and all word hashes."""
    word = words.hashes()
    at, hashes = words.windows(word, size)
    member = np.zeros(period, bool)
    member[list(cover)] = True
    take = member[(at - words.first[words.doc[at]]) % period]
    return at[take], hashes[take], word


def _spread(hit: np.ndarray, n: int, back: int, ahead: int) -> np.ndarray:
    """Positions p with some hit in [p - ahead, p + back]."""
    edge = np.zeros(n + back + ahead + 2, np.int64)
    np.add.at(edge, np.maximum(hit - back, 0), 1)
    np.add.at(edge, hit + ahead + 1, -1)
    return np.cumsum(edge)[:n] > 0


def _finish(words: Words, keys: np.ndarray, replied: _Replied, window: int, keep_text: bool) -> list[pa.Array]:
    """n_words, n_removed and what is kept, for each row of a chunk."""
    word = words.hashes()
    first, full = words.windows(word, window)
    gone = _spread(first[replied(keys[words.doc[first]], full)], len(word), 0, window - 1)
    removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[words.first])
    out = []
    for k in range(words.chunk.n):
        kept = words.chunk.text(k).split()
        if removed[k]:
            kept = compress(kept, (~gone[words.first[k] : words.first[k + 1]]).tolist())
        out.append(b" ".join(kept))
    text = pa.array(out, pa.binary()).cast(pa.string()) if keep_text else pa.array([hashlib.sha256(x).hexdigest() for x in out], pa.string())
    return [pa.array(words.count, pa.int64()), pa.array(removed, pa.int64()), text]


def remove_repeats(docs: DataFrame, window: int = 35, keep_text: bool = True, text_column: str = "text", keep: list[str] | None = None, buckets: int | None = None) -> DataFrame:
    """Columns of ``docs`` (or those of ``keep``) with n_words, n_removed and the kept words joined by spaces.

    The last is ``kept_text``, or ``kept_sha256`` of its UTF-8.  Windows are judged on the input.  Null text has no words;
    texts shorter than the window stay whole; repeated rows repeat each other's windows, so both lose them; null ids are
    kept; an empty table gives no row; columns named as the new ones are replaced.  Rows meet their replies by a hash of
    all kept columns and the text, which equal rows share; nothing depends on partition numbers or row order.

    Anchors travel as 32 bits beside their bucket number, as they only choose what is extended; windows with 64 bits.
    Texts are shuffled once: both meetings with replies read the same exchange.
    """
    small_batches(docs.sparkSession)
    buckets = dests = buckets or parts(docs.sparkSession)
    period, cover = cover_for(window)
    size = window - period + 1
    new = {"n_words": "long", "n_removed": "long", "kept_text" if keep_text else "kept_sha256": "string"}
    kept = [c for c in (keep if keep is not None else docs.columns) if c not in new and c != text_column]
    source = docs.select(*[F.col(f"`{c}`").alias(f"_{k}") for k, c in enumerate(kept)], F.col(text_column).alias("text"))
    key = row_key(*source.columns)
    source = source.withColumn("key", F.when(key == 0, 1).otherwise(key))
    dealt = source.withColumn("dest", F.pmod("key", F.lit(dests)))

    def send(batches):
        for chunk in chunks(batches):
            words = chunk.words()
            at, hashes, _ = _anchors(words, size, period, cover)
            yield from _packed(chunk.ints("key").view(U64)[words.doc[at]], hashes, buckets, "<u4")

    def extend(rows: pa.Table, replies: pa.Table) -> pa.Table:
        replied, out = _Replied(replies, "<u4"), []
        for chunk in chunks(rows.to_batches()) if len(replied.pairs) else ():
            words, keys = chunk.words(), chunk.ints("key").view(U64)
            at, hashes, word = _anchors(words, size, period, cover)
            hit = at[replied(keys[words.doc[at]], hashes)]
            first, full = words.windows(word, window)
            near = _spread(hit, len(word), period - 1, 0)[first]
            out += _packed(keys[words.doc[first[near]]], full[near], buckets, "<u8")
        return pa.Table.from_batches(out, BLOB_SCHEMA)

    def finish(rows: pa.Table, replies: pa.Table) -> pa.Table:
        replied, out = _Replied(replies, "<u8"), []
        for chunk in chunks(rows.to_batches()):
            columns = [chunk.rows.column(chunk.rows.schema.get_field_index(f"_{k}")) for k in range(len(kept))]
            columns += _finish(chunk.words(), chunk.ints("key").view(U64), replied, window, keep_text)
            out.append(pa.RecordBatch.from_arrays(columns, [*kept, *new]))
        return pa.Table.from_batches(out) if out else empty.empty_table()

    def replies_of(sent: DataFrame, kind: str) -> DataFrame:
        return sent.groupBy("bucket").applyInArrow(_replies(buckets, dests, kind), BLOBS)

    schema = T.StructType([T.StructField(c, docs.schema[c].dataType) for c in kept] + [T.StructField(c, T._parse_datatype_string(t)) for c, t in new.items()])
    empty = to_arrow_schema(schema)
    anchors = replies_of(source.select("key", "text").mapInArrow(send, BLOBS), "<u4")
    windows = dealt.groupBy("dest").cogroup(anchors.groupBy("bucket")).applyInArrow(extend, BLOBS)
    full = replies_of(windows, "<u8")
    return dealt.groupBy("dest").cogroup(full.groupBy("bucket")).applyInArrow(finish, schema)


def op5_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"), keep_text=False, keep=["doc_id"])
