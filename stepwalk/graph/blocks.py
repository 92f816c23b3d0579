"""Edges in packed blocks: one row holds the edges of many vertices as compressed arrays.

Shuffling and keeping 200 M edges as rows costs 30 to 40 bytes an edge; packed they take 3 to 6.  A vertex lies in one block,
by ``part_of``; a block is read whole by one task, so blocks are many enough that one is small.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..walk.kernel import ragged

FLUSH = 1 << 20
NULL = -(1 << 63)


def squeezed(values: np.ndarray) -> bytes:
    """Bytes of equal weight together, then compressed: the high bytes of ids nearly vanish."""
    if not len(values):
        return b""
    return pa.compress(np.ascontiguousarray(values.view(np.uint8).reshape(-1, 8).T).tobytes(), codec="zstd", asbytes=True)


def spread(body: bytes, n: int, dtype) -> np.ndarray:
    if not n:
        return np.zeros(0, dtype)
    raw = pa.decompress(body, decompressed_size=8 * n, codec="zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, n).T).reshape(-1).view(dtype)


def block_of(v: np.ndarray, blocks: int) -> np.ndarray:
    """``part_of`` in arrays."""
    return (v ^ (v >> 16)) % blocks


def _column(batch: pa.RecordBatch, name: str) -> np.ndarray:
    column = batch.column(name)
    if column.null_count:
        raise ValueError(f"null {name} in an edge")
    return np.asarray(column)


def packed(edges: DataFrame, blocks: int) -> DataFrame:
    """(block, n, src, dst, w): the edges (src, dst, w), dealt by src, a row for each block and about a million edges read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held.append([_column(b, c) for c in ("src", "dst", "w")])
            n += b.num_rows
            if n >= FLUSH:
                yield dealt(held)
                held, n = [], 0
        if n:
            yield dealt(held)

    def dealt(held: list) -> pa.RecordBatch:
        arrays = [np.concatenate(x) for x in zip(*held)]
        block = block_of(arrays[0], blocks)
        order = np.argsort(block.astype(np.uint16) if blocks <= 1 << 16 else block, kind="stable")
        names, begin, counts = np.unique(block[order], return_index=True, return_counts=True)
        columns = [[squeezed(a[order[i : i + k]]) for i, k in zip(begin, counts)] for a in arrays]
        return pa.RecordBatch.from_arrays([pa.array(names, pa.int32()), pa.array(counts, pa.int64()), *[pa.array(c, pa.binary()) for c in columns]], names=["block", "n", "src", "dst", "w"])

    return edges.select("src", "dst", "w").mapInArrow(run, "block int, n long, src binary, dst binary, w binary")


def _sorted_edges(rows: pa.Table, dtype) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A block's edges in the order of (src, dst)."""
    counts = rows.column("n").to_pylist()
    src, dst, w = (np.concatenate([spread(x.as_buffer(), n, kind) for x, n in zip(rows.column(c), counts)]) for c, kind in (("src", np.int64), ("dst", np.int64), ("w", dtype)))
    order = np.lexsort((dst, src))
    return src[order], dst[order], w[order]


def counted(pairs: DataFrame, blocks: int) -> DataFrame:
    """(a, b, w): each pair (a, b) once, and how often it is there; the same rows as a count by a and b."""
    known = pairs.select(*[F.coalesce(F.col(x), F.lit(NULL)).alias(y) for x, y in (("a", "src"), ("b", "dst"))], F.lit(1).cast("long").alias("w"))

    def run(rows: pa.Table) -> pa.Table:
        src, dst, _ = _sorted_edges(rows, np.int64)
        first = np.flatnonzero(np.concatenate([[True], (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])]))
        return pa.table({"a": src[first], "b": dst[first], "w": np.diff(np.append(first, len(src)))})

    found = packed(known, blocks).groupBy("block").applyInArrow(run, "a long, b long, w long")
    return found.select(*[F.nullif(x, F.lit(NULL)).alias(x) for x in ("a", "b")], "w")


def adjacency_blocks(edges: DataFrame, blocks: int) -> DataFrame:
    """(block, n, m, vids, deg, ids, ws): the lists of a block's vertices, one after the other; ``n`` edges, ``m`` vertices.

    ``ids`` are the differences of neighbours that follow each other.
    """
    dtype = _dtype(edges)

    def run(rows: pa.Table) -> pa.Table:
        src, dst, w = _sorted_edges(rows, dtype)
        vids, deg = np.unique(src, return_counts=True)
        columns = {"block": pa.array([rows.column("block")[0].as_py()], pa.int32()), "n": [len(src)], "m": [len(vids)]}
        return pa.table(columns | {k: pa.array([squeezed(x)], pa.binary()) for k, x in (("vids", vids), ("deg", deg.astype(np.int64)), ("ids", np.diff(dst, prepend=0)), ("ws", w))})

    return packed(edges, blocks).groupBy("block").applyInArrow(run, "block int, n long, m long, vids binary, deg binary, ids binary, ws binary")


def _dtype(edges: DataFrame):
    return np.float64 if dict(edges.dtypes)["w"] == "double" else np.int64


class Block:
    """A block's lists as arrays."""

    def __init__(self, row: dict, dtype, lists: bool = True):
        n, m = row["n"], row["m"]
        self.vids, self.deg = spread(row["vids"], m, np.int64), spread(row["deg"], m, np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.deg)])
        self.ws = spread(row["ws"], n, dtype)
        if lists:
            self.ids = np.cumsum(spread(row["ids"], n, np.int64))

    @cached_property
    def prefix(self) -> np.ndarray:
        return np.concatenate([np.zeros(1, self.ws.dtype), np.cumsum(self.ws)])

    @cached_property
    def _keys(self) -> tuple:
        """(sorted keys of (vertex, neighbour), whether some are equal, smallest neighbour, bits of a neighbour or the neighbours' names)."""
        low = int(self.ids.min())
        bits = max(1, (int(self.ids.max()) - low).bit_length())
        rows = np.repeat(np.arange(len(self.vids)), self.deg)
        if bits + len(self.vids).bit_length() < 63:
            keys, names = (rows << bits) + (self.ids - low), None
        else:
            names = np.unique(self.ids)
            keys = rows * len(names) + np.searchsorted(names, self.ids)
        return keys, bool((keys[1:] == keys[:-1]).any()), low, bits, names

    def slot(self, v: np.ndarray) -> np.ndarray:
        """Index of each vertex, -1 where it is not here."""
        at = np.minimum(np.searchsorted(self.vids, v), len(self.vids) - 1)
        return np.where(self.vids[at] == v, at, -1)

    def find(self, slot: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which x, where): the places of x in the lists of ``slot`` (none for -1), all of them where an edge is there more than once."""
        keys, repeated, low, bits, names = self._keys
        if names is None:
            fits = (slot >= 0) & (x >= low) & (x <= low + (1 << bits) - 1)
            sought = (slot << bits) + np.where(fits, x - low, 0)
        else:
            code = np.minimum(np.searchsorted(names, x), len(names) - 1)
            fits = (slot >= 0) & (names[code] == x)
            sought = slot * len(names) + code
        at = np.minimum(np.searchsorted(keys, sought), len(keys) - 1)
        hit = np.flatnonzero(fits & (keys[at] == sought))
        if not repeated:
            return hit, at[hit]
        many = np.searchsorted(keys, sought[hit], side="right") - at[hit]
        return np.repeat(hit, many), ragged(at[hit], many)


def vertices(blocks: DataFrame, dtype) -> DataFrame:
    """(vid, deg, wmin, wmax) of every vertex."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            b = Block(row, dtype, lists=False)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (b.vids, b.deg, np.minimum.reduceat(b.ws, b.offsets[:-1]), np.maximum.reduceat(b.ws, b.offsets[:-1]))], names=["vid", "deg", "wmin", "wmax"])

    w = "double" if dtype == np.float64 else "long"
    return blocks.mapInArrow(run, f"vid long, deg long, wmin {w}, wmax {w}")


def lists_of(blocks: DataFrame, dtype, only: np.ndarray) -> DataFrame:
    """(vid, deg, wmin, wmax, ids, ws) of the vertices named (sorted)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            b = Block(row, dtype)
            mine = np.flatnonzero(np.isin(b.vids, only))
            for some in np.array_split(mine, max(1, int(b.deg[mine].sum()) >> 20)):
                if len(some):
                    at = ragged(b.offsets[some], b.deg[some])
                    offsets = pa.array(np.concatenate([[0], np.cumsum(b.deg[some])]), pa.int32())
                    ids, ws = (pa.ListArray.from_arrays(offsets, pa.array(x[at])) for x in (b.ids, b.ws))
                    begin = offsets.to_numpy()[:-1]
                    yield pa.RecordBatch.from_arrays([pa.array(b.vids[some]), pa.array(b.deg[some]), *[pa.array(f.reduceat(b.ws[at], begin)) for f in (np.minimum, np.maximum)], ids, ws], names=["vid", "deg", "wmin", "wmax", "ids", "ws"])

    w = "double" if dtype == np.float64 else "long"
    return blocks.mapInArrow(run, f"vid long, deg long, wmin {w}, wmax {w}, ids array<long>, ws array<{w}>")


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for b in batches:
        for i in range(b.num_rows):
            yield b.slice(i, 1).to_pylist()[0]


def deltas(ids: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Of each list, its first id and then the differences: small numbers compress."""
    out = np.diff(ids, prepend=0)
    first = offsets[:-1][np.diff(offsets) > 0]
    out[first] = ids[first]
    return out


def undeltas(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    sums = np.concatenate([[0], np.cumsum(values)])
    return sums[1:] - np.repeat(sums[offsets[:-1]], np.diff(offsets))


__all__ = ["Block", "adjacency_blocks", "block_of", "counted", "deltas", "lists_of", "packed", "undeltas", "vertices"]
