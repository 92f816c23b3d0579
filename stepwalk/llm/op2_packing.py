"""Bounded-space online packing of token sequences.

Every partition keeps a fixed number of open windows.  A document first gives away whole windows, then its rest goes to
the open window that it fills best; when it fits none, the fullest window is topped up with a cut of it and emitted.
What the partitions still hold open at their end is merged in rounds of bounded fan-in, again filling windows exactly,
and the last open window is cut at powers of two, which need no padding.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import small_batches, table, written
from .textbatch import Chunk, KnownWords, chunks, kept_in_worker

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
NAMES = [x.split()[0] for x in PIECES.split(", ")]


class WordTokens:
    """Token ids of whole texts by a tokenizer that never joins across ASCII white space.

    Each distinct word of a batch is encoded once, and up to ``limit`` words are remembered.  Words are joined by a control mark of a single id that the word list never holds;
    words that hold it are encoded alone.
    """

    MARK = "\x01"

    def __init__(self, path: str, limit: int = 600_000):
        from tokenizers import Tokenizer

        self.encoder = Tokenizer.from_file(path)
        mark = self.encoder.encode(self.MARK, add_special_tokens=False).ids
        self.mark = mark[0] if len(mark) == 1 else None
        self.words = KnownWords(self.encode_words, limit)

    def encode_words(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids one after the other, ids per word)."""
        mark = self.MARK.encode()
        odd = [k for k, w in enumerate(words) if mark in w] if self.mark is not None else list(range(len(words)))
        plain = words
        if odd:
            plain = list(words)
            for k in odd:
                plain[k] = b""
        groups = [f" {self.MARK} ".join([x.decode("utf-8", "replace") for x in plain[i : i + 2000]]) + f" {self.MARK}" for i in range(0, len(plain), 2000)]
        some = [np.zeros(0, np.int32)]
        for i in range(0, len(groups), 8):  # an encoding holds each token as a string too
            some += [np.array(e.ids, dtype=np.int32) for e in self.encoder.encode_batch_fast(groups[i : i + 8], add_special_tokens=False)]
        flat = np.concatenate(some)
        if not odd:
            ends = np.flatnonzero(flat == self.mark)
            assert len(ends) == len(words)
            size = np.diff(np.concatenate([[-1], ends])) - 1
            return flat[flat != self.mark], size
        alone = {k: self.encoder.encode(words[k].decode("utf-8", "replace"), add_special_tokens=False).ids for k in odd}
        if self.mark is None:
            split = [alone[k] for k in range(len(words))]
        else:
            split = np.split(flat, np.flatnonzero(flat == self.mark) + 1)[: len(words)]
            split = [alone[k] if k in alone else x[:-1] for k, x in enumerate(split)]
        size = np.array([len(x) for x in split], dtype=np.int64)
        return np.concatenate([np.asarray(x, dtype=np.int32) for x in split] or [np.zeros(0, np.int32)]), size

    def __call__(self, chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows one after the other, ids per row)."""
        words = chunk.words()
        data = chunk.bytes.tobytes()
        ids, per = self.words(words.hashes(), lambda k: data[words.start[k] : words.end[k]])
        return ids, np.diff(np.concatenate([[0], np.cumsum(per)])[words.first])


def word_tokens(path: str) -> WordTokens:
    """One encoder per Python worker: its word list outlives a task."""
    return kept_in_worker(("tokens", path), lambda: WordTokens(path))


class Windows:
    """Open windows of one partition.  ``put`` returns (window, offset, take) for each piece; full windows close."""

    def __init__(self, size: int, open_windows: int):
        self.size, self.most = size, open_windows
        self.fill: dict[int, int] = {}
        self.next = 0

    def _new(self) -> int:
        self.next += 1
        self.fill[self.next - 1] = 0
        return self.next - 1

    def _add(self, window: int, take: int) -> tuple[int, int, int]:
        at = self.fill[window]
        if at + take == self.size:
            del self.fill[window]
        else:
            self.fill[window] = at + take
        return window, at, take

    def put(self, length: int) -> list[tuple[int, int, int]]:
        out = []
        while length >= self.size:
            out.append(self._add(self._new(), self.size))
            length -= self.size
        while length:
            fits = [(f, w) for w, f in self.fill.items() if f + length <= self.size]
            if fits:
                out.append(self._add(max(fits)[1], length))
                break
            if len(self.fill) < self.most:
                out.append(self._add(self._new(), length))
                break
            fullest = max((f, w) for w, f in self.fill.items())[1]
            take = self.size - self.fill[fullest]
            out.append(self._add(fullest, take))
            length -= take
        return out


def _powers(length: int) -> list[int]:
    """Sizes with no padding whose sum is ``length``: its binary digits, largest first."""
    return [1 << b for b in range(length.bit_length() - 1, -1, -1) if length >> b & 1]


def _pack_partition(encode: Callable[[Chunk], tuple[np.ndarray, np.ndarray]], size: int, open_windows: int, end_id: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        windows, left = Windows(size, open_windows), {}

        def batch(rows: list[tuple]) -> pa.RecordBatch:
            columns = zip(*rows, strict=True)
            return pa.RecordBatch.from_arrays([pa.array(c, pa.binary() if n == "ids" else pa.int64()) for n, c in zip([*NAMES, "ids"], columns, strict=True)], [*NAMES, "ids"])

        for chunk in chunks(batches, limit=1 << 19):
            ids, per_doc = encode(chunk)
            begin = np.cumsum(per_doc) - per_doc
            keys = chunk.rows.column(0).to_pylist()
            rows = []
            for k in range(chunk.n):
                doc = ids[begin[k] : begin[k] + per_doc[k]].astype("<u4")
                if end_id is not None:
                    doc = np.append(doc, np.uint32(end_id))
                data, at = doc.tobytes(), 0
                for window, offset, take in windows.put(len(doc)):
                    cut = data[4 * at : 4 * (at + take)]
                    left.setdefault(window, []).append((keys[k], at, take, zlib.crc32(cut), len(doc), part << 32 | window, offset, cut))
                    at += take
                    if window not in windows.fill:
                        rows += [(*r[:-1], None) for r in left.pop(window)]
            if rows:
                yield batch(rows)
        rows = [r for window in sorted(left) for r in left[window]]
        if rows:
            yield batch(rows)

    return run


def _merge(size: int):
    """Open windows that meet in one group: joined end to end, cut into full windows; the rest is cut at powers of two."""

    def run(group: pa.Table) -> pa.Table:
        rows = sorted(group.select([*NAMES, "ids"]).to_pylist(), key=lambda r: (r["sequence_id"], r["offset"]))
        total = sum(r["length"] for r in rows)
        sizes = [size] * (total // size) + _powers(total % size)
        base = 1 << 62 | min(r["sequence_id"] for r in rows)
        out, window, used = [], 0, 0
        for r in rows:
            at = 0
            while at < r["length"]:
                take = min(r["length"] - at, sizes[window] - used)
                crc = zlib.crc32(r["ids"][4 * at : 4 * (at + take)])
                out.append(r | {"start": r["start"] + at, "length": take, "ids_crc32": crc, "sequence_id": base + window, "offset": used})
                at, used = at + take, used + take
                if used == sizes[window]:
                    window, used = window + 1, 0
        return pa.table({n: pa.array([r[n] for r in out], pa.int64()) for n in NAMES})

    return run


def pack(docs: DataFrame, tokenizer: str, size: int = 2048, open_windows: int = 16, end_id: int | None = 1, fan_in: int = 64, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    ``tokenizer`` is the path of a tokenizer file; ``end_id`` ends every document (None: none, empty documents then give
    no piece).  Null text counts as empty; a null id is kept; repeated rows are packed each; an empty table gives no row;
    extra columns are ignored.  Space per task: ``open_windows`` windows and one batch.  Pieces are written once to the
    shared folder.  Windows still open at the end of partitions (at most ``open_windows`` each, with their ids) meet in
    groups of ``fan_in`` partitions; the tail of a group gives sequences whose lengths are powers of two, hence unpadded.
    """
    small_batches(docs.sparkSession)
    source = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).alias("text"))
    found = source.mapInArrow(_pack_partition(lambda chunk: word_tokens(tokenizer)(chunk), size, open_windows, end_id), PIECES + ", ids binary")
    pieces = written(found, "pieces")
    part = F.shiftright(F.shiftright("sequence_id", 32), int(fan_in).bit_length() - 1)
    merged = pieces.where("ids is not null").groupBy(part.alias("meet")).applyInArrow(_merge(size), PIECES)
    return pieces.where("ids is null").drop("ids").unionByName(merged)


def padding(pieces: DataFrame, size: int = 2048) -> DataFrame:
    """One row: sequences, tokens, padded (what filling up to ``size`` adds where a length is no power of two)."""
    used = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.expr("n & (n - 1)") == 0, 0).otherwise(size - F.col("n"))
    return used.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padded"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
