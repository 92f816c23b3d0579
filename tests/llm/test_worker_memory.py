"""What Python workers hold: the language parser's build and what stays for the stages after it."""

from __future__ import annotations

import tracemalloc
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
from pyspark import TaskContext

from stepwalk.llm.op2_packing import _pack_partition
from stepwalk.llm.op6_minhash import _sketch
from stepwalk.llm.op7_language import Parser, parser
from stepwalk.llm.textbatch import _KEPT


def _samples(n: int, size: int) -> dict[str, bytes]:
    r = np.random.default_rng(4)
    return {f"l{k}": r.choice(np.frombuffer(b"abcdefghijklmnopqrstuvwxyz      ", np.uint8), size).tobytes() for k in range(n)}


def test_parser_is_built_in_little_more_than_its_table():
    samples = _samples(8, 8000)
    tracemalloc.start()
    built = Parser(samples)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 1.6 * built.table.nbytes


def test_parser_goes_when_minhash_begins():
    parser(_samples(1, 200))
    assert _KEPT
    assert list(_sketch(iter(()))) == [] and not _KEPT


def test_packing_encodes_half_a_megabyte_at_once(monkeypatch):
    monkeypatch.setattr(TaskContext, "get", staticmethod(lambda: SimpleNamespace(partitionId=lambda: 0)))
    sizes = []

    def encode(chunk):
        sizes.append(len(chunk.bytes))
        return np.zeros(chunk.n, np.int32), np.ones(chunk.n, np.int64)

    batch = pa.record_batch({"doc_id": range(100), "text": ["x" * 20000] * 100})
    packed = list(_pack_partition(encode, 2048, 16, 1)([batch]))
    assert sum(sizes) == 2_000_000 and max(sizes) <= 1 << 19
    assert sum(b.num_rows for b in packed) == 100
