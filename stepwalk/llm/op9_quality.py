"""Quality classifier by attention-based multiple-instance learning.

A document is a bag of passages.  Every passage is measured and encoded; a gated attention, learned from document labels
alone, weighs the encodings; the weighted sum is scored.  Training runs on a bounded, hash-chosen sample of labelled
rows; scoring is one pass over whole texts.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import hash_sample, held_back, table, with_measures, written
from .textbatch import U64, Chunk, mix, repeated_cover

PASSAGE_WORDS = 64

# Byte classes. 0 lower, 1 upper, 2 digit, 3 space, 4 newline, 5 other control, 6 non-ASCII, then each mark.
_CLASS = np.full(256, 5, np.int64)
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58], _CLASS[32], _CLASS[10], _CLASS[128:] = 0, 1, 2, 3, 4, 6
_MARKS = [b for b in range(33, 127) if not chr(b).isalnum()]
_CLASS[_MARKS] = np.arange(7, 7 + len(_MARKS))
CLASSES = 7 + len(_MARKS)
FEATURES = CLASSES + 6


def passages(chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """(features of each passage, passages per row); a text without words is one passage of zeros."""
    words = chunk.words()
    hashes = words.hashes()
    per = np.maximum(1, -(-words.count // PASSAGE_WORDS))
    base = np.cumsum(per) - per
    total = int(per.sum())
    nth = np.arange(len(hashes)) - words.first[:-1][words.doc]
    owner = base[words.doc] + nth // PASSAGE_WORDS
    begin = np.zeros(total + 1, np.int64)
    begin[base] = chunk.offsets[:-1]
    later = (nth % PASSAGE_WORDS == 0) & (nth > 0)
    begin[owner[later]] = words.start[later]
    begin[-1] = len(chunk.bytes)
    size = np.diff(begin)
    kind = np.repeat(np.arange(total) * CLASSES, size) + _CLASS[chunk.bytes]
    shares = np.bincount(kind, minlength=total * CLASSES).reshape(total, CLASSES) / np.maximum(size, 1)[:, None]
    n = np.bincount(owner, minlength=total)
    some = np.maximum(n, 1)
    letters = np.bincount(owner, words.end - words.start, total)
    again = np.zeros(len(hashes))
    again[1:] = (hashes[1:] == hashes[:-1]) & (words.doc[1:] == words.doc[:-1])
    own = np.sort(mix(hashes ^ (owner.astype(U64) * U64(0x9E3779B97F4A7C15))) >> U64(24) | owner.astype(U64) << U64(40)) if len(hashes) else hashes
    fresh = np.ones(len(own), bool)
    fresh[1:] = own[1:] != own[:-1]
    distinct = np.bincount((own[fresh] >> U64(40)).astype(np.int64), minlength=total)
    cover = np.bincount(owner, repeated_cover(words, hashes), total)
    rest = [letters / some / 10, np.bincount(owner, again, total) / some, distinct / some, cover / some, n / PASSAGE_WORDS, np.log1p(np.repeat(words.count, per)) / 10]
    return np.concatenate([shares, np.stack(rest, 1)], axis=1), per


class AttentionScorer:
    """Encoder, gated attention and scorer.  Plain arrays, a few kilobytes: it travels with the task."""

    def __init__(self, features: int = FEATURES, hidden: int = 24, gate: int = 12, seed: int = 7):
        draw = np.random.default_rng(seed).normal
        self.p = {
            "encode": draw(0, features**-0.5, (features, hidden)), "shift": np.zeros(hidden), "v": draw(0, hidden**-0.5, (hidden, gate)),
            "u": draw(0, hidden**-0.5, (hidden, gate)), "w": draw(0, gate**-0.5, gate), "score": draw(0, hidden**-0.5, hidden), "bias": np.zeros(1),
        }
        self.mean, self.scale = np.zeros(features), np.ones(features)
        self.constant: float | None = 0.5

    def forward(self, x: np.ndarray, per: np.ndarray) -> dict[str, np.ndarray]:
        p = self.p
        at = np.cumsum(per) - per
        doc = np.repeat(np.arange(len(per)), per)
        s = np.clip((x - self.mean) / self.scale, -8, 8)
        h = np.tanh(s @ p["encode"] + p["shift"])
        t, g = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
        e = (t * g) @ p["w"]
        e = np.exp(e - np.maximum.reduceat(e, at)[doc])
        a = e / np.add.reduceat(e, at)[doc]
        z = np.add.reduceat(a[:, None] * h, at, axis=0)
        y = 1 / (1 + np.exp(-np.clip(z @ p["score"] + p["bias"], -30, 30)))
        return {"s": s, "h": h, "t": t, "g": g, "a": a, "z": z, "y": y, "doc": doc, "at": at}

    def gradients(self, x: np.ndarray, per: np.ndarray, label: np.ndarray) -> dict[str, np.ndarray]:
        p, f = self.p, self.forward(x, per)
        d = (f["y"] - label) / len(label)
        dz = (d[:, None] * p["score"])[f["doc"]]
        da = (dz * f["h"]).sum(1)
        de = f["a"] * (da - np.add.reduceat(f["a"] * da, f["at"])[f["doc"]])
        both = de[:, None] * p["w"]
        dt, dg = both * f["g"] * (1 - f["t"] ** 2), both * f["t"] * f["g"] * (1 - f["g"])
        dh = (f["a"][:, None] * dz + dt @ p["v"].T + dg @ p["u"].T) * (1 - f["h"] ** 2)
        return {"encode": f["s"].T @ dh, "shift": dh.sum(0), "v": f["h"].T @ dt, "u": f["h"].T @ dg, "w": (f["t"] * f["g"]).T @ de, "score": f["z"].T @ d, "bias": np.array([d.sum()])}

    def fit(self, x: np.ndarray, per: np.ndarray, label: np.ndarray, epochs: int = 40, batch: int = 256, rate: float = 0.01, decay: float = 1e-4, seed: int = 7) -> AttentionScorer:
        """Adam over shuffled batches of bags; one class alone gives its share as a constant score."""
        if len(label) == 0 or label.min() == label.max():
            self.constant = float(label[0]) if len(label) else 0.5
            return self
        self.constant = None
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-3
        first, second = ({k: np.zeros_like(v) for k, v in self.p.items()} for _ in range(2))
        begin, step, random = np.cumsum(per) - per, 0, np.random.default_rng(seed)
        for _ in range(epochs):
            order = random.permutation(len(per))
            for k in range(0, len(order), batch):
                own = order[k : k + batch]
                rows = np.concatenate([np.arange(begin[i], begin[i] + per[i]) for i in own])
                step += 1
                for name, g in self.gradients(x[rows], per[own], label[own]).items():
                    g = g + decay * self.p[name]
                    first[name] = 0.9 * first[name] + 0.1 * g
                    second[name] = 0.999 * second[name] + 0.001 * g * g
                    self.p[name] -= rate * (first[name] / (1 - 0.9**step)) / (np.sqrt(second[name] / (1 - 0.999**step)) + 1e-8)
        return self

    def score(self, chunk: Chunk) -> np.ndarray:
        if self.constant is not None:
            return np.full(chunk.n, self.constant)
        return self.forward(*passages(chunk))["y"]


def train(docs: DataFrame, labels: DataFrame, per_label: int = 2000, most_passages: int = 200_000) -> AttentionScorer:
    """A scorer from ``labels`` (doc_id, quality) and the texts of ``docs``.

    About ``per_label`` rows of each label are taken by a hash of the id (repeated ids once, with their highest label), so
    the sample, which is broadcast, has a bound.  Of an id that several documents have, one text is taken (the smallest by
    hash).  The driver first gets the passages of each sampled text as a number and chooses, in hash order, texts that
    have at most ``most_passages`` together; only their features come to it.
    """
    unique = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("quality").alias("quality"))
    chosen = hash_sample(unique, "quality", per_label, "doc_id", most_groups=2)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").withColumn("place", F.xxhash64("doc_id", "text"))
    one = rows.groupBy("doc_id", "quality").agg(F.min("place").alias("place"))
    rows = rows.join(F.broadcast(one.withColumnsRenamed({"doc_id": "_id", "quality": "_q", "place": "_p"})), (F.col("doc_id") == F.col("_id")) & (F.col("place") == F.col("_p"))).drop("_id", "_q", "_p")
    rows = written(rows.dropDuplicates(["doc_id"]), "labelled")

    def sizes(chunk: Chunk) -> dict:
        return {"passages": np.maximum(1, -(-chunk.words().count // PASSAGE_WORDS))}

    def compute(chunk: Chunk) -> dict:
        x, per = passages(chunk)
        cut = np.split(x.astype(np.float32), np.cumsum(per)[:-1])
        return {"features": [c.tobytes() for c in cut]}

    taken, total = [], 0
    for r in sorted(with_measures(rows, sizes, {"passages": "long"}, keep=["doc_id", "place"]).collect(), key=lambda r: (r["place"], r["doc_id"])):
        if total + r["passages"] <= most_passages:
            taken.append((r["doc_id"],))
            total += r["passages"]
    if not taken:
        return AttentionScorer()
    rows = rows.join(F.broadcast(docs.sparkSession.createDataFrame(taken, "doc_id long")), "doc_id", "left_semi")
    found = with_measures(rows, compute, {"features": "binary"}, keep=["doc_id", "quality", "place"]).collect()
    found.sort(key=lambda r: (r["place"], r["doc_id"]))
    bags = [np.frombuffer(r["features"], np.float32).reshape(-1, FEATURES).astype(np.float64) for r in found]
    return AttentionScorer().fit(np.concatenate(bags), np.array([len(b) for b in bags]), np.array([r["quality"] for r in found], float))


def classify(docs: DataFrame, scorer: AttentionScorer, text_column: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with score (0 to 1, higher: label 1 likelier) and predicted (1 from 0.5 on).

    Whole texts are scored; null and empty texts as one empty passage; equal texts get equal scores; an empty table gives no
    row; columns named score or predicted are replaced, others kept.
    """

    def compute(chunk: Chunk) -> dict:
        score = scorer.score(chunk)
        return {"score": score, "predicted": (score >= 0.5).astype(np.int32)}

    return with_measures(docs, compute, {"score": "double", "predicted": "int"}, text_column, keep)


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    scorer = train(docs, labels.where(~held_back("doc_id", 3, 1)))
    found = classify(docs.select("doc_id", "text"), scorer, keep=["doc_id"])
    return found.select("doc_id", held_back("doc_id", 3, 1).alias("held_out"), "score", "predicted")
