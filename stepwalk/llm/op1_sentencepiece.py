"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie of pieces with log scores.

Texts are cut where no piece can cross (before a run of spaces, around line breaks if no piece holds one), which leaves the
best path unchanged.  Each distinct stretch is encoded once per batch, all of them in lockstep: one trie step moves every
stretch by one byte.  Characters without a piece fall back to byte pieces.  Decoding joins pieces, turns the white-space
mark into spaces and runs of byte pieces into bytes.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from .tables import table, with_measures
from .textbatch import BYTES, U64, Chunk, KnownWords, kept_in_worker, mix, ragged, span_sums

MARK = "▁"
UNKNOWN_PENALTY = 10.0


class DoubleArray:
    """Trie over bytes as two arrays: the child of state s by byte b is t = base[s] + b + 1, if check[t] = s."""

    def __init__(self, keys: list[bytes]):
        children: list[dict[int, int]] = [{}]
        value = [-1]
        for number, key in enumerate(keys):
            node = 0
            for b in key:
                if b not in children[node]:
                    children[node][b] = len(children)
                    children.append({})
                    value.append(-1)
                node = children[node][b]
            value[node] = number
        # Wide nodes are placed first, each in the first gap from a front that moves on where it is crowded; nodes of one child then fill what is free.
        placed, used, front, free = {0: 0}, bytearray(4 * len(children) + 1024), 1, 257
        base = dict.fromkeys(range(len(children)), 0)
        used[0] = 1
        wide = sorted((n for n in range(len(children)) if len(children[n]) > 1), key=lambda n: -len(children[n]))
        for node in [*wide, *(n for n in range(len(children)) if len(children[n]) == 1)]:
            own = sorted(children[node])
            if len(own) > 1:
                at, tries = max(front, own[0] + 1), 0
                while any(used[at + b - own[0]] for b in own):
                    at, tries = at + 1, tries + 1
                    if at + 256 >= len(used):
                        used.extend(bytes(len(used)))
                if tries > 64:
                    front = at - 32
            else:
                while used[free]:
                    free += 1
                at = free
                while used[at]:
                    at += 1
                    if at >= len(used):
                        used.extend(bytes(len(used)))
            base[node] = at - own[0] - 1
            for b in own:
                used[base[node] + b + 1] = 1
                placed[children[node][b]] = base[node] + b + 1
        size = max(placed.values()) + 300
        self.base, self.check, self.value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        for node, state in placed.items():
            self.base[state], self.value[state] = base[node], value[node]
            for child in children[node].values():
                self.check[placed[child]] = state

    def step(self, state: np.ndarray, byte: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(next states, which exist)."""
        to = self.base[state] + byte + 1
        return to, self.check[to] == state


class Unigram:
    """Pieces with log scores; ids as in the model."""

    LONG = 48

    def __init__(self, pieces: list[tuple[str, float, str]], unknown_id: int = 0, add_prefix: bool = True):
        """``pieces``: (text, score, kind) by id; kind is normal, byte, unknown or control."""
        self.add_prefix, self.unknown_id = add_prefix, unknown_id
        normal = [(t.encode(), s, i) for i, (t, s, k) in enumerate(pieces) if k == "normal"]
        self.trie = DoubleArray([t for t, _, _ in normal])
        self.score = np.array([s for _, s, _ in normal], np.float64)
        self.id = np.array([i for _, _, i in normal], np.int32)
        self.unknown_score = float(self.score.min(initial=0.0)) - UNKNOWN_PENALTY
        self.longest = max((len(t) for t, _, _ in normal), default=1)
        self.byte_id = np.full(256, -1, np.int32)
        for i, (t, _, k) in enumerate(pieces):
            if k == "byte":
                self.byte_id[int(t[3:5], 16)] = i
        mark = MARK.encode()
        text = [b"" if k == "control" else bytes([int(t[3:5], 16)]) if k == "byte" else b" \xe2\x81\x87 " if k == "unknown" else t.encode().replace(mark, b" ") for t, _, k in pieces]
        self.text_bytes = np.frombuffer(b"".join(text), np.uint8)
        self.text_len = np.array([len(t) for t in text], np.int64)
        self.text_at = np.cumsum(self.text_len) - self.text_len
        self.cut_lines = not any(b"\n" in t for t, _, _ in normal)
        self.cut_spaces = not any(MARK in t.lstrip(MARK) for t, _, k in pieces if k == "normal")
        self.known = KnownWords(self.encode_stretches)

    @classmethod
    def from_model(cls, path: str) -> Unigram:
        """The pieces of a SentencePiece model file."""
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        kind = lambda i: "byte" if m.is_byte(i) else "unknown" if m.is_unknown(i) else "control" if m.is_control(i) or m.is_unused(i) else "normal"
        return cls([(m.id_to_piece(i), m.get_score(i), kind(i)) for i in range(m.get_piece_size())], m.unk_id())

    def _path(self, data: bytes) -> list[tuple[int, int]]:
        """(start, piece number or -1) of the best path of one stretch; the plain form, also for very long stretches."""
        n = len(data)
        best, back, via = [0.0] + [-np.inf] * n, [0] * (n + 1), [-1] * (n + 1)
        base, check, value = self.trie.base, self.trie.check, self.trie.value
        for s in range(n):
            if data[s] & 0xC0 == 0x80 or best[s] == -np.inf:
                continue
            width = 1
            while s + width < n and data[s + width] & 0xC0 == 0x80:
                width += 1
            state, single = 0, False
            for e in range(s, min(n, s + self.longest)):
                to = int(base[state]) + data[e] + 1
                if check[to] != state:
                    break
                state = to
                v = int(value[state])
                if v >= 0:
                    single |= e + 1 - s == width
                    c = best[s] + self.score[v]
                    if c > best[e + 1]:
                        best[e + 1], back[e + 1], via[e + 1] = c, s, v
            if not single and best[s] + self.unknown_score > best[s + width]:
                best[s + width], back[s + width], via[s + width] = best[s] + self.unknown_score, s, -1
        out = []
        while n:
            out.append((back[n], via[n]))
            n = back[n]
        return out[::-1]

    def _ids(self, data: bytes, path: list[tuple[int, int]]) -> list[int]:
        ends = [s for s, _ in path[1:]] + [len(data)]
        out: list[int] = []
        for (s, v), e in zip(path, ends, strict=True):
            if v >= 0:
                out.append(int(self.id[v]))
            elif (self.byte_id >= 0).all():
                out += self.byte_id[list(data[s:e])].tolist()
            elif not out or out[-1] != self.unknown_id:
                out.append(self.unknown_id)
        return out

    def encode_stretches(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids one after the other, ids per stretch)."""
        mark = MARK.encode()
        texts = [t.replace(b" ", mark) for t in texts]
        size = np.array([len(t) for t in texts], np.int64)
        out: list = [None] * len(texts)
        short = np.flatnonzero(size <= self.LONG)
        order = short[np.argsort(size[short], kind="stable")]
        for k in range(0, len(order), 1 << 15):
            own = order[k : k + (1 << 15)]
            self._lockstep([texts[i] for i in own], size[own], own, out)
        for i in np.flatnonzero(size > self.LONG):
            out[i] = np.array(self._ids(texts[i], self._path(texts[i])), np.int32)
        count = np.array([len(x) for x in out], np.int64)
        return (np.concatenate(out) if out else np.zeros(0, np.int32)), count

    def _lockstep(self, texts: list[bytes], size: np.ndarray, own: np.ndarray, out: list) -> None:
        n, deep = len(texts), int(size.max(initial=0))
        grid = np.zeros((n, deep + 1), np.int32)
        flat = np.frombuffer(b"".join(texts), np.uint8)
        grid[np.repeat(np.arange(n), size), ragged(np.zeros(n, np.int64), size)] = flat
        inner = (grid & 0xC0) == 0x80
        best = np.full((n, deep + 1), -np.inf)
        best[:, 0] = 0
        back, via = np.zeros((n, deep + 1), np.int16), np.full((n, deep + 1), -1, np.int32)
        for s in range(deep):
            live = np.flatnonzero((size > s) & ~inner[:, s] & (best[:, s] > -np.inf))
            if not len(live):
                continue
            width = np.ones(len(live), np.int64)
            for w in (1, 2, 3):
                if s + w <= deep:
                    width += (width == w) & inner[live, s + w] & (s + w < size[live])
            single = np.zeros(len(live), bool)
            at, state = np.arange(len(live)), np.zeros(len(live), np.int32)
            for e in range(s, min(deep, s + self.longest)):
                state, good = self.trie.step(state, grid[live[at], e])
                good &= e < size[live[at]]
                at, state = at[good], state[good]
                if not len(at):
                    break
                v = self.trie.value[state]
                end = np.flatnonzero(v >= 0)
                if not len(end):
                    continue
                single[at[end]] |= width[at[end]] == e + 1 - s
                row, v = live[at[end]], v[end]
                c = best[row, s] + self.score[v]
                up = c > best[row, e + 1]
                row = row[up]
                best[row, e + 1], back[row, e + 1], via[row, e + 1] = c[up], s, v[up]
            lone = np.flatnonzero(~single)
            row, to = live[lone], s + width[lone]
            c = best[row, s] + self.unknown_score
            up = c > best[row, to]
            row, to = row[up], to[up]
            best[row, to], back[row, to], via[row, to] = c[up], s, -1
        where, rows, steps = size.copy(), np.arange(n), []
        unknown = np.zeros(n, bool)
        while len(rows):
            rows = rows[where[rows] > 0]
            piece = via[rows, where[rows]]
            unknown[rows[piece < 0]] = True
            steps.append((rows, piece))
            where[rows] = back[rows, where[rows]]
        row = np.concatenate([r for r, _ in steps]) if steps else np.zeros(0, np.int64)
        piece = np.concatenate([p for _, p in steps]) if steps else np.zeros(0, np.int32)
        order = np.argsort(row, kind="stable")
        counts = np.bincount(row, minlength=n)
        ids = self.id[piece[order]] if len(self.id) else piece[order]
        edge = np.concatenate([[0], np.cumsum(counts)])
        for k in range(n):
            out[own[k]] = ids[edge[k] : edge[k + 1]][::-1]
        for k in np.flatnonzero(unknown):
            starts, p = [], int(size[k])
            while p:
                starts.append((int(back[k, p]), int(via[k, p])))
                p = int(back[k, p])
            out[own[k]] = np.array(self._ids(texts[k], starts[::-1]), np.int32)

    def encode_chunk(self, chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows one after the other, ids per row)."""
        data, at = chunk.bytes, chunk.offsets
        n = len(data)
        head = np.zeros(n + 1, bool)
        full = np.flatnonzero(np.diff(at) > 0)
        head[at[:-1][full]] = True
        starts = head[:n].copy()
        if self.cut_spaces:
            space = data == 32
            starts[1:] |= space[1:] & ~space[:-1]
        if self.cut_lines:
            line = data == 10
            starts |= line
            starts[1:] |= line[:-1]
        start = np.flatnonzero(starts)
        end = np.append(start[1:], n)
        first = head[start] & self.add_prefix
        raw = span_sums(data, start, end)
        raw = np.where(first, U64(33) + raw * U64(BYTES.base), raw)
        body = data.tobytes()
        word = lambda k: b" " + body[start[k] : end[k]] if first[k] else body[start[k] : end[k]]
        ids, per = self.known(mix(raw + (end - start + first).astype(U64)), word)
        total = np.concatenate([[0], np.cumsum(per)])
        return ids, np.diff(total[np.searchsorted(start, at)])

    def encode(self, text: str) -> list[int]:
        """Ids of one text, by the plain form over the whole text."""
        if not text:
            return []
        data = ((" " if self.add_prefix else "") + text).replace(" ", MARK).encode()
        return self._ids(data, self._path(data))

    def decode_bytes(self, ids: np.ndarray) -> np.ndarray:
        return self.text_bytes[ragged(self.text_at[ids], self.text_len[ids])]

    def decode(self, ids: list[int]) -> str:
        """Text of ids: pieces joined, marks as spaces, byte pieces as bytes (ill-formed ones replaced), the added space dropped."""
        text = self.decode_bytes(np.asarray(ids, np.int64)).tobytes()
        if self.add_prefix and text.startswith(b" "):
            text = text[1:]
        return text.decode("utf-8", "replace")


def model(path: str) -> Unigram:
    """Read once per Python worker."""
    return kept_in_worker(("unigram", path), lambda: Unigram.from_model(path))


def encode(docs: DataFrame, path: str, text_column: str = "text") -> DataFrame:
    """``docs`` with ids (array<int>).  Null and empty texts have none; an ids column is replaced; an empty table gives no row."""

    def compute(chunk: Chunk) -> dict:
        ids, per = model(path).encode_chunk(chunk)
        return {"ids": np.split(ids, np.cumsum(per)[:-1])}

    return with_measures(docs, compute, {"ids": "array<int>"}, text_column)


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """``encoded`` (an ids column) with decoded (string); null ids give null."""
    from pyspark.sql import functions as F

    @F.pandas_udf("string")
    def text(ids):
        return ids.map(lambda x: None if x is None else model(path).decode(x))

    return encoded.withColumn("decoded", text("ids"))


def digests(docs: DataFrame, path: str, text_column: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Per row n_pieces, n_byte_pieces, ids_crc32 (little-endian unsigned 32-bit ids) and round_trip (the decoded bytes are the text's).

    A text that holds the white-space mark itself decodes to a space there, so its round_trip is false; null counts as empty.
    """

    def compute(chunk: Chunk) -> dict:
        own = model(path)
        ids, per = own.encode_chunk(chunk)
        edge = np.concatenate([[0], np.cumsum(per)])
        is_byte = np.isin(ids, own.byte_id)
        back = own.decode_bytes(ids)
        made = np.concatenate([[0], np.cumsum(own.text_len[ids])])[edge]
        size = np.diff(chunk.offsets)
        extra = ((size > 0) & own.add_prefix).astype(np.int64)
        same = np.diff(made) == size + extra
        ok = same.copy()
        rows = np.flatnonzero(same & (size > 0))
        equal = back[ragged(made[rows] + extra[rows], size[rows])] == chunk.bytes[ragged(chunk.offsets[rows], size[rows])]
        ok[rows] = np.diff(np.concatenate([[0], np.cumsum(equal)])[np.concatenate([[0], np.cumsum(size[rows])])]) == size[rows]
        packed = ids.astype("<u4")
        return {
            "n_pieces": per, "n_byte_pieces": np.diff(np.concatenate([[0], np.cumsum(is_byte)])[edge]),
            "ids_crc32": [zlib.crc32(packed[a:b].tobytes()) for a, b in zip(edge[:-1], edge[1:], strict=True)], "round_trip": ok,
        }

    return with_measures(docs, compute, {"n_pieces": "long", "n_byte_pieces": "long", "ids_crc32": "long", "round_trip": "boolean"}, text_column, keep)


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(table(spark, sf_dir, "documents").select("doc_id", "text"), public_tokenizers.path("piece_bpe_32k.model"), keep=["doc_id"])
