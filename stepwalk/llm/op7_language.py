"""Language identification by cross-parsing against suffix automata of labelled text.

Each language has a suffix automaton of a bounded sample of its texts.  A text is parsed greedily into the longest
stretches that occur in the sample; few phrases mean little new information.  The language with the fewest phrases per
symbol, weighted by the logarithm of its sample's size, wins.  Texts are parsed in lockstep: blocks of fixed length are
lanes of one array, all languages at once, and one step moves every lane by one symbol; the blocks' parses are then joined
so that the phrases counted are those of one parse of the whole text.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import held_back, table, with_measures
from .textbatch import Chunk, kept_in_worker

BLOCK = 512
LANES = 1 << 14


def symbols(data: np.ndarray) -> np.ndarray:
    """Bytes reduced to letters in lower case and single gaps (32); bytes of non-ASCII characters stay, Latin-1 ones lowered.

    The result has as many entries as ``data``; 0 marks a place to leave out.
    """
    out = np.full(len(data), 32, np.uint8)
    low = data | 0x20
    letter = (low >= 97) & (low <= 122) & (data < 128)
    out[letter] = low[letter]
    high = data >= 128
    out[high] = data[high]
    if len(data):
        lead = np.zeros(len(data), bool)
        lead[1:] = data[:-1] == 0xC3
        upper = lead & (data >= 0x80) & (data <= 0x9E) & (data != 0x97)
        out[upper] = data[upper] + 0x20
        gap = out == 32
        out[1:][gap[1:] & gap[:-1]] = 0
    return out


def automaton(text: list[int]) -> tuple[list[dict[int, int]], int]:
    """Transitions of the suffix automaton of ``text``; state 0 is the root."""
    follow: list[dict[int, int]] = [{}]
    link, longest = [-1], [0]
    last = 0
    for c in text:
        new = len(follow)
        follow.append({})
        longest.append(longest[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in follow[p]:
            follow[p][c] = new
            p = link[p]
        if p >= 0:
            q = follow[p][c]
            if longest[p] + 1 == longest[q]:
                link[new] = q
            else:
                copy = len(follow)
                follow.append(dict(follow[q]))
                longest.append(longest[p] + 1)
                link.append(link[q])
                while p >= 0 and follow[p].get(c) == q:
                    follow[p][c] = copy
                    p = link[p]
                link[q] = link[new] = copy
        last = new
    return follow, last


def _moves(codes: np.ndarray) -> tuple[int, np.ndarray, np.ndarray, np.ndarray]:
    """(states, and of each transition of the suffix automaton: state, symbol, next state): small arrays, its dictionaries go."""
    follow, _ = automaton(codes.tolist())
    size = np.fromiter(map(len, follow), np.int32, len(follow))
    at, n = np.repeat(np.arange(len(follow), dtype=np.int32), size), int(size.sum())
    return len(follow), at, np.fromiter((c for f in follow for c in f), np.uint8, n), np.fromiter((s for f in follow for s in f.values()), np.int32, n)


class _Lanes:
    """Texts cut into blocks that are parsed side by side, and put together to what one parse of each whole text gives.

    A greedy parse depends on nothing but where a phrase starts.  Each block is parsed as if a phrase started with it, and its
    phrase starts are marked.  Then each block's parse goes on into the next block until one of its phrases starts at a
    marked place: from there on both parses are the same.  The starts that it passed replace the marked ones before that
    place.  Where a parse meets no mark within a block, it goes on, alone, until it meets one or the text ends.
    """

    def __init__(self, codes: np.ndarray, size: np.ndarray):
        each = -(-size // BLOCK)
        self.texts, self.text = len(size), np.repeat(np.arange(len(size)), each)
        self.n = len(self.text)
        first = np.cumsum(each) - each
        nth = np.arange(self.n) - np.repeat(first, each)
        start = (np.cumsum(size) - size)[self.text] + nth * BLOCK
        self.length = np.minimum(BLOCK, size[self.text] - nth * BLOCK)
        self.more = nth + 1 < each[self.text]  # another block of the text follows
        self.first, self.after = first[each > 0], (first + each)[each > 0]  # of the texts that have a block
        order = np.argsort(-self.length, kind="stable")
        self.column = np.empty(self.n, np.int64)
        self.column[order] = np.arange(self.n)
        deep = int(self.length.max(initial=0))
        self.active = np.searchsorted(-self.length[order], -np.arange(deep), side="left")
        self.blocks = np.zeros((deep, self.n), np.uint8)
        for i, a in enumerate(self.active):
            self.blocks[i, :a] = codes[start[order[:a]] + i]

    def counted(self, table: np.ndarray, roots: np.ndarray) -> np.ndarray:
        """Phrases of each text, (texts, roots)."""
        langs, n = len(roots), self.n
        state = np.tile(roots, (n, 1))
        marks = np.zeros((len(self.blocks), n, langs), np.int8)
        count = np.zeros((n, langs), np.int32)
        value, sign = np.empty_like(state), np.empty_like(state)
        for i, a in enumerate(self.active):
            np.add(state[:a], self.blocks[i, :a, None], out=state[:a])
            np.take(table, state[:a], out=value[:a], mode="clip")
            np.right_shift(value[:a], 31, out=sign[:a])
            np.bitwise_xor(value[:a], sign[:a], out=state[:a])
            np.subtract(count[:a], sign[:a], out=count[:a])
            marks[i, :a] = sign[:a]
        lane, lang = (x.ravel() for x in np.meshgrid(np.flatnonzero(self.more), np.arange(langs), indexing="ij"))
        change, reached, at = np.zeros((n, langs), np.int64), np.ones((n, langs), bool), state[self.column]
        at[lane, lang], change[lane, lang], met, _ = self._onward(table, marks, at[lane, lang], lane + 1, lang)
        reached[lane, lang] = met | ~self.more[lane + 1]
        total = np.zeros((self.texts, langs), np.int64)
        summed = np.concatenate([np.zeros((1, langs), np.int64), np.cumsum(np.where(reached, change, 0), axis=0)])
        np.add.at(total, self.text, count[self.column])
        total[self.text[self.first]] += summed[self.after] - summed[self.first]
        self._alone(table, marks, at, change, reached, summed, total)
        return total

    def _onward(self, table, marks, state, lane, lang):
        """Parses from the start of ``lane`` until they meet a mark of it or its end: (state, starts passed less marks passed, met, steps)."""
        state, change, met, steps = state.copy(), np.zeros(len(lane), np.int64), np.zeros(len(lane), bool), 0
        column, length = self.column[lane], self.length[lane]
        live = np.flatnonzero(length > 0)
        while len(live):
            now = table[state[live] + self.blocks[steps, column[live]]]
            own = now < 0
            state[live] = np.where(own, ~now, now)
            theirs = marks[steps, column[live], lang[live]] != 0
            both = own & theirs
            change[live] += own.astype(np.int64) - theirs
            met[live[both]] = True
            steps += 1
            live = live[~both & (length[live] > steps)]
        return state, change, met, steps

    def _alone(self, table, marks, at, change, reached, summed, total) -> None:
        """Mends ``total`` of texts where a parse went through a whole block without meeting a mark."""
        n, langs = reached.shape
        stuck = np.where(reached, n, np.arange(n)[:, None])
        stuck = np.minimum.accumulate(stuck[::-1], axis=0)[::-1]  # the next lane from here on that met no mark
        after = np.zeros(n, np.int64)
        after[self.first] = self.after
        after = np.maximum.accumulate(after)
        text, lang = np.nonzero(stuck[self.first] < self.after[:, None])
        lane = self.first[text]
        owner = self.text[lane]
        total[owner, lang] -= summed[after[lane], lang] - summed[lane, lang]  # counted anew below, along the true parse
        while len(lane):
            bad = stuck[lane, lang]
            end = np.minimum(bad, after[lane])
            np.add.at(total, (owner, lang), summed[end, lang] - summed[lane, lang])
            go = bad < after[lane]
            lane, lang, owner, bad = lane[go], lang[go], owner[go], bad[go]
            np.add.at(total, (owner, lang), change[bad, lang])
            state, lane = at[bad, lang], bad + 2
            out = [np.zeros(0, np.int64)] * 3
            while len(lane):
                state, passed, met, _ = self._onward(table, marks, state, lane, lang)
                np.add.at(total, (owner, lang), passed)
                out = [np.concatenate(x) for x in zip(out, (lane[met], lang[met], owner[met]), strict=True)]
                go = ~met & self.more[lane]
                state, lane, lang, owner = state[go], lane[go] + 1, lang[go], owner[go]
            lane, lang, owner = out


class Parser:
    """Automata of all languages in one table.

    An entry is the next state's row offset where the phrase goes on, else the complement of the offset at which a new
    phrase starts: the sign counts phrases and no branch is needed.  The table is filled in place, and the automata are
    built one after the other, so that building takes little more than the table.
    """

    def __init__(self, samples: dict[str, bytes]):
        self.names = sorted(samples)
        parsed = {n: symbols(np.frombuffer(samples[n], np.uint8)) for n in self.names}
        parsed = {n: x[x != 0] for n, x in parsed.items()}
        used = np.unique(np.concatenate([*parsed.values(), np.array([32], np.uint8)]))
        self.code = np.zeros(256, np.uint8)  # 0: left out, or never seen in any sample
        self.code[used] = np.arange(1, len(used) + 1)
        width = len(used) + 1
        self.width = width
        moves = [_moves(self.code[parsed[n]]) for n in self.names]
        ends = np.cumsum([0, *(states * width for states, *_ in moves)])
        self.roots = ends[:-1].tolist()
        self.table = np.zeros(max(1, ends[-1]), np.int32)
        for base, (states, at, by, to) in zip(self.roots, moves, strict=True):
            grid = self.table[base : base + states * width].reshape(states, width)
            first = at == 0
            start = np.full(width, base, np.int32)
            start[by[first]] += to[first] * np.int32(width)
            np.copyto(grid, ~start)
            grid[at[~first], by[~first]] = base + to[~first] * np.int32(width)
        self.log_size = np.array([np.log(len(parsed[n]) + 2.0) for n in self.names])

    def phrases(self, codes: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Phrases of each whole text (its symbols in ``codes``, ``size`` of each; code 0 is a phrase of its own): (texts, languages)."""
        texts = _Lanes(codes, size)
        some = max(1, LANES // max(1, texts.n))
        found = [texts.counted(self.table, np.array(self.roots[k : k + some], np.int32)) for k in range(0, len(self.roots), some)]
        return np.concatenate(found, axis=1)

    def counted(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(phrases of each text in each language, symbols of each text)."""
        reduced = symbols(data)
        inner = offsets[:-1][np.diff(offsets) > 0]
        first = data[inner] if len(inner) else data[:0]
        reduced[inner[(reduced[inner] == 0) & (first < 128)]] = 32
        keep = reduced != 0
        codes = self.code[reduced[keep]]
        size = np.diff(np.concatenate([[0], np.cumsum(keep)])[offsets])
        return self.phrases(codes, size), size

    def weighed(self, total: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Phrases per symbol, weighted by the size of the samples; nan where a text has no symbol."""
        with np.errstate(divide="ignore", invalid="ignore"):
            return total * self.log_size / size[:, None]

    def rates(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        return self.weighed(*self.counted(data, offsets))


def parser(samples: dict[str, bytes]) -> Parser:
    """Built once per Python worker from the samples, which are small enough to travel with the task."""
    digest = hashlib.sha256(b"\0".join(k.encode() + b"\1" + v for k, v in sorted(samples.items()))).hexdigest()
    return kept_in_worker(("parser", digest), lambda: Parser(samples))


def _has_letter(chunk: Chunk) -> np.ndarray:
    low = chunk.bytes | 0x20
    plain = (low >= 97) & (low <= 122) & (chunk.bytes < 128)
    some = np.diff(np.concatenate([[0], np.cumsum(plain)])[chunk.offsets]) > 0
    for k in np.flatnonzero(~some & (np.diff(chunk.offsets) > 0)):
        some[k] = any(c.isalpha() for c in chunk.text(k).decode("utf-8", "replace"))
    return some


def learn(labelled: DataFrame, symbols_per_language: int = 60_000, docs_per_language: int = 150, symbols_in_all: int = 4_000_000) -> dict[str, bytes]:
    """A sample of text of every language that has a text, of at most ``symbols_per_language`` bytes, from about ``docs_per_language`` rows each.

    ``labelled`` has doc_id, text, lang.  Rows are chosen by a hash of id and text, at least one a language.  A text is taken
    whole up to a tenth of the bound (more where a language has fewer than ten rows), else a span of that size at a place
    that the hash chooses.  Where languages are so many that their samples together would pass ``symbols_in_all`` (the
    parser's table has 32-bit offsets), all get an equal share of it.
    """
    place = F.pmod(F.xxhash64("doc_id", "text", F.lit(7)), F.lit(1 << 30))
    usable = labelled.where((F.octet_length("text") > 0) & F.col("lang").isNotNull()).select("lang", "text", place.alias("place"))
    counts = usable.groupBy("lang").agg(F.count("*").alias("n"), F.min("place").alias("first")).collect()
    if not counts:
        return {}
    bound = max(1, min(symbols_per_language, symbols_in_all // len(counts)))
    most = {r["lang"]: max(4, bound // min(10, r["n"])) for r in counts}
    rows = [(r["lang"], max(r["first"], int(min(1.0, docs_per_language / r["n"]) * (1 << 30))), most[r["lang"]]) for r in counts]
    upto = labelled.sparkSession.createDataFrame(rows, "lang string, upto long, most int")
    begin = F.pmod(F.xxhash64("place"), F.greatest(F.char_length("text") - F.col("most"), F.lit(0)) + 1).cast("int") + 1
    span = F.substring(F.substring("text", begin, F.col("most")).cast("binary"), F.lit(1), F.col("most"))
    piece = F.when(F.octet_length("text") <= F.col("most"), F.col("text").cast("binary")).otherwise(span)
    chosen = usable.join(F.broadcast(upto), "lang").where("place <= upto").select("lang", "place", piece.alias("piece")).distinct()
    taken: dict[str, list[bytes]] = {}
    for r in sorted(chosen.collect(), key=lambda r: (r["lang"], r["place"], r["piece"])):
        data = bytes(r["piece"]).decode("utf-8", "ignore").encode()
        if r["lang"] not in taken or sum(map(len, taken[r["lang"]])) + len(data) <= bound:
            taken.setdefault(r["lang"], []).append(data)
    return {k: b"\n".join(v) for k, v in taken.items()}


def identify(docs: DataFrame, samples: dict[str, bytes], text_column: str = "text", keep: list[str] | None = None, least_matched: float = 0.0) -> DataFrame:
    """``docs`` with lang_pred and score.

    lang_pred is ``und`` with score 0 for null texts and texts without a letter, or if nothing was learned; else score is the
    runner-up's rate over the sum of the two lowest, 0.5 to 1 (1 with a single language).  Ties go to the first name in
    order.  With ``least_matched`` a text whose best language matches fewer symbols a phrase than that (two phrases of
    grace, so short texts are not judged by a word) is ``und`` too: it is in no learned language.  Whole texts are parsed;
    equal texts get equal results; an empty table gives no row; columns named lang_pred or score are replaced, others kept.
    """

    def compute(chunk: Chunk) -> dict:
        names = np.array([*sorted(samples), "und"], dtype=object)
        known = _has_letter(chunk)
        if not samples:
            return {"lang_pred": ["und"] * chunk.n, "score": np.zeros(chunk.n)}
        own = parser(samples)
        total, size = own.counted(chunk.bytes, chunk.offsets)
        rates = np.nan_to_num(own.weighed(total, size), nan=1.0)
        best = np.argmin(rates, axis=1)
        known &= least_matched * (total[np.arange(chunk.n), best] - 2) <= size
        ranked = np.sort(rates, axis=1)
        score = ranked[:, 1] / np.maximum(ranked[:, 0] + ranked[:, 1], 1e-12) if rates.shape[1] > 1 else np.ones(chunk.n)
        return {"lang_pred": names[np.where(known, best, len(samples))].tolist(), "score": np.where(known, score, 0.0)}

    return with_measures(docs, compute, {"lang_pred": "string", "score": "double"}, text_column, keep)


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    samples = learn(docs.where(~held_back("doc_id", 4, 2) & F.col("lang").isNotNull()).select("doc_id", "text", "lang"))
    found = identify(docs.select("doc_id", "text"), samples, keep=["doc_id"])
    return found.select("doc_id", held_back("doc_id", 4, 2).alias("held_out"), "lang_pred", "score")
