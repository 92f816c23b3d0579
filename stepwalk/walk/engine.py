"""Supersteps of second-order walks.

A walker is one row: where it is, where it came from, and the neighbour ids of that last vertex if its route ships them.
Every superstep brings the walkers to the lists of their vertex, draws in an Arrow kernel, and writes one table: that table
is the step log of this move, the next state and the restart point at once.  Only walkers and the lists they need are shuffled.

The plain route and the eager cache keep the graph in packed blocks (``graph/blocks``).  A walker meets its vertex's block and
draws from running sums, corrected at the common neighbours, so a vertex's list is there once a block and not once a walker.
Between two vertices the shorter list travels: that of a last vertex with few neighbours goes along, and where a walker
leaves a vertex with many, the next vertex's list goes back to it and it draws.  The log books what the route ships.

Routes decide how the last vertex's list reaches the next draw: ``list`` (it rides on the row), ``local`` (read beside
the walker's vertex), ``ref`` (popular vertex, cached), ``ask`` (the roles switch: the new vertex's list goes to the last
one, which draws), ``static`` (bounds are tight, no list), ``none`` (no later draw needs it).

With the eager cache, popular vertices' lists and running sums are in every worker, from the most popular on as far as a
budget of bytes goes; the figures that bounds need are there for all of them.  Walkers that stand at a popular vertex
are then joined to nothing: they are drawn where they are, in logarithmic time from the running sums (corrected at the
few common neighbours, or not at all where the bounds are tight), so no popular vertex is a join key.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import WalkParams, batch_rows, run_dir, setting, swept
from ..graph import blocks as packs
from ..graph.model import adjacency, part_of, place, unchunked
from .bounds import gap
from .csr import Resident
from .kernel import biased_mass, draw_corrected, member, pick, ragged, runs
from .rng import draw48

STATE = "start long, round int, vertex long, prev long, prev_ids array<long>, route string, n_ids long, hops int, at_hot boolean, replied long"
LOG = "start long, round int, vertex long, route string, n_ids long, hops int, replied long, step int"
BLOCK_STATE = STATE + ", asked boolean"
MOST_ASKED = 50_000
BLOCK_EDGES = 2_000_000
CHUNK_IDS = 1 << 21
HEAVY_FROM = 256
MOST_HEAVY = 200_000
DENSE_BYTES = 64 << 20
HOT_BYTES = 96 << 20


@dataclass(frozen=True)
class Variant:
    """``cache`` includes ``local``; ``approx`` includes ``cache``; ``switch`` stands alone."""

    local: bool = False
    switch: bool = False
    cache: str | None = None
    approx: bool = False

    def __post_init__(self):
        if self.cache not in (None, "eager", "lazy"):
            raise ValueError("cache is eager or lazy")
        if self.switch and (self.local or self.cache or self.approx):
            raise ValueError("switch goes with no other route")
        if self.approx and not self.cache:
            raise ValueError("approx includes cache")
        if self.cache and not self.local:
            raise ValueError("cache includes local")


BASE, LOCAL, SWITCH = Variant(), Variant(local=True), Variant(switch=True)
CACHE, LAZY, APPROX = Variant(local=True, cache="eager"), Variant(local=True, cache="lazy"), Variant(local=True, cache="eager", approx=True)


@dataclass
class Walk:
    """A finished run: its step tables lie under ``path``."""

    spark: SparkSession
    path: str
    params: WalkParams
    parts: int

    def log(self) -> DataFrame:
        """(start, round, step, vertex, route, n_ids, hops, replied): ``n_ids`` are sent with the move, ``replied`` came back for the draw."""
        return self.spark.read.schema(LOG).parquet(self.path)

    def steps(self) -> DataFrame:
        """(start, round, step, vertex): step 0 is the start."""
        return self.log().select("start", "round", "step", "vertex")

    def paths(self) -> DataFrame:
        return paths_of(self.steps())

    def messages(self) -> DataFrame:
        return messages_of(self.log())


def paths_of(steps: DataFrame) -> DataFrame:
    """(start, round, path)."""
    found = steps.groupBy("start", "round").agg(F.array_sort(F.collect_list(F.struct("step", "vertex"))).alias("p"))
    return found.select("start", "round", F.col("p.vertex").alias("path"))


def messages_of(log: DataFrame) -> DataFrame:
    """Message log (step, kind, n_msgs, n_ids, bytes): one step message per move; list messages by route, 8 bytes an id.

    Under ``ask`` a message has one id; its ``reply``, the list of the vertex asked, is booked at the same step.
    """
    moves = log.where("step > 0")
    told = moves.groupBy("step").agg(F.count("*").alias("n_msgs")).select("step", F.lit("step").alias("kind"), "n_msgs", F.col("n_msgs").alias("n_ids"))
    lists = moves.groupBy("step", F.col("route").alias("kind")).agg(F.count("*").alias("n_msgs"), F.sum("n_ids").alias("n_ids"))
    replies = log.where("replied > 0").groupBy((F.col("step") - 1).alias("step")).agg(F.count("*").alias("n_msgs"), F.sum("replied").alias("n_ids"))
    return told.unionByName(lists).unionByName(replies.withColumn("kind", F.lit("reply"))).withColumn("bytes", 8 * F.col("n_ids"))


@dataclass(frozen=True)
class Hot:
    """Popular vertices: sorted ids with degrees and weight ranges, and (eager cache only) their lists.  Size-checked before it is made."""

    vid: np.ndarray
    deg: np.ndarray
    wmin: np.ndarray
    wmax: np.ndarray
    offsets: np.ndarray | None = None
    ids: np.ndarray | None = None
    ws: np.ndarray | None = None

    def place(self, v: np.ndarray) -> np.ndarray:
        """Index of each vertex, -1 where it is not popular."""
        if not len(self.vid):
            return np.full(len(v), -1)
        at = np.searchsorted(self.vid, v)
        at[at == len(self.vid)] = 0
        return np.where(self.vid[at] == v, at, -1)

    @cached_property
    def prefix(self) -> np.ndarray:
        return np.concatenate([np.zeros(1, self.ws.dtype), np.cumsum(self.ws)])

    @cached_property
    def known(self) -> np.ndarray:
        return np.unique(self.ids)

    @cached_property
    def codes(self) -> np.ndarray:
        """Of each list entry, its place among all ids known here."""
        return np.searchsorted(self.known, self.ids)

    @cached_property
    def keys(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.vid)), self.deg) * len(self.known) + self.codes

    @cached_property
    def direct(self) -> np.ndarray | None:
        """Place among the known ids by id less the smallest, where the ids are dense enough."""
        span = int(self.known[-1] - self.known[0]) + 1
        if span > 8 * len(self.known):
            return None
        out = np.full(span, len(self.known) - 1)
        out[self.known - self.known[0]] = np.arange(len(self.known))
        return out

    @cached_property
    def dense(self) -> tuple[np.ndarray, np.ndarray]:
        """(row of each popular vertex or -1, place in its list by code): for the most popular ones, as many as DENSE_BYTES hold."""
        most = min(len(self.vid), DENSE_BYTES // (4 * len(self.known)))
        best = np.argsort(-self.deg, kind="stable")[:most]
        row = np.full(len(self.vid), -1)
        row[best] = np.arange(most)
        at = np.full((most, len(self.known)), -1, np.int32)
        place = ragged(self.offsets[best], self.deg[best])
        at[np.repeat(np.arange(most), self.deg[best]), self.codes[place]] = runs(self.deg[best])
        return row, at

    def coded(self, x: np.ndarray) -> np.ndarray:
        """Places of x among the known ids; ids unknown get some other's."""
        if self.direct is not None:
            return self.direct[np.clip(x - self.known[0], 0, len(self.direct) - 1)]
        return np.minimum(np.searchsorted(self.known, x), len(self.known) - 1)

    def find(self, slot: np.ndarray, x: np.ndarray, code: np.ndarray | None = None) -> np.ndarray:
        """Where the list of the popular vertex ``slot`` has x, -1 where it has not; ``code``: the places of x, if known."""
        if not len(self.ids) or not len(x):
            return np.full(len(x), -1)
        if code is None:
            code = self.coded(x)
            there = self.known[code] == x
        else:
            there = True
        row, table = self.dense
        own = row[slot]
        at = table[np.maximum(own, 0), code].astype(np.int64) if len(table) else np.full(len(x), -1)
        out = np.where((own >= 0) & (at >= 0) & there, self.offsets[slot] + at, -1)
        rest = np.flatnonzero(own < 0)
        if len(rest):
            sought = slot[rest] * len(self.known) + code[rest]
            at = np.minimum(np.searchsorted(self.keys, sought), len(self.keys) - 1)
            out[rest] = np.where((self.keys[at] == sought) & (self.known[code[rest]] == x[rest]), at, -1)
        return out

    def common(self, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(pair, place in v's list) of the common neighbours of popular u and v: the shorter list is looked up in the longer."""
        swap = self.deg[u] > self.deg[v]
        scan, probe = np.where(swap, v, u), np.where(swap, u, v)
        own = np.repeat(np.arange(len(u)), self.deg[scan])
        at = ragged(self.offsets[scan], self.deg[scan])
        there = self.find(probe[own], self.ids[at], self.codes[at])
        hit = there >= 0
        return own[hit], np.where(swap[own[hit]], at[hit], there[hit])

    def draw(self, cur: np.ndarray, prev: np.ndarray, biased: np.ndarray, seen: tuple[np.ndarray, np.ndarray], draw: np.ndarray, factors: tuple) -> np.ndarray:
        """Next vertices of walkers at popular vertices; ``seen`` (walker, id) are the shipped neighbours of their last ones."""
        back, near, other = factors
        v = self.place(cur)
        whole = self.ws.dtype.kind == "i" and all(isinstance(f, int) for f in factors)
        row, at = [seen[0]], [self.find(v[seen[0]], seen[1])]
        u = np.where(biased, self.place(prev), -1)
        pair = np.flatnonzero(u >= 0)
        if len(pair):
            own, there = self.common(u[pair], v[pair])
            row.append(pair[own])
            at.append(there)
        row, at = np.concatenate(row), np.concatenate(at)
        keep = (at >= 0) & biased[row] & (self.ids[at] != prev[row])
        walker = np.flatnonzero(biased)
        home = self.find(v[walker], prev[walker])
        row, at, extra = [row[keep], walker[home >= 0]], [at[keep], home[home >= 0]], [np.full(int(keep.sum()), near - other), np.full(int((home >= 0).sum()), back - other)]
        special = tuple(np.concatenate(x) for x in (row, at, extra))
        return self.ids[draw_corrected(self.prefix, self.ws, self.offsets[v], self.deg[v], np.where(biased, other, 1), special, draw, whole)]


def collect_hot(adj: DataFrame, popular: DataFrame, with_lists: bool, most_bytes: int = 1 << 30) -> Hot:
    """The popular vertices' figures (and lists), if they take at most ``most_bytes`` in a worker; else an error: choose fewer."""
    rows = adj.join(popular.select("vid").distinct(), "vid", "left_semi")
    size = rows.agg(F.coalesce(F.sum(F.col("deg") * 40 + 64), F.lit(0)) if with_lists else F.count("*") * 32).first()[0]
    if size > most_bytes:
        raise ValueError(f"popular vertices take {size} bytes, more than {most_bytes}")
    columns = ["vid", "deg", "wmin", "wmax"] + ["ids", "ws"] * with_lists
    found = rows.select(*columns).toArrow().sort_by("vid")
    arrays = [np.asarray(found.column(c)) for c in columns[:4]]
    if not with_lists:
        return Hot(*arrays)
    lists = [np.asarray(found.column(c).combine_chunks().flatten()) for c in ("ids", "ws")]
    return Hot(*arrays, np.concatenate([[0], np.cumsum(arrays[1])]), *lists)


def kept_vids(known: Hot, most_bytes: int) -> np.ndarray:
    """The most popular vertices, as many as ``most_bytes`` hold lists of in a worker; walkers at the others go to their blocks."""
    order = np.lexsort((known.vid, -known.deg))
    return np.sort(known.vid[order[np.cumsum(known.deg[order] * 40 + 64) <= most_bytes]])


@dataclass(frozen=True)
class Heavy:
    """Vertices of more than ``limit`` neighbours (sorted ids, degrees): walkers that leave one do not carry its list."""

    vid: np.ndarray
    deg: np.ndarray
    limit: int

    def degree(self, v: np.ndarray) -> np.ndarray:
        """Degrees, 0 for the others."""
        if not len(self.vid):
            return np.zeros(len(v), np.int64)
        at = np.minimum(np.searchsorted(self.vid, v), len(self.vid) - 1)
        return np.where(self.vid[at] == v, self.deg[at], 0)


def _lists(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(values, offsets from 0, which are not null)."""
    offsets = np.asarray(column.offsets)
    valid = np.asarray(column.is_valid())
    return np.asarray(column.values)[offsets[0] : offsets[-1]] if len(offsets) else np.zeros(0, np.int64), offsets - offsets[0], valid


class _Kernel:
    """One superstep's draws: ``at_lists`` for walkers that come with their vertex's list, ``at_hot`` for those at popular
    vertices that every worker knows, ``beside`` for those whose last vertex draws for them.

    Over packed blocks: ``at_block`` for walkers beside their vertex's block; ``fetch`` gives a walker its vertex's list, and
    ``answer`` draws beside its last vertex's block.
    """

    def __init__(self, params: WalkParams, variant: Variant, parts: int, hot, kept, last: bool, first: bool, eps: float, heavy=None, dtype=np.int64):
        self.params, self.variant, self.parts, self.hot, self.kept, self.last, self.eps = params, variant, parts, hot, kept, last, eps
        self.heavy, self.dtype = heavy, dtype
        self.factors = params.scaled() or params.factors()
        self.plain = first or params.first_order()

    def at_lists(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = self.hot.value if self.hot is not None else None
        for b in batches:
            if b.num_rows:
                yield self._drawn(b, known, None)

    def at_hot(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, kept = self.hot.value, self.kept.value
        for b in batches:
            if not b.num_rows:
                continue
            cur, draw, route = np.asarray(b.column("vertex")), np.asarray(b.column("draw")), np.asarray(b.column("route").to_pylist(), dtype=object)
            biased = np.full(b.num_rows, not self.plain) & (route != "static")
            seen, at, _ = _lists(b.column("prev_ids"))
            seen = packs.undeltas(seen, at)
            prev = np.asarray(pc.fill_null(b.column("prev"), -1))
            chosen = kept.draw(cur, prev, biased, (np.repeat(np.arange(b.num_rows), np.diff(at)), seen), draw, self.factors)
            yield self._sent(b, known, cur, chosen, kept.deg[kept.place(cur)], (kept.ids, kept.offsets, kept.place(cur)), np.zeros(b.num_rows, np.int64))

    def at_block(self, walkers: pa.Table, rows: pa.Table) -> pa.Table:
        """Walkers that stand at vertices of one block."""
        if not walkers.num_rows or not rows.num_rows:
            return _BLOCK_STATE.empty_table()
        block, known, out = packs.Block(rows.to_pylist()[0], self.dtype), self.hot.value if self.hot is not None else None, []
        kept = self.kept.value if self.kept is not None else None
        for b in _slices(walkers, "prev_ids"):
            slot = block.slot(np.asarray(b.column("vertex")))
            if (slot < 0).any():
                b, slot = b.filter(pa.array(slot >= 0)), slot[slot >= 0]
            if not b.num_rows:
                continue
            cur, draw, begin, size = np.asarray(b.column("vertex")), np.asarray(b.column("draw")), block.offsets[slot], block.deg[slot]
            if self.plain:
                biased, special = np.zeros(b.num_rows, bool), (np.zeros(0, np.int64),) * 3
            else:
                prev = np.asarray(b.column("prev"))
                biased = np.asarray(b.column("route").to_pylist(), dtype=object) != "static"
                special = self._special(block, b, kept, slot, prev, biased)
            whole = self.dtype == np.int64 and all(isinstance(f, int) for f in self.factors)
            at = draw_corrected(block.prefix, block.ws, begin, size, np.where(biased, self.factors[2], 1), special, draw, whole)
            out.append(self._sent(b, known, cur, block.ids[at], size, (block.ids, block.offsets, slot), np.zeros(b.num_rows, np.int64)))
        return pa.Table.from_batches(out, _BLOCK_STATE)

    def _special(self, block: packs.Block, b: pa.RecordBatch, kept: Hot | None, slot: np.ndarray, prev: np.ndarray, biased: np.ndarray) -> tuple:
        """(walker, place, factor beyond the usual) of the last vertex and the common neighbours."""
        back, near, other = self.factors
        values, offsets, _ = _lists(b.column("prev_ids"))
        seen, who = packs.undeltas(values, offsets), np.repeat(np.arange(b.num_rows), np.diff(offsets))
        hit, at = block.find(slot[who], seen)
        walker = who[hit]
        if kept is not None:
            ref = np.flatnonzero(biased & (kept.place(prev) >= 0))
            if len(ref):
                own, place = np.repeat(ref, block.deg[slot[ref]]), ragged(block.offsets[slot[ref]], block.deg[slot[ref]])
                there = kept.find(np.repeat(kept.place(prev[ref]), block.deg[slot[ref]]), block.ids[place]) >= 0
                walker, at = np.concatenate([walker, own[there]]), np.concatenate([at, place[there]])
        keep = biased[walker] & (block.ids[at] != prev[walker])
        wide = len(block.ids) + 1
        walker, at = np.divmod(np.unique(walker[keep] * wide + at[keep]), wide)
        mine = np.flatnonzero(biased)
        home, place = block.find(slot[mine], prev[mine])
        extra = [np.full(len(walker), near - other), np.full(len(home), back - other)]
        return np.concatenate([walker, mine[home]]), np.concatenate([at, place]), np.concatenate(extra)

    def fetch(self, walkers: pa.Table, rows: pa.Table) -> pa.Table:
        """Walkers with the lists of their vertices."""
        schema, out = _fetched(self.dtype), []
        if not walkers.num_rows or not rows.num_rows:
            return schema.empty_table()
        block = packs.Block(rows.to_pylist()[0], self.dtype)
        slots = block.slot(np.asarray(walkers.column("vertex")))
        walkers, slots = walkers.filter(pa.array(slots >= 0)), slots[slots >= 0]
        bounds = np.searchsorted(np.cumsum(block.deg[slots]), np.arange(0, int(block.deg[slots].sum()) + CHUNK_IDS, CHUNK_IDS)) if len(slots) else [0]
        bounds = np.unique(np.append(bounds, len(slots)))
        for low, high in zip(bounds[:-1], bounds[1:]):
            some = slots[low:high]
            at, offsets = ragged(block.offsets[some], block.deg[some]), np.concatenate([[0], np.cumsum(block.deg[some])])
            lists = [pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(x)) for x in (packs.deltas(block.ids[at], offsets), block.ws[at])]
            b = walkers.slice(low, high - low).combine_chunks().to_batches()[0]
            out.append(pa.RecordBatch.from_arrays([*[b.column(c) for c in schema.names[:-2]], *lists], schema=schema))
        return pa.Table.from_batches(out, schema)

    def answer(self, walkers: pa.Table, rows: pa.Table) -> pa.Table:
        """Walkers that left vertices of one block, each with the list of the vertex where it is: the last one draws."""
        if not walkers.num_rows or not rows.num_rows:
            return _BLOCK_STATE.empty_table()
        block, known, out = packs.Block(rows.to_pylist()[0], self.dtype), self.hot.value if self.hot is not None else None, []
        for b in _slices(walkers, "ids"):
            values, offsets, _ = _lists(b.column("ids"))
            ids, ws, lengths = packs.undeltas(values, offsets), _lists(b.column("ws"))[0], np.diff(offsets)
            rows, prev = np.repeat(np.arange(b.num_rows), lengths), np.asarray(b.column("prev"))
            common = np.zeros(len(ids), bool)
            common[block.find(block.slot(prev)[rows], ids)[0]] = True
            mass = biased_mass(rows, ids, ws, prev, common, np.ones(b.num_rows, bool), self.factors)
            chosen = ids[pick(mass, lengths, np.asarray(b.column("draw")))]
            out.append(self._sent(b, known, np.asarray(b.column("vertex")), chosen, lengths, (ids, offsets, np.arange(b.num_rows)), np.zeros(b.num_rows, np.int64)))
        return pa.Table.from_batches(out, _BLOCK_STATE)

    def beside(self, walkers: pa.Table, vertex: pa.Table) -> pa.Table:
        """Of one popular vertex: its list, once, and walkers that left it, each with the list of the vertex where it is."""
        known, out = self.hot.value, []
        mine = np.asarray(vertex.column("near").combine_chunks().flatten()) if vertex.num_rows else None
        for b in walkers.combine_chunks().to_batches() if mine is not None else ():
            out.append(self._drawn(b, known, mine))
        return pa.Table.from_batches(out, _STATE)

    def _drawn(self, b: pa.RecordBatch, known: Hot | None, mine: np.ndarray | None) -> pa.RecordBatch:
        n = b.num_rows
        ids, offsets, _ = _lists(b.column("ids"))
        ws, _, _ = _lists(b.column("ws"))
        lengths = np.diff(offsets)
        cur, draw = np.asarray(b.column("vertex")), np.asarray(b.column("draw"))
        if self.plain:
            mass = ws
        else:
            rows = np.repeat(np.arange(n), lengths)
            prev = np.asarray(b.column("prev"))
            if mine is not None:
                common = _held(mine, ids)
            else:
                seen, at, _ = _lists(b.column("prev_ids"))
                common = member(rows, ids, np.repeat(np.arange(n), np.diff(at)), seen)
            route = np.asarray(b.column("route").to_pylist(), dtype=object)
            mass = biased_mass(rows, ids, ws, prev, common, route != "static", self.factors)
        chosen = ids[pick(mass, lengths, draw)]
        replied = lengths if mine is not None else np.zeros(n, np.int64)
        return self._sent(b, known, cur, chosen, lengths, (ids, offsets, np.arange(n)), replied)

    def _sent(self, b: pa.RecordBatch, known: Hot | None, cur, chosen, degree, lists, replied) -> pa.RecordBatch:
        """The walkers after their moves, each with the route of the list that its next draw needs."""
        n, variant = b.num_rows, self.variant
        none = self.last or self.params.first_order()
        route = np.full(n, "none" if none else "list", dtype=object)
        to_hot = known.place(chosen) if known is not None else np.full(n, -1)
        kept = self.kept.value if self.kept is not None else None
        to_kept = kept.place(chosen) >= 0 if kept is not None else np.zeros(n, bool)
        if not none:
            if variant.local:
                route[(cur ^ (cur >> 16)) % self.parts == (chosen ^ (chosen >> 16)) % self.parts] = "local"
            if known is not None:
                from_hot = known.place(cur) >= 0
                if variant.switch:
                    route[from_hot & (to_hot < 0)] = "ask"
                if variant.cache == "lazy":
                    route[from_hot & (route != "local")] = "ref"
                if variant.cache == "eager":
                    from_kept = kept.place(cur) >= 0
                    route[~from_kept & to_kept] = "list"
                    route[from_kept] = "ref"
                if variant.approx:
                    able = np.flatnonzero(~from_hot & (to_hot >= 0))
                    spot = to_hot[able]
                    tight = gap(degree[able], known.deg[spot], known.wmin[spot], known.wmax[spot], self.params.p, self.params.q) < self.eps
                    route[able[tight]] = "static"
        size = np.where(route == "list", degree, 0)
        ship, back = route == "list", np.zeros(n, bool)
        if self.heavy is not None:
            needed, heavy = (route == "list") | (route == "local"), self.heavy.value
            back = needed & (degree > heavy.limit) & (heavy.degree(chosen) < degree) & ~to_kept
            ship = needed & ~back
        ids, offsets, slot = lists
        carried = np.where(ship, degree, 0)
        ends = np.concatenate([[0], np.cumsum(carried)])
        body = ids[ragged(offsets[slot[ship]], carried[ship])]
        if self.heavy is not None:
            body = packs.deltas(body, ends)
        sent = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(body, pa.int64()), mask=pa.array(~ship))
        asked = route == "ask"
        hops = np.asarray(b.column("hops")) + 1 + asked
        columns = [b.column("start"), b.column("round"), pa.array(chosen), pa.array(cur), sent, pa.array(route.tolist(), pa.string()), pa.array(np.where(asked, 1, size), pa.int64()), pa.array(hops, pa.int32())]
        columns += [pa.array(to_kept), pa.array(replied, pa.int64())]
        if self.heavy is not None:
            return pa.RecordBatch.from_arrays([*columns, pa.array(back)], schema=_BLOCK_STATE)
        return pa.RecordBatch.from_arrays(columns, schema=_STATE)


_STATE = pa.schema([("start", pa.int64()), ("round", pa.int32()), ("vertex", pa.int64()), ("prev", pa.int64()), ("prev_ids", pa.list_(pa.int64())), ("route", pa.string()), ("n_ids", pa.int64()), ("hops", pa.int32()), ("at_hot", pa.bool_()), ("replied", pa.int64())])
_BLOCK_STATE = _STATE.append(pa.field("asked", pa.bool_()))
_FETCHED = "start long, round int, vertex long, prev long, hops int, draw long, home int, ids array<long>, ws array<{}>"


def _fetched(dtype) -> pa.Schema:
    w = pa.int64() if dtype == np.int64 else pa.float64()
    return pa.schema([("start", pa.int64()), ("round", pa.int32()), ("vertex", pa.int64()), ("prev", pa.int64()), ("hops", pa.int32()), ("draw", pa.int64()), ("home", pa.int32()), ("ids", pa.list_(pa.int64())), ("ws", pa.list_(w))])


def _slices(walkers: pa.Table, column: str) -> Iterator[pa.RecordBatch]:
    """The rows in pieces of about CHUNK_IDS list entries."""
    for b in walkers.to_batches():
        ends = np.asarray(b.column(column).offsets)[1:] + np.arange(b.num_rows) if b.num_rows else np.zeros(0, np.int64)
        bounds = np.unique(np.searchsorted(ends, np.arange(ends[0], ends[-1] + CHUNK_IDS, CHUNK_IDS))) if len(ends) else []
        for low, high in zip(bounds, [*bounds[1:], b.num_rows]):
            if high > low:
                yield b.slice(low, high - low)


def _held(sorted_ids: np.ndarray, ids: np.ndarray) -> np.ndarray:
    at = np.searchsorted(sorted_ids, ids)
    at[at == len(sorted_ids)] = 0
    return sorted_ids[at] == ids


class Engine:
    """A graph placed for walking.  ``adj`` is an adjacency frame without chunks (see ``walk_chunked`` for hubs beyond a row)."""

    def __init__(self, adj: DataFrame | None, parts: int | None = None, keep: str = "memory", edges: DataFrame | None = None):
        self.edges = edges if edges is not None else unchunked(adj)
        self.spark = self.edges.sparkSession
        self.parts = parts or int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        self._rows, self._keep = adj, keep
        self._adj: DataFrame | None = None
        self._by_part: DataFrame | None = None
        self._blocks: DataFrame | None = None
        self.dtype = np.float64 if dict(self.edges.dtypes)["w"] == "double" else np.int64

    @property
    def adj(self) -> DataFrame:
        """A row per vertex: what the local, lazy and switching routes join."""
        if self._adj is None:
            self._adj = place(self._rows if self._rows is not None else adjacency(self.edges), self.parts, self._keep)
        return self._adj

    def blocks(self) -> DataFrame:
        """The lists in packed blocks, laid out by block."""
        if self._blocks is None:
            self.n_blocks = max(self.parts, -(-self.edges.count() // BLOCK_EDGES))
            self._blocks = packs.adjacency_blocks(self.edges, self.n_blocks).repartition(self.n_blocks, "block").persist()
        return self._blocks

    def _heavy(self, figures: DataFrame) -> Heavy:
        """Vertices of more than HEAVY_FROM neighbours; of a higher limit where these are more than MOST_HEAVY."""
        many = figures.where(F.col("deg") > HEAVY_FROM).groupBy("deg").count().toArrow().sort_by([("deg", "descending")])
        deg, fits = np.asarray(many.column("deg")), np.cumsum(np.asarray(many.column("count"))) <= MOST_HEAVY
        limit = int(deg[~fits][0]) if not fits.all() else HEAVY_FROM
        found = figures.where(F.col("deg") > limit).select("vid", "deg").toArrow().sort_by("vid")
        return Heavy(np.asarray(found.column("vid")), np.asarray(found.column("deg")), limit)

    def by_part(self) -> DataFrame:
        """The adjacency laid out by vertex partition: both lookups of the local route then happen in one task."""
        if self._by_part is None:
            self._by_part = self.adj.select("part", "vid", "ids", "ws").repartition(self.parts, "part").persist()
        return self._by_part

    @classmethod
    def of_edges(cls, edges: DataFrame, **options) -> Engine:
        return cls(None, edges=edges, **options)

    def close(self) -> None:
        for kept in (self._adj, self._by_part, self._blocks):
            if kept is not None:
                kept.unpersist()

    def size_biased_degree(self) -> float:
        """Mean length of the list that a walker meets."""
        d = self.adj.agg(F.sum(F.col("deg") * F.col("deg")).alias("a"), F.sum("deg").alias("b")).first()
        return float(d.a or 0) / max(1, d.b or 0)

    def walk(self, params: WalkParams, variant: Variant = BASE, popular: DataFrame | None = None, starts: DataFrame | None = None, eps: float = 1e-3, path: str | None = None, hot_bytes: int | None = None) -> Walk:
        """Run ``params.length`` supersteps; ``popular`` (vid) is needed by switch, cache and approx.

        The eager cache keeps the lists of the most popular ones, as many as HOT_BYTES hold; walkers at the others take the
        usual way.  With ``hot_bytes`` all lists must fit these, or there is an error.
        """
        if (variant.switch or variant.cache) and popular is None:
            raise ValueError("this variant needs the popular vertices")
        path = path or run_dir(self.spark, "walk")
        if variant.cache == "eager" or not (variant.local or variant.switch):
            return self._walk_blocks(params, variant, popular, starts, eps, path, hot_bytes)
        spark = self.spark
        known = collect_hot(self.adj, popular, False) if variant.switch or variant.cache else None
        hot = spark.sparkContext.broadcast(known) if known is not None else None
        self._begin(params, starts, self.adj, path, STATE)
        sent = _Sent(self, popular) if variant.cache == "lazy" else None
        with batch_rows(spark, 24 * self.size_biased_degree()), setting(spark, "spark.sql.requireAllClusterKeysForCoPartition", "false"):
            for move in range(1, params.length + 1):
                now = spark.read.schema(STATE).parquet(f"{path}/step={move - 1}").drop("replied")
                now = now.withColumn("draw", draw48(params.seed, "round", "start", move, params.rng))
                kernel = _Kernel(params, variant, self.parts, hot, None, move == params.length, move == 1, eps)
                plain = move == 1 or params.first_order()
                rest = now.where("route <> 'ask'") if variant.switch and not plain else now
                moved = self._attach(rest, variant, sent, plain).drop("at_hot").mapInArrow(kernel.at_lists, STATE)
                if variant.switch and not plain:
                    moved = moved.unionByName(self._switched(now.where("route = 'ask'").drop("at_hot"), popular, kernel))
                moved.write.parquet(f"{path}/step={move}")
                if params.directed and move % 8 == 0 and spark.read.schema(STATE).parquet(f"{path}/step={move}").isEmpty():
                    break
        return Walk(spark, path, params, self.parts)

    def _begin(self, params: WalkParams, starts: DataFrame | None, every: DataFrame, path: str, schema: str, kept: DataFrame | None = None) -> None:
        begin = starts.select(F.col("vid").alias("vertex")).distinct() if starts is not None else every.select(F.col("vid").alias("vertex"))
        begin = begin.select(F.col("vertex").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(params.walks_per_vertex - 1))).alias("round"), "vertex")
        empty = {"prev": "long", "prev_ids": "array<long>", "route": "string"}
        state = begin.withColumns({k: F.lit(None).cast(t) for k, t in empty.items()} | {"n_ids": F.lit(0).cast("long"), "hops": F.lit(0), "replied": F.lit(0).cast("long"), "asked": F.lit(False)})
        if kept is not None:
            state = state.join(kept.select(F.col("vid").alias("vertex"), F.lit(True).alias("at_hot")).distinct(), "vertex", "left").withColumn("at_hot", F.coalesce("at_hot", F.lit(False)))
        else:
            state = state.withColumn("at_hot", F.lit(False))
        state.select([x.split()[0] for x in schema.split(", ")]).write.parquet(f"{path}/step=0")

    def _walk_blocks(self, params: WalkParams, variant: Variant, popular: DataFrame | None, starts: DataFrame | None, eps: float, path: str, hot_bytes: int | None) -> Walk:
        """Supersteps over packed blocks: the plain route and the eager cache."""
        spark, eager, kept_rows, known, kept = self.spark, variant.cache == "eager", None, None, None
        blocks = self.blocks()
        with batch_rows(spark, 2048), setting(spark, "spark.sql.shuffle.partitions", str(self.n_blocks)):
            figures = packs.vertices(blocks, self.dtype)
            if eager:
                known = collect_hot(figures, popular, False)
                if hot_bytes is not None and (size := int((known.deg * 40 + 64).sum())) > hot_bytes:
                    raise ValueError(f"popular vertices take {size} bytes, more than {hot_bytes}")
                vids = kept_vids(known, hot_bytes if hot_bytes is not None else HOT_BYTES)
                kept_rows = spark.createDataFrame(pa.table({"vid": pa.array(vids, pa.int64())}))
                kept = collect_hot(packs.lists_of(blocks, self.dtype, vids), kept_rows, True)
            hot, kept, heavy = (spark.sparkContext.broadcast(x) if x is not None else None for x in (known, kept, self._heavy(figures)))
            self._begin(params, starts, figures, path, BLOCK_STATE, kept_rows)
            for move in range(1, params.length + 1):
                now = spark.read.schema(BLOCK_STATE).parquet(f"{path}/step={move - 1}").drop("replied")
                now = now.withColumn("draw", draw48(params.seed, "round", "start", move, params.rng)).withColumn("block", part_of("vertex", self.n_blocks))
                kernel = _Kernel(params, variant, self.parts, hot, kept, move == params.length, move == 1, eps, heavy, self.dtype)
                meet = lambda rows, by, run, schema: rows.groupBy(by).cogroup(blocks.groupBy("block")).applyInArrow(lambda walkers, lists: run(walkers, lists), schema)
                moved = meet(now.where("not at_hot and not asked").drop("at_hot", "asked"), "block", kernel.at_block, BLOCK_STATE)
                if eager:
                    moved = moved.unionByName(now.where("at_hot").drop("at_hot", "asked", "block").mapInArrow(kernel.at_hot, BLOCK_STATE))
                if move > 1 and not params.first_order():
                    asked = now.where("asked").withColumn("home", part_of("prev", self.n_blocks)).select("start", "round", "vertex", "prev", "hops", "draw", "home", "block")
                    lists = meet(asked, "block", kernel.fetch, _FETCHED.format("long" if self.dtype == np.int64 else "double"))
                    moved = moved.unionByName(meet(lists, "home", kernel.answer, BLOCK_STATE))
                moved.write.option("compression", "zstd").parquet(f"{path}/step={move}")
                swept(spark)
                if params.directed and move % 8 == 0 and spark.read.schema(BLOCK_STATE).parquet(f"{path}/step={move}").isEmpty():
                    break
        return Walk(spark, path, params, self.parts)

    def _switched(self, asked: DataFrame, popular: DataFrame, kernel: _Kernel) -> DataFrame:
        """Walkers that left a popular vertex for another kind: the list of where they are goes back to it, and it draws.

        A popular vertex's walkers are dealt over a salt for each ``MOST_ASKED`` of its neighbours; its list enters once a salt.
        """
        lists = self.adj.join(popular.select("vid").distinct(), "vid", "left_semi")
        salts = F.ceil(F.col("deg") / MOST_ASKED).cast("int")
        there = lists.select(F.col("vid").alias("_of"), F.col("ids").alias("near"), F.explode(F.sequence(F.lit(0), salts - 1)).alias("_part"))
        of = lists.select(F.col("vid").alias("_vid"), salts.alias("_salts"))
        own = self.adj.select("vid", F.col("ids").alias("ids"), F.col("ws").alias("ws"))
        back = asked.join(own, F.col("vertex") == F.col("vid")).drop("vid")
        back = back.join(of, F.col("prev") == F.col("_vid")).withColumn("salt", F.pmod(F.xxhash64("start", "round"), F.col("_salts")).cast("int")).drop("_vid", "_salts")
        return back.groupBy("prev", "salt").cogroup(there.groupBy("_of", "_part")).applyInArrow(lambda walkers, vertex: kernel.beside(walkers, vertex), STATE)

    def _attach(self, now: DataFrame, variant: Variant, sent: _Sent | None, plain: bool) -> DataFrame:
        """Walkers with the neighbours of their vertex (ids, ws) and, where it was not shipped, the last vertex's list."""
        if variant.local and not plain:
            return self._attach_in_part(now, sent)
        lists = self.adj.select("vid", "ids", "ws")
        return now.join(lists, F.col("vertex") == F.col("vid")).drop("vid")

    def _attach_in_part(self, now: DataFrame, sent: _Sent | None) -> DataFrame:
        """Walkers go to the partition of their vertex once; the list of a last vertex that lives there is read in place.

        Needs spark.sql.requireAllClusterKeysForCoPartition off, which ``walk`` sees to: the joins' keys hold the partition.
        """
        lists = self.by_part()
        now = now.withColumn("_at", part_of("vertex", self.parts)).repartition(self.parts, "_at")
        own = lists.select(F.col("part").alias("_p"), "vid", "ids", "ws")
        joined = now.join(own, (F.col("_at") == F.col("_p")) & (F.col("vertex") == F.col("vid"))).drop("_p", "vid")
        beside = lists.select(F.col("part").alias("_p"), F.col("vid").alias("_vid"), F.col("ids").alias("_ids"))
        joined = joined.withColumn("_want", F.when(F.col("route") == "local", F.col("prev")))
        joined = joined.join(beside, (F.col("_at") == F.col("_p")) & (F.col("_want") == F.col("_vid")), "left")
        joined = joined.withColumn("prev_ids", F.coalesce("prev_ids", "_ids")).drop("_want", "_vid", "_ids", "_p", "_at")
        return sent.attach(joined) if sent is not None else joined


class _Sent:
    """Lazy cache: the lists that partitions have got so far, each sent at its first use there."""

    def __init__(self, engine: Engine, popular: DataFrame):
        self.engine = engine
        self.path = run_dir(engine.spark, "sent")
        self.round = 0
        self.schema = "part int, vid long, ids array<long>"
        engine.spark.createDataFrame([], self.schema).write.parquet(f"{self.path}/n=0")

    def attach(self, joined: DataFrame) -> DataFrame:
        engine, spark = self.engine, self.engine.spark
        refs = joined.where("route = 'ref'").select(part_of("vertex", engine.parts).alias("part"), F.col("prev").alias("vid")).distinct()
        had = spark.read.schema(self.schema).parquet(self.path)
        fresh = refs.join(had.select("part", "vid"), ["part", "vid"], "left_anti")
        self.round += 1
        fresh.join(engine.adj.select("vid", "ids"), "vid").select("part", "vid", "ids").write.parquet(f"{self.path}/n={self.round}")
        have = spark.read.schema(self.schema).parquet(self.path).select(F.col("part").alias("_part"), F.col("vid").alias("_vid"), F.col("ids").alias("_ids"))
        want = F.when(F.col("route") == "ref", F.col("prev"))
        out = joined.withColumn("_want", want).withColumn("_at", part_of("vertex", engine.parts))
        out = out.join(have, (F.col("_want") == F.col("_vid")) & (F.col("_at") == F.col("_part")), "left")
        return out.withColumn("prev_ids", F.coalesce("prev_ids", "_ids")).drop("_want", "_at", "_part", "_vid", "_ids")


def walk_rounds(engine: Engine, params: WalkParams, k: int, variant: Variant = BASE, path: str | None = None, **options) -> list[Walk]:
    """Start vertices in ``k`` groups, one group after the other: state and messages shrink by ``k``; a finished group is kept.

    A group's folder that holds its last step is read, not run again.
    """
    path = path or run_dir(engine.spark, "rounds")
    starts = options.pop("starts", None)
    starts = engine.adj.select("vid") if starts is None else starts
    out = []
    for i in range(k):
        own = f"{path}/group={i}"
        done = engine.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{own}/step={params.length}/_SUCCESS")
        if done.getFileSystem(engine.spark.sparkContext._jsc.hadoopConfiguration()).exists(done):
            out.append(Walk(engine.spark, own, params, engine.parts))
        else:
            out.append(engine.walk(params, variant, starts=starts.where(F.pmod(F.xxhash64("vid"), F.lit(k)) == i), path=own, **options))
    return out


def resident_graph(edges: DataFrame, most_bytes: int = 1 << 29) -> Resident | None:
    """The graph as arrays, if its edges (24 bytes each, and as much again for prefix sums and keys) stay within ``most_bytes``."""
    if edges.count() * 48 > most_bytes:
        return None
    rows = edges.select("src", "dst", "w").toArrow()
    return Resident.of(*(np.asarray(rows.column(c)) for c in ("src", "dst", "w")))


def walk_resident(edges: DataFrame, params: WalkParams, starts: DataFrame | None = None, most_bytes: int = 1 << 29, tasks: int | None = None, popular: DataFrame | None = None, eps: float = 0.0, reject: bool = False) -> DataFrame:
    """(start, round, step, vertex) with no shuffle between moves: the graph, checked to be small, is broadcast to workers.

    Larger graphs take the superstep engine.  Both give the same walks.  With ``popular`` (vid) and ``eps`` a popular vertex
    that is reached from another kind is sampled statically where its bounds lie closer than ``eps``.  ``reject`` draws by
    rejection, with the same probabilities but other walks (larger graphs do not know it).
    """
    spark = edges.sparkSession
    graph = resident_graph(edges, most_bytes)
    if graph is None:
        engine = Engine.of_edges(edges)
        return engine.walk(params, APPROX if popular is not None else BASE, popular=popular, starts=starts, eps=eps).steps()
    if popular is not None:
        graph.mark(np.asarray(popular.select("vid").distinct().toArrow().column("vid")))
    shared = spark.sparkContext.broadcast(graph)
    factors = params.scaled() or params.factors()
    vids = starts.select("vid").distinct() if starts is not None else edges.select(F.col("src").alias("vid")).distinct()
    tasks = tasks or spark.sparkContext.defaultParallelism
    rows = vids.select(F.col("vid").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(params.walks_per_vertex - 1))).alias("round")).repartition(tasks)
    moves = F.transform(F.sequence(F.lit(1), F.lit(params.length)), lambda m: draw48(params.seed, F.col("round"), F.col("start"), m, params.rng))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = shared.value
        for b in batches:
            start, round_ = np.asarray(b.column("start")), np.asarray(b.column("round"))
            draw = np.asarray(b.column("draws").flatten()).reshape(len(start), -1)
            cur = np.searchsorted(g.vids, start)
            cur[cur == len(g.vids)] = 0
            live = np.arange(len(start))
            yield _log(start, round_, 0, start)
            live = live[(g.vids[cur] == start) & (g.deg[cur] > 0)] if len(g.vids) else live[:0]
            prev, cur = np.full(len(live), -1), cur[live]
            for move in range(1, params.length + 1):
                if not len(live):
                    break
                known = np.full(len(cur), -1) if params.first_order() else g.remembered(prev, cur, params, eps) if eps > 0 else prev
                to = (g.step_reject if reject else g.step)(cur, known, draw[live, move - 1], factors)
                prev, cur = cur, to
                yield _log(start[live], round_[live], move, g.vids[cur])
                on = g.deg[cur] > 0
                live, prev, cur = live[on], prev[on], cur[on]

    with batch_rows(spark, 8.0 * params.length + 4096):
        found = rows.withColumn("draws", moves).mapInArrow(run, "start long, round int, step int, vertex long")
        path = run_dir(spark, "resident")
        found.write.parquet(path)
    return spark.read.schema("start long, round int, step int, vertex long").parquet(path)


def _log(start: np.ndarray, round_: np.ndarray, step: int, vertex: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(start, pa.int64()), pa.array(round_, pa.int32()), pa.array(np.full(len(start), step), pa.int32()), pa.array(vertex, pa.int64())], ["start", "round", "step", "vertex"])


def walk_chunked(chunks: DataFrame, params: WalkParams, starts: DataFrame | None = None) -> Walk:
    """Walks where a vertex's neighbours lie in several rows (vid, chunk): no row outgrows memory.

    A walker meets each chunk of its vertex, the kernel returns masses, the draw chooses the chunk by running sums per
    walker, and a second meeting with that one chunk picks inside it.  The last vertex's list arrives by its chunks too:
    common neighbours are found by joining edges, so nothing but single chunks is ever held.  Whole weights only.
    """
    spark, path = chunks.sparkSession, run_dir(chunks.sparkSession, "chunked")
    factors = params.scaled()
    if factors is None:
        raise ValueError("chunked walks need whole factors")
    back, common, other = factors
    edges = unchunked(chunks).select("src", F.col("dst").alias("x"), "w").withColumn("chunk", F.lit(0))
    each = chunks.select(F.col("vid").alias("vertex"), "chunk", F.explode(F.arrays_zip("ids", "ws")).alias("e")).select("vertex", "chunk", F.col("e.ids").alias("x"), F.col("e.ws").alias("w"))
    vids = starts.select("vid").distinct() if starts is not None else chunks.select("vid").distinct()
    state = vids.select(F.col("vid").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(params.walks_per_vertex - 1))).alias("round"), F.col("vid").alias("vertex"))
    state = state.withColumns({"prev": F.lit(None).cast("long"), "route": F.lit(None).cast("string"), "n_ids": F.lit(0).cast("long"), "hops": F.lit(0), "replied": F.lit(0).cast("long")})
    kept = "start long, round int, vertex long, prev long, route string, n_ids long, hops int, replied long"
    state.write.parquet(f"{path}/step=0")
    pairs = edges.select(F.col("src").alias("prev"), "x", F.lit(True).alias("_near"))
    for move in range(1, params.length + 1):
        now = spark.read.schema(kept).parquet(f"{path}/step={move - 1}").withColumn("draw", draw48(params.seed, "round", "start", move, params.rng))
        met = now.join(each, "vertex").join(pairs, ["prev", "x"], "left")
        factor = F.when(F.col("prev").isNull(), 1).when(F.col("x") == F.col("prev"), back).when(F.col("_near"), common).otherwise(other)
        met = met.withColumn("mass", F.col("w") * factor)
        per = met.groupBy("start", "round", "vertex", "draw", "chunk").agg(F.sum("mass").alias("mass"))
        own = Window.partitionBy("start", "round")
        upto = F.sum("mass").over(own.orderBy("chunk"))
        per = per.withColumns({"upto": upto, "total": F.sum("mass").over(own)}).withColumn("target", F.col("draw") % F.col("total"))
        chosen = per.where("target < upto AND target >= upto - mass").select("start", "round", "chunk", (F.col("target") - F.col("upto") + F.col("mass")).alias("rest"))
        inside = met.join(chosen, ["start", "round", "chunk"]).withColumn("upto", F.sum("mass").over(own.orderBy("x")))
        moved = inside.where("rest < upto AND rest >= upto - mass")
        moved = moved.select("start", "round", F.col("x").alias("vertex"), F.col("vertex").alias("prev"), F.lit("list").alias("route"), F.lit(0).cast("long").alias("n_ids"), (F.col("hops") + 1).alias("hops"), "replied")
        moved.write.parquet(f"{path}/step={move}")
    return Walk(spark, path, params, 0)
