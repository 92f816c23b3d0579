"""Hierarchical navigable small-world graph of one shard, in arrays: many searches advance together.

A shard is bounded, so two layers do: the upper one holds about a sixteenth of the nodes and is small enough for a beam as
wide as itself (one matrix product); its best nodes are the entries to the base layer.  That also finds tight clusters,
whose members' links all stay inside.
"""

from __future__ import annotations

import numpy as np

LINKS, SHARE = 32, 16
BATCH = 256
FRONTIER = 1 << 14  # pairs whose links are looked at together, so that dense shards stay within memory


def _level(keys: np.ndarray) -> np.ndarray:
    """0 or 1 by a hash of the keys: one of ``SHARE`` nodes is in the upper layer."""
    h = keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(31)
    h = (h * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(11)
    return (h % np.uint64(SHARE) == 0).astype(np.int64)


def _diverse(x: np.ndarray, ids: np.ndarray, sims: np.ndarray, most: int) -> np.ndarray:
    """Of each row's candidates (best first, -1 for none) up to ``most``: those nearer to the row than to any taken before, then the rest by nearness."""
    n, c = ids.shape
    near = x[np.maximum(ids, 0)]
    between = np.einsum("ncd,nkd->nck", near, near)
    taken = np.zeros((n, c), bool)
    for k in range(c):
        closest = np.where(taken, between[:, k, :], -np.inf).max(1, initial=-np.inf)
        taken[:, k] = (ids[:, k] >= 0) & (sims[:, k] > closest) & (taken.sum(1) < most)
    order = np.argsort(np.where(ids < 0, 2, np.where(taken, 0, 1)), axis=1, kind="stable")[:, :most]
    out = np.take_along_axis(ids, order, 1)
    return np.pad(out, ((0, 0), (0, most - out.shape[1])), constant_values=-1)


def _exact_links(x: np.ndarray, members: np.ndarray, most: int, wide: int) -> np.ndarray:
    """Links of each member among the members, by full comparison (small sets only)."""
    out = np.full((len(members), most), -1, np.int32)
    own = x[members]
    for k in range(0, len(members), BATCH):
        sims = own[k : k + BATCH] @ own.T
        sims[np.arange(len(sims)), np.arange(k, k + len(sims))] = -np.inf
        best = np.argsort(-sims, axis=1)[:, : min(wide, len(members) - 1)]
        if best.shape[1]:
            out[k : k + BATCH] = _diverse(x, members[best], np.take_along_axis(sims, best, 1), most)
    return out


class Graph:
    """``x``: unit vectors (float32), one row per node."""

    def __init__(self, x: np.ndarray, keys: np.ndarray, build_width: int = 64, links: np.ndarray | None = None):
        """``links``: those of a graph built before over the same nodes; nothing else has to be made."""
        self.x = x
        n = len(x)
        level = _level(keys)
        self.order = np.lexsort((keys, -level))
        self.upper = self.order[: max(1, int(level.sum()))]
        self.links = np.full((n, LINKS), -1, np.int32) if links is None else links
        if links is not None:
            return
        first = self.order[: 2 * BATCH]
        self.links[first] = _exact_links(x, first, LINKS, 64)
        self._back(first)
        for k in range(2 * BATCH, n, BATCH):
            own = self.order[k : k + BATCH]
            ids, sims = self.search(x[own], build_width)
            among = x[own] @ x[own].T
            np.fill_diagonal(among, -np.inf)
            close = np.argsort(-among, axis=1)[:, :LINKS]
            ids = np.concatenate([ids, own[close]], axis=1)
            sims = np.concatenate([sims, np.take_along_axis(among, close, 1)], axis=1)
            rank = np.argsort(-sims, axis=1)[:, :build_width]
            self.links[own] = _diverse(x, np.take_along_axis(ids, rank, 1), np.take_along_axis(sims, rank, 1), LINKS)
            self._back(own)
        self._reach()

    def _reach(self, least: int = 8) -> None:
        """Nodes that too few others link to (choices inside tight clusters leave some) get links from their own neighbours, in place of links to much-linked nodes."""
        into = np.bincount(self.links[self.links >= 0], minlength=len(self.x))
        for v in np.flatnonzero(into < least):
            for u in self.links[v]:
                if u < 0 or into[v] >= least:
                    break
                row = self.links[u]
                if (row == v).any():
                    continue
                slot = int(np.where(row >= 0, into[row], len(self.x)).argmax())
                if row[slot] < 0 or into[row[slot]] > least:
                    if row[slot] >= 0:
                        into[row[slot]] -= 1
                    row[slot] = v
                    into[v] += 1

    def _back(self, own: np.ndarray) -> None:
        """Every link gets its opposite; a node with too many keeps a diverse choice."""
        source = np.repeat(own, LINKS)
        target = self.links[own].ravel()
        source, target = source[target >= 0], target[target >= 0]
        there = (self.links[target] == source[:, None]).any(1)
        source, target = source[~there], target[~there]
        order = np.argsort(target, kind="stable")
        source, target = source[order], target[order]
        nodes, count = np.unique(target, return_counts=True)
        if not len(nodes):
            return
        more = np.full((len(nodes), int(count.max())), -1, np.int32)
        row = np.repeat(np.arange(len(nodes)), count)
        more[row, np.arange(len(target)) - np.repeat(np.cumsum(count) - count, count)] = source
        for k in range(0, len(nodes), BATCH):
            at = nodes[k : k + BATCH]
            both = np.concatenate([self.links[at], more[k : k + BATCH]], axis=1)
            sims = np.where(both >= 0, np.einsum("nd,ncd->nc", self.x[at], self.x[np.maximum(both, 0)]), -np.inf)
            rank = np.argsort(-sims, axis=1)[:, : 2 * LINKS]
            self.links[at] = _diverse(self.x, np.take_along_axis(both, rank, 1), np.take_along_axis(sims, rank, 1), LINKS)

    def search(self, q: np.ndarray, width: int, seen: np.ndarray | None = None, least: float = np.inf, near_enough: list | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids, similarities) of the beam of each query, best first, -1 where it is shorter.

        ``seen`` marks what was visited; ``near_enough`` gets (queries, nodes) of at least the similarity ``least``, also
        those that the beam has no room for.
        """
        n, rows = len(q), np.arange(len(q))
        seen = np.zeros((n, len(self.x)), bool) if seen is None else seen
        near_enough = [] if near_enough is None else near_enough
        ids, sims, done = np.full((n, width), -1, np.int64), np.full((n, width), -np.inf, np.float32), np.zeros((n, width), bool)
        top = q @ self.x[self.upper].T
        entries = min(len(self.upper), width)
        best = np.argpartition(-top, entries - 1, axis=1)[:, :entries]
        ids[:, :entries], sims[:, :entries] = self.upper[best], np.take_along_axis(top, best, 1)
        seen[rows[:, None], self.upper[None, :]] = True
        r, c = np.nonzero(top >= least)
        near_enough.append((r, self.upper[c]))
        live = rows
        while len(live):
            fresh = []
            for _ in range(4):
                open_ = np.where((ids[live] >= 0) & ~done[live], sims[live], -np.inf)
                k = open_.argmax(1)
                go = open_[np.arange(len(live)), k] > -np.inf
                done[live[go], k[go]] = True
                near = np.full((len(live), LINKS), -1, np.int64)
                near[go] = self.links[ids[live[go], k[go]]]
                near[seen[live[:, None], np.maximum(near, 0)]] = -1
                r, c = np.nonzero(near >= 0)
                seen[live[r], near[r, c]] = True
                fresh.append(near)
            near = np.concatenate(fresh, axis=1)
            new = np.full(near.shape, -np.inf, np.float32)
            r, c = np.nonzero(near >= 0)
            new[r, c] = np.einsum("nd,nd->n", q[live[r]], self.x[near[r, c]])
            hit = new[r, c] >= least
            near_enough.append((live[r[hit]], near[r[hit], c[hit]]))
            every, value, flag = np.concatenate([ids[live], near], 1), np.concatenate([sims[live], new], 1), np.concatenate([done[live], np.zeros(near.shape, bool)], 1)
            top = np.argpartition(-value, width - 1, axis=1)[:, :width]
            ids[live], sims[live], done[live] = (np.take_along_axis(a, top, 1) for a in (every, value, flag))
            live = live[((ids[live] >= 0) & ~done[live]).any(1)]
        rank = np.argsort(-sims, axis=1)
        return np.take_along_axis(ids, rank, 1), np.take_along_axis(sims, rank, 1)

    def within(self, q: np.ndarray, least: float, width: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, node) pairs of at least this similarity: a beam, then a flood over links between nodes that are near enough."""
        seen = np.zeros((len(q), len(self.x)), bool)
        hits: list[tuple[np.ndarray, np.ndarray]] = []
        self.search(q, width, seen, least, hits)
        row, node = np.concatenate([h[0] for h in hits]), np.concatenate([h[1] for h in hits])
        found, waiting = [(row, node)], [(row, node)]
        while waiting:
            row, node = waiting.pop()
            if len(row) > FRONTIER:
                waiting.append((row[FRONTIER:], node[FRONTIER:]))
                row, node = row[:FRONTIER], node[:FRONTIER]
            near = self.links[node].ravel()
            r = np.repeat(row, LINKS)
            ok = near >= 0
            ok[ok] = ~seen[r[ok], near[ok]]
            both = np.unique(r[ok].astype(np.int64) * len(self.x) + near[ok])
            r, near = both // len(self.x), both % len(self.x)
            seen[r, near] = True
            hit = np.einsum("nd,nd->n", q[r], self.x[near]) >= least
            if hit.any():
                found.append((r[hit], near[hit]))
                waiting.append(found[-1])
        return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
