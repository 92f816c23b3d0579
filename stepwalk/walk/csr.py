"""Walks over a graph that fits one worker: adjacency in compressed rows, all walkers of a batch in lockstep.

A draw uses static prefix sums with corrections at the last vertex and the common neighbours, found by probing the shorter
of the two lists.  With whole weights the picks equal those of the ordered scan.
"""

from __future__ import annotations

import numpy as np

from .bounds import gap
from .kernel import draw_corrected, ragged, runs
from .rng import SPAN


class Resident:
    def __init__(self, vids: np.ndarray, offsets: np.ndarray, dst: np.ndarray, ws: np.ndarray):
        """``dst`` holds positions in ``vids`` (sorted), ascending within a row."""
        self.vids, self.offsets, self.dst, self.ws = vids, offsets, dst, ws
        self.prefix = np.concatenate([np.zeros(1, ws.dtype), np.cumsum(ws)])
        self.deg = np.diff(offsets)
        self.keys = np.repeat(np.arange(len(vids)), self.deg) * len(vids) + dst

    @classmethod
    def of(cls, src: np.ndarray, dst: np.ndarray, ws: np.ndarray) -> Resident:
        vids = np.unique(np.concatenate([src, dst]))
        a, b = np.searchsorted(vids, src), np.searchsorted(vids, dst)
        order = np.lexsort((b, a))
        offsets = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=len(vids)))])
        return cls(vids, offsets, b[order], ws[order])

    def mark(self, popular: np.ndarray) -> None:
        """Marks popular vertices and notes the weight ranges that bounds need."""
        self.hot = np.isin(self.vids, popular)
        some = np.flatnonzero(self.deg > 0)
        self.wmin, self.wmax = np.ones(len(self.vids), self.ws.dtype), np.ones(len(self.vids), self.ws.dtype)
        if len(some):
            self.wmin[some] = np.minimum.reduceat(self.ws, self.offsets[some])
            self.wmax[some] = np.maximum.reduceat(self.ws, self.offsets[some])

    def remembered(self, prev: np.ndarray, cur: np.ndarray, params, eps: float) -> np.ndarray:
        """``prev``, or -1 where the bounds are tight enough for a static draw."""
        able = np.flatnonzero((prev >= 0) & ~self.hot[np.maximum(prev, 0)] & self.hot[cur])
        tight = gap(self.deg[prev[able]], self.deg[cur[able]], self.wmin[cur[able]], self.wmax[cur[able]], params.p, params.q) < eps
        out = prev.copy()
        out[able[tight]] = -1
        return out

    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.vids, self.offsets, self.dst, self.ws, self.prefix, self.keys))

    def find(self, u: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Position of edge u-x in the edge arrays, -1 where there is none."""
        sought = u * len(self.vids) + x
        at = np.searchsorted(self.keys, sought)
        at[at == len(self.keys)] = 0
        return np.where(self.keys[at] == sought, at, -1) if len(self.keys) else np.full(len(u), -1)

    def step(self, cur: np.ndarray, prev: np.ndarray, draw: np.ndarray, factors: tuple) -> np.ndarray:
        """Next positions; ``prev`` is -1 for static draws.  Every ``cur`` must have neighbours."""
        back, near, other = factors
        n = len(cur)
        whole = self.ws.dtype.kind == "i" and all(isinstance(f, int) for f in factors)
        begin, size = self.offsets[cur], self.deg[cur]
        biased = prev >= 0
        plain = np.where(biased, other, 1)
        walker = np.flatnonzero(biased)
        if len(walker) and near != other:
            u, v = prev[walker], cur[walker]
            swap = self.deg[u] > size[walker]
            scan, probe = np.where(swap, v, u), np.where(swap, u, v)
            lengths = self.deg[scan]
            x = self.dst[ragged(self.offsets[scan], lengths)]
            at = self.find(np.repeat(probe, lengths), x)
            own = np.repeat(np.arange(len(walker)), lengths)
            hit = np.flatnonzero(at >= 0)
            own, x, at = own[hit], x[hit], at[hit]
            at = np.where(swap[own], self.offsets[scan[own]] + runs(lengths)[hit], at)
            keep = x != u[own]
            row, place, extra = [walker[own[keep]]], [at[keep]], [np.full(int(keep.sum()), near - other)]
        else:
            row, place, extra = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if len(walker):
            at = self.find(cur[walker], prev[walker])
            row.append(walker[at >= 0])
            place.append(at[at >= 0])
            extra.append(np.full(int((at >= 0).sum()), back - other))
        special = np.concatenate(row).astype(np.int64), np.concatenate(place).astype(np.int64), np.concatenate(extra)
        return self.dst[draw_corrected(self.prefix, self.ws, begin, size, plain, special, draw, whole)]

    def step_reject(self, cur: np.ndarray, prev: np.ndarray, draw: np.ndarray, factors: tuple) -> np.ndarray:
        """Next positions by rejection: propose by plain weights, accept by factor over the largest factor.

        One probe of an edge a trial instead of a list; each trial's numbers come from the walker's draw.
        """
        back, near, other = (float(f) for f in factors)
        out, live, trial = np.zeros(len(cur), np.int64), np.arange(len(cur)), 0
        while len(live):
            trial += 1
            seed = (draw[live].astype(np.uint64) + np.uint64(trial)) * np.uint64(0x9E3779B97F4A7C15)
            seed = (seed ^ (seed >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            seed ^= seed >> np.uint64(27)
            r1 = (seed >> np.uint64(32)).astype(float) / 2**32
            r2 = (((seed * np.uint64(0x94D049BB133111EB)) >> np.uint64(32)).astype(float)) / 2**32
            v, u = cur[live], prev[live]
            low, high = self.prefix[self.offsets[v]], self.prefix[self.offsets[v + 1]]
            at = np.searchsorted(self.prefix, low + r1 * (high - low), side="right") - 1
            at = np.clip(at, self.offsets[v], self.offsets[v + 1] - 1)
            x = self.dst[at]
            factor = np.where(u < 0, max(back, near, other), np.where(x == u, back, np.where(self.find(np.maximum(u, 0), x) >= 0, near, other)))
            ok = r2 * max(back, near, other) < factor
            out[live[ok]] = x[ok]
            live = live[~ok]
        return out
