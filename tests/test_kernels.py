from __future__ import annotations

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from stepwalk.config import WalkParams
from stepwalk.walk import alias, bounds
from stepwalk.walk.csr import Resident
from stepwalk.walk.kernel import biased_mass, member, pick, pick_corrected
from stepwalk.walk.rng import SPAN

FIVE = [(1, 2, 1), (2, 3, 1), (1, 3, 2), (3, 4, 1), (4, 5, 3)]


def both(edges):
    return sorted([(a, b, w) for a, b, w in edges] + [(b, a, w) for a, b, w in edges])


def masses(edges, u, v, params):
    near = [(x, w) for a, x, w in both(edges) if a == v]
    mine = np.array(sorted(x for a, x, _ in both(edges) if a == u))
    ids, ws = np.array([x for x, _ in near]), np.array([w for _, w in near])
    rows = np.zeros(len(ids), int)
    common = member(rows, ids, np.zeros(len(mine), int), mine)
    return ids, ws, common, biased_mass(rows, ids, ws, np.array([u]), common, np.array([True]), params.scaled())


def test_worked_five_vertices():
    low, far = WalkParams(0.5, 2.0), WalkParams(2.0, 0.5)
    assert masses(FIVE, 1, 3, low)[3].tolist() == [8, 2, 1]
    assert masses(FIVE, 2, 3, low)[3].tolist() == [4, 4, 1]
    assert masses(FIVE, 1, 3, far)[3].tolist() == [2, 2, 4]
    assert masses(FIVE, 3, 4, far)[3].tolist() == [1, 12]
    picks = [pick(np.array([8, 2, 1]), np.array([3]), np.array([d]))[0] for d in range(11)]
    assert picks == [0] * 8 + [1] * 2 + [2]


def test_scaled_factors():
    assert WalkParams(0.5, 2.0).scaled() == (4, 2, 1)
    assert WalkParams(2.0, 0.5).scaled() == (1, 2, 4)
    assert WalkParams(1.0, 1.0).scaled() == (1, 1, 1)
    assert WalkParams(1 / 3 + 1e-7, 2.0).scaled() is None


def random_graph(seed, n=12, p=0.4):
    r = np.random.default_rng(seed)
    return [(int(a), int(b), int(r.integers(1, 5))) for a in range(n) for b in range(a + 1, n) if r.random() < p]


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000), st.sampled_from([(0.5, 2.0), (2.0, 0.5), (0.25, 4.0), (4.0, 4.0), (1.0, 1.0)]), st.integers(0, SPAN - 1))
def test_scan_corrected_and_resident_picks_agree(seed, pq, draw):
    edges, params = random_graph(seed), WalkParams(*pq)
    if not edges:
        return
    u, v, _ = both(edges)[seed % len(both(edges))]
    ids, ws, common, mass = masses(edges, u, v, params)
    scan = int(pick(mass, np.array([len(ids)]), np.array([draw]))[0])
    prefix = np.concatenate([[0], np.cumsum(ws)])
    assert pick_corrected(ids, prefix, u, np.flatnonzero(common), params.scaled(), draw) == scan
    src, dst, w = (np.array(x) for x in zip(*both(edges), strict=True))
    g = Resident.of(src, dst, w)
    at = np.searchsorted(g.vids, [u, v])
    assert g.vids[g.step(at[1:], at[:1], np.array([draw]), params.scaled())[0]] == ids[scan]


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10_000), st.sampled_from([(0.5, 2.0), (2.0, 0.5), (0.25, 4.0), (4.0, 0.25), (4.0, 4.0)]))
def test_bounds_hold(seed, pq):
    edges, params = random_graph(seed), WalkParams(*pq)
    degree = {v: sum(1 for a, _, _ in both(edges) if a == v) for e in edges for v in e[:2]}
    for u, v, _ in both(edges)[:20]:
        ids, ws, _, mass = masses(edges, u, v, params)
        probs = mass / mass.sum()
        a, b = bounds._ends(np.float64(degree[u]), np.float64(degree[v]), *pq, "tight", np.minimum)
        low = min(1.0, 1 / pq[1]) * ws.min() / (max(a, b) * ws.max())
        high = min(1.0, max(1.0, 1 / pq[1]) * ws.max() / (min(a, b) * ws.min()))
        for x, pr in zip(ids, probs, strict=True):
            if x != u:
                assert low - 1e-12 <= pr <= high + 1e-12


def test_bounds_approach_equal_shares_at_hubs():
    one = np.array([1.0])
    gap = bounds.gap(np.array([3]), np.array([100_000]), one, one, 0.5, 2.0)[0]
    assert abs(gap * 100_000 - 1) < 1e-3


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(1, 50), min_size=1, max_size=20))
def test_alias_gives_back_the_weights(weights):
    accept, other = alias.build(np.array(weights, float))
    np.testing.assert_allclose(alias.probabilities(accept, other), np.array(weights) / sum(weights), atol=1e-12)
    assert 0 <= alias.pick(accept, other, 0.999999, 0.5) < len(weights)


def test_member_with_wide_ids():
    big = 1 << 61
    assert member(np.array([0, 1]), np.array([big, -big]), np.array([0, 1]), np.array([big, big])).tolist() == [True, False]
