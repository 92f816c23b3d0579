"""Entity walks start from every vertex; experiment workloads move with their parameters as they should."""

from __future__ import annotations

from collections import defaultdict

from stepwalk.plans import catalog
from stepwalk.plans.shared import graph


def test_entity_walks_start_everywhere(spark, sf):
    want = {tuple(r) for r in graph(spark, sf, "entity").select("src").distinct().collect()}
    found = catalog.queries()
    for name in ("walk_base_entity", "walk_approx_entity", "cost_switch_supersteps"):
        assert {tuple(r) for r in found[name](spark, sf).select("start").distinct().collect()} == want
    told = found["cost_message_log"](spark, sf).where("kind = 'step' and step = 1").first()
    assert told.n_msgs == len(want)


def test_savings_and_messages_grow_with_skew(spark, sf):
    rows = catalog.queries()["work_skew_costs"](spark, sf).collect()
    by = defaultdict(list)
    for r in sorted(rows, key=lambda r: r.s):
        by[r.p].append(r)
    for own in by.values():
        assert [r.s for r in own] == [1.78, 2.0, 3.0, 4.0, 5.0]
        assert all(r.ids_approx <= r.ids_cache < r.ids_base for r in own)
        cache, approx, share = ([f(r) for r in own] for f in (lambda r: r.ids_cache / r.ids_base, lambda r: r.ids_approx / r.ids_base, lambda r: r.message_share))
        assert cache[0] > cache[2] > cache[4] and approx[0] > approx[4] and share[0] < share[2] < share[4]


def test_planted_scores_rank_the_solutions(spark, sf):
    rows = catalog.queries()["acc_planted_curves"](spark, sf).collect()
    assert len(rows) == 2 * 4 * 2
    mean = defaultdict(list)
    for r in rows:
        mean[r.solution].append(r.micro)
        assert 0 < r.macro <= 1
    mean = {k: sum(v) / len(v) for k, v in mean.items()}
    assert abs(mean["exact"] - mean["precomputed"]) < 0.06 and abs(mean["approx"] - mean["exact"]) < 0.06
    assert mean["trimmed"] < mean["exact"] - 0.02
    assert all(max(r.micro for r in rows if r.fraction == 0.6 and r.solution == k) > max(r.micro for r in rows if r.fraction == 0.2 and r.solution == k) for k in mean)


def test_measured_ratios(spark, sf):
    rows = {(r.graph, r.variant): r for r in catalog.queries()["cost_speedup"](spark, sf).collect()}
    assert len(rows) == 2 * 7 and all(r.ratio > 0 for r in rows.values())
    assert all(r.ratio == 1 for (_, v), r in rows.items() if v == "base")
    shares = catalog.queries()["cost_stage_breakdown"](spark, sf).collect()
    assert len(shares) == 6 and abs(sum(r.share for r in shares if r.graph == "base") - 1) < 1e-9
