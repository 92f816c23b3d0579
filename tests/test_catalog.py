"""Every catalog query that has SQL, on the smallest tables."""

from __future__ import annotations

import pytest

import __spark_entry__ as entry_point
from stepwalk.plans import catalog

from .compare import connect, same

SQL = catalog.oracle_sql()
# The builders have a test of their own; these take the largest share of the rest at no gain.
SLOW = {"graph_prob_memory", "trans_alias"}


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(n for n in SQL if not n.endswith("_edges") and n not in SLOW))
def test_query_matches_sql(spark, sf, con, name):
    same(con, catalog.queries()[name](spark, sf), SQL[name])


def test_entry_and_names(spark):
    assert entry_point.entry(spark).count() > 0
    assert set(entry_point.oracle_sql()) <= set(entry_point.queries())
