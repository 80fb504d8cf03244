"""Every query with an SQL twin gives the twin's rows on the smallest tables."""

from __future__ import annotations

import pytest
from twins import differences

import pdpview.operators.relational  # noqa: F401
from pdpview.catalog import QUERIES

SLOW = ("sweep", "scale_", "density_", "_w2s", "w2s_", "deferred_bound", "comparison_w2")


@pytest.mark.parametrize("name", [n for n, q in QUERIES.items() if q.sql and not any(x in n for x in SLOW)])
def test_twin(spark, small, con, name):
    q = QUERIES[name]
    assert differences(q.run(spark, small), q.sql, con) == ""


@pytest.mark.parametrize("name", [n for n, q in QUERIES.items() if not q.sql])
def test_runs(spark, small, name):
    assert QUERIES[name].run(spark, small).count() > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
