"""Worked selections over a given table: Spark reads it, and rows follow it."""

import pytest

from labelroute.queries import ORACLES, QUERIES
from labelroute.sources import tables

NAMES = ["c02_running_example", "c09_optimal", "c14_set_cover", "c15_disjoint", "c17_greedy_trace_udtf", "c17_selection_trace", "m14_approximation_gap"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_lineitem(spark, small, duck, name, monkeypatch):
    read = []
    load = tables.load
    monkeypatch.setattr("labelroute.queries.selection.load", lambda s, d, t: read.append(t) or load(s, d, t))
    got = QUERIES[name](spark, small)
    assert read == ["lineitem"]
    want = duck.sql(ORACLES[name])
    assert sorted(map(tuple, got.select(*want.columns).collect())) == sorted(want.fetchall())
