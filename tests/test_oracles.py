"""Every library query against its SQL on the smallest tables."""

import pytest

from labelroute.queries import ORACLES, QUERIES


def _rows(rows):
    return sorted((tuple(round(x, 5) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


# one query of each shape; the driver runs all of them
PICKED = sorted(
    n for n in ORACLES
    if n[:3] in ("a03", "a07", "a10", "b02", "b08", "b10", "b11", "b16", "c01", "c02", "c09", "c12", "c17", "d01", "d04", "d05", "d07", "d13", "e06", "f03", "f05", "f11", "g01", "g03", "g07", "g11", "m01")
)


@pytest.mark.parametrize("name", PICKED)
def test_matches_sql(spark, small, duck, name):
    df = QUERIES[name](spark, small)
    cols = sorted(df.columns)
    want = duck.sql(ORACLES[name])
    assert sorted(want.columns) == cols
    at = [want.columns.index(c) for c in cols]
    assert _rows(tuple(r) for r in df.select(*cols).collect()) == _rows(tuple(r[i] for i in at) for r in want.fetchall())


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)
