"""Every registered query that has SQL gives the rows of its SQL, at the smallest scale."""

from __future__ import annotations

import pytest

from trajdist.plans import registry

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()


def test_names():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 150


def plain(v):
    if v is None or v != v:
        return "null"
    if isinstance(v, bool) or type(v).__name__ == "bool_":
        return str(bool(v))
    if hasattr(v, "isoformat"):
        return str(v)[:19]
    return f"{float(v):.12g}" if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, duck, sf_dir, name):
    got = QUERIES[name](spark, sf_dir)
    columns = sorted(got.columns)
    mine = sorted(tuple(plain(r[c]) for c in columns) for r in got.collect())
    want = duck.execute(ORACLES[name]).df()
    assert sorted(want.columns) == columns
    assert mine == sorted(tuple(plain(None if v is None or v is __import__("pandas").NA or v is __import__("pandas").NaT else v) for v in r) for r in want[columns].itertuples(index=False, name=None))
