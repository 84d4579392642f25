"""All registered queries and their SQL."""

from __future__ import annotations

from ..streaming import streams
from . import measures, relational, searches, workloads

_PARTS = (searches, workloads, measures, relational, streams)


def queries() -> dict:
    out: dict = {}
    for p in _PARTS:
        out |= p.queries()
    return out


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for p in _PARTS:
        out |= p.oracles()
    return out
