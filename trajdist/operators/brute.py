"""All pairs: the standard that every method is held against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry
from .index import as_queries, entries_of, other_trajectory


def candidates(q: DataFrame, d: DataFrame, time: str = "overlap", dist: float | str = 0.0) -> DataFrame:
    """All pairs, or those whose times overlap.  A range predicate alone runs as a nested loop: for small inputs only."""
    qs, d = as_queries(q, dist), entries_of(d)
    if time == "none":
        return qs.crossJoin(d)
    return qs.join(d, (F.col("q_t0") < F.col("t1")) & (F.col("t0") < F.col("q_t1")))


def search(q: DataFrame, d: DataFrame, dist: float | str, exclude_self: bool = True) -> DataFrame:
    return geometry.matches(candidates(q, d, dist=dist).where(other_trajectory(exclude_self)), dist)
