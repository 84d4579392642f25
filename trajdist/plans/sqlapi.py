"""The searches as SQL: views of the scenarios, table functions, and the text of a search."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions.geometry import AXES, approach_text
from ..operators import timebins
from ..operators.index import as_queries
from ..operators.meeting import OWNED
from ..session import kept
from ..sources.tables import COLUMNS
from .scenarios import DISTANCE, SCENARIOS, queries_of, segments


class BinsOfInterval:
    """The bins of a width that an interval touches."""

    def eval(self, t0: float, t1: float, start: float, width: float) -> Iterator[tuple[int]]:
        for b in range(int((t0 - start) // width), int((t1 - start) // width) + 1):
            yield (b,)


class CellsOfBox:
    """The cells (by axis) of a box in a grid of one width."""

    def eval(self, xlo: float, xhi: float, ylo: float, yhi: float, zlo: float, zhi: float, width: float) -> Iterator[tuple[int, int, int]]:
        for x in range(int(xlo // width), int(xhi // width) + 1):
            for y in range(int(ylo // width), int(yhi // width) + 1):
                for z in range(int(zlo // width), int(zhi // width) + 1):
                    yield x, y, z


class Splice:
    """The parts of an interval cut into k."""

    def eval(self, t0: float, t1: float, k: int) -> Iterator[tuple[int, float, float]]:
        for i in range(k):
            yield i, t0 + (t1 - t0) * i / k, t0 + (t1 - t0) * (i + 1) / k


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("bins_of_interval", udtf(BinsOfInterval, returnType="bin long"))
    spark.udtf.register("cells_of_box", udtf(CellsOfBox, returnType="cx long, cy long, cz long"))
    spark.udtf.register("splice_interval", udtf(Splice, returnType="part int, t0 double, t1 double"))


def register(spark: SparkSession, sf_dir: str, bins: dict[str, int] | None = None, reach: dict[str, float] | None = None) -> None:
    """Views seg_* of each scenario.  Of the dense one, and of those in ``bins``, also query_* (prefixed columns, one row for each overlapped bin),
    binned_* (entries, a row for each cell h that their box touches) and grid_* (one row: the cells of each axis, about as wide as ``reach``, the
    distance that most searches ask for; any other is answered as well)."""
    register_functions(spark)
    for name in SCENARIOS:
        d = segments(spark, sf_dir, name)
        if name == "dense" or (bins and name in bins):
            d = kept(d)
            index = timebins.placed(timebins.build(d, (bins or {}).get(name, 48)), (reach or DISTANCE).get(name, DISTANCE[name]))
            mine = timebins.overlaps(as_queries(queries_of(d, name)), index.directory, index.bins).drop("first", "last", "n")
            mine.createOrReplaceTempView(f"query_{name}")
            index.entries.createOrReplaceTempView(f"binned_{name}")
            axes = zip(AXES, index.grid.n, index.grid.lo, index.grid.width)
            spark.range(1).select(*(v.alias(f"{k}{c}") for c, n, lo, w in axes for k, v in (("n", F.lit(n)), ("lo", F.lit(float(lo))), ("w", F.lit(float(w) if w > 0 else None).cast("double"))))).createOrReplaceTempView(f"grid_{name}")
        d.createOrReplaceTempView(f"seg_{name}")


def _asked(name: str, dist: str) -> str:
    """The queries' rows once more for each cell that their box, grown by the distance, touches; q_low tells on which axes it is the first, as low does of entries."""
    mine = ", ".join(f"q_{c}" for c in COLUMNS)
    cell = lambda c, e: f"CAST(least(n{c} - 1, greatest(0, coalesce(floor(({e} - lo{c}) / w{c}), 0))) AS BIGINT)"
    ends = ", ".join(f"{cell(c, f'least(q_{c}0, q_{c}1) - {dist}')} AS _{c}a, {cell(c, f'greatest(q_{c}0, q_{c}1) + {dist}')} AS _{c}z" for c in AXES)
    out = f"(SELECT /*+ BROADCAST(g) */ *, {ends} FROM query_{name} CROSS JOIN grid_{name} g)"
    for c in AXES:
        out = f"(SELECT *, explode(sequence(_{c}a, _{c}z)) AS _{c} FROM {out})"
    low = " + ".join(f"CASE WHEN _{c} = _{c}a THEN {1 << i} ELSE 0 END" for i, c in enumerate(AXES))
    return f"(SELECT {mine}, bin, (_x * ny + _y) * nz + _z AS h, {low} + 8 AS q_low FROM {out})"


def search_text(name: str, dist: float, m: int) -> str:
    """A search over the registered views: an equi-join on bin and cell that keeps a pair in one cell, the boxes, then the closed form."""
    d = f"CAST({float(dist)!r} AS DOUBLE)"
    near = " AND ".join(f"greatest({c}0, {c}1) >= least(q_{c}0, q_{c}1) - {d} AND least({c}0, {c}1) <= greatest(q_{c}0, q_{c}1) + {d}" for c in AXES)
    out = f"(SELECT /*+ MERGE(a) */ * FROM {_asked(name, d)} a JOIN binned_{name} USING (bin, h) WHERE {OWNED} AND q_t0 < t1 AND t0 < q_t1 AND {near} AND q_traj_id <> traj_id)"
    for i, layer in enumerate(approach_text(dist)):
        out = f"(SELECT *, {', '.join(f'{v} AS {k}' for k, v in layer.items())} FROM {out})"
        if i == 2:
            out = f"(SELECT q_traj_id, q_seg_id, traj_id, seg_id, inline(array(named_struct('b0', b0, 'b1', b1, 'qa', qa, 'qb', qb, 'qc', qc))) FROM {out})"
    return f"""SELECT q_traj_id AS q_traj, q_seg_id AS q_seg, traj_id, seg_id, floor((b0 + s0) * 1e6D + 0.5D) / 1e6D AS lo, floor((b0 + s1) * 1e6D + 0.5D) / 1e6D AS hi FROM {out} WHERE s0 <= s1"""
