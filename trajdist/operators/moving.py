"""CELL for entries that cross many cells: these meet while they are in them, slice by slice of time.

The box of a long move touches most of the grid, so that cells leave little out.  Time is cut into slices in which the mean
entry moves little further than the distance; in a slice a segment is a piece, whose box is small.  Pieces stand in the cells of
the grid, and those of a query's cell look at the cells whose pieces come near them, as matrices: what may be within the distance goes
through the closed form, by the steps of SQL.  A pair is kept in the slice in which it first is within the distance, so it
arises once and nothing is shuffled to remove repeats.  Rows are dealt over windows of some slices.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import MICRO
from ..sources.tables import COLUMNS
from .index import Extents
from .meeting import MOST_TIMES, Grid, Times
from .tally import _groups, _Moves, _Pieces, _slack

#: Slices of time for each distance that the mean entry moves; entries to a window at least, and entries and queries of a task at most, about.
SLICES_PER_REACH, WINDOW, ENTRIES, QUERIES = 1.5, 10_000, 400_000, 400_000
#: Queries and entries of a matrix, entries of a group, and pairs that go through the closed form together.
MINE, RUN, ITS, PAIRS = 64, 1024, 128, 1 << 13
#: Pairs from which rows are handed on.
ROWS = 1 << 15
#: Pieces that a cell holds on average, at least; where it would be fewer, cells are put together.
LEAST = 16


def _by_cells(grid: Grid, points: np.ndarray, size: int) -> list[np.ndarray]:
    """Rows by the cell of their point; those of a full cell in groups of at most ``size``."""
    n, most = list(grid.n), max(1.0, len(points) / LEAST)
    while math.prod(n) > most:
        n[n.index(max(n))] //= 2
    at = np.zeros(len(points), np.int64)
    for i, (k, m) in enumerate(zip(n, grid.n)):
        width = grid.width[i] * m / k
        at = at * k + (np.clip(np.floor((points[:, i] - grid.lo[i]) / width), 0, k - 1).astype(np.int64) if width > 0 else 0)
    order = np.argsort(at, kind="stable")
    cells = np.split(order, np.flatnonzero(np.diff(at[order])) + 1)
    return [rows[g] for rows in cells for g in (_groups(points[rows], size) if len(rows) > size else [slice(None)])]


def _closed(q: tuple[np.ndarray, ...], e: tuple[np.ndarray, ...], i: np.ndarray, j: np.ndarray, dist: float, since: float, until: float, out: list[np.ndarray]) -> int:
    """Writes the result's columns of the pairs of other trajectories that are within the distance, and first are in this slice, and tells how many there are: the steps of
    ``geometry.approach_text``, in its order."""
    q0, e0 = q[0].take(i), e[0].take(j)
    b0, b1 = np.maximum(q0, e0), np.minimum(q[1].take(i), e[1].take(j))
    np.subtract(b0, q0, out=q0)
    np.subtract(b0, e0, out=e0)
    qa = qb = qc = None
    for k in (2, 3, 4):
        v, u = q[k + 3].take(i), e[k + 3].take(j)
        w = v - u
        v *= q0
        v += q[k].take(i)
        u *= e0
        u += e[k].take(j)
        v -= u
        if qa is None:
            qa, qb, qc = w * w, v * w, v * v
        else:
            np.multiply(w, w, out=u)
            qa += u
            w *= v
            qb += w
            v *= v
            qc += v
    qc -= dist * dist
    disc = np.multiply(qb, qb, out=q0)
    np.multiply(qa, qc, out=e0)
    disc -= e0
    keep, rest = disc >= 0, qa == 0
    np.negative(qb, out=qb)
    with np.errstate(all="ignore"):
        root = np.sqrt(np.maximum(disc, 0.0, out=disc), out=disc)
        s0 = np.subtract(qb, root, out=e0)
        s0 /= qa
        s1 = np.add(qb, root, out=qb)
        s1 /= qa
    if rest.any():
        s0[rest], s1[rest] = np.where(qc[rest] <= 0, 0.0, np.inf), np.inf
        keep |= rest
    np.maximum(s0, 0.0, out=s0)
    np.minimum(s1, np.subtract(b1, b0, out=v), out=s1)
    keep &= s0 <= s1
    s0 += b0
    s1 += b0
    first = np.minimum(s0, b1, out=v)
    keep &= first <= until
    began = first > since
    began |= b0 >= since
    keep &= began
    keep &= b0 < b1
    mine, its = q[8].take(i), e[8].take(j)
    keep &= mine != its
    k = np.flatnonzero(keep)
    for column, values, at in zip(out, (mine, q[9], its, e[9], s0, s1), (k, i.take(k), k, j.take(k), k, k)):
        values.take(at, out=column[: len(k)], mode="clip")
    return len(k)


def _rows(q: tuple[np.ndarray, ...], e: tuple[np.ndarray, ...], some: list[tuple[np.ndarray, np.ndarray]], dist: float, since: float, until: float, rounded: bool) -> list[np.ndarray]:
    i, j = map(np.concatenate, zip(*some))
    out, n = [np.empty(len(i), c.dtype) for c in (q[8], q[9], e[8], e[9], q[0], q[0])], 0
    for k in range(0, len(i), PAIRS):
        n += _closed(q, e, i[k : k + PAIRS], j[k : k + PAIRS], dist, since, until, [c[n:] for c in out])
    out = [c[:n] for c in out]
    for c in out[4:] if rounded else []:
        # The steps of ``geometry.rounded``.
        c *= MICRO
        c += 0.5
        np.floor(c, out=c)
        c /= MICRO
    return out


def _dot(f: np.ndarray, g: np.ndarray) -> np.ndarray:
    return np.einsum("ij,ij->i", f, g)


def _factors(p: _Pieces, rows: np.ndarray | slice, centre: np.ndarray, width: float) -> tuple:
    """Places from the centre and speeds, their products, start and end inside the slice, and the longest way that one has to look from the centre."""
    at, v = p.at[rows] - centre, p.v[rows]
    pp, vv = _dot(at, at), _dot(v, v)
    return at, v, pp, _dot(at, v), vv, np.maximum(p.u0[rows], 0.0), np.minimum(p.u1[rows], width), float((np.sqrt(pp) + width * np.sqrt(vv)).max())


def _maybe(a: _Pieces, b: _Pieces, x: np.ndarray, y: np.ndarray, mine: tuple, its: tuple, dist: float) -> np.ndarray:
    """Places of the matrix of a group's pieces and others that may be within the distance in the slice, less those that surely were before it."""
    (p, v, pp, pv, vv, p0, p1, one), (o, u, oo, ou, uu, o0, o1, other) = mine, its
    scale = one + other
    kind = np.float32 if _slack(scale, dist, np.float32) < dist * dist / 8 else np.float64
    slack, m, n = _slack(scale, dist, kind), len(x), len(y)
    # Of the squared distance: twice the square of the speed, what the start takes off it, and the square of the start.
    left, right = np.zeros((3, m, 10), kind), np.empty((10, n), kind)
    left[0, :, :3], left[0, :, 6], left[0, :, 7] = -4 * v, 2 * vv, 2
    left[1, :, :3], left[1, :, 3:6], left[1, :, 6], left[1, :, 8] = 2 * p, 2 * v, -2 * pv, -2
    left[2, :, 3:6], left[2, :, 6], left[2, :, 9] = -2 * p, pp, 1
    right[:3], right[3:6], right[6], right[7], right[8], right[9] = u.T, o.T, 1, uu, ou, oo
    qa, qb, qc = (left.reshape(3 * m, 10) @ right).reshape(3, m, n)
    np.maximum(qa, np.finfo(kind).tiny, out=qa)
    with np.errstate(over="ignore", invalid="ignore"):
        s = qb / qa
    for clamp, f, g in ((np.maximum, p0.astype(kind), o0.astype(kind)), (np.minimum, p1.astype(kind), o1.astype(kind))):
        clamp(s, g, out=s)
        if f.min() != f.max() or f[0] != g[0] or g.min() != g.max():
            clamp(s, f[:, None], out=s)
    qa *= s
    qa *= kind(0.5)
    qa -= qb
    qa *= s
    qa += qc
    found = qa <= kind(dist * dist + slack)
    if a.old[x].any() and b.old[y].any():
        before = qc <= kind(dist * dist - slack)
        before &= a.old[x][:, None]
        before &= b.old[y]
        found &= ~before
    return found


def matches(q: _Moves, e: _Moves, q_seg: np.ndarray, e_seg: np.ndarray, edges: np.ndarray, grid: Grid, dist: float, rounded: bool = False) -> Iterator[list[np.ndarray]]:
    """Columns of the result, some rows at a time: the pairs that first are within the distance in one of the slices."""
    columns = [(m.t0, m.t1, *m.start, *m.speed, m.traj, seg) for m, seg in ((q, q_seg), (e, e_seg))]
    for since, until in zip(edges[:-1], edges[1:]):
        i, j = (np.flatnonzero((m.t0 < until) & (m.t1 > since)) for m in (q, e))
        if not len(i) or not len(j):
            continue
        width = until - since
        fast = 8 * dist + 4 * width * sum(float(np.median(np.abs(v[j]))) for v in e.speed)
        a, b = (_Pieces(m, rows, since, width, fast, size, lambda points, size: _by_cells(grid, points, size)) for m, rows, size in ((q, i, MINE), (e, j, ITS)))
        mine, its = (tuple(c[p.rows] for c in side) for side, p in zip(columns, (a, b)))
        some: list[tuple[np.ndarray, np.ndarray]] = []
        waiting = 0
        for g in range(len(a.ends)):
            x, low, high = a.inside(g), a.low[g], a.high[g]
            every, centre = b.close(low, high, dist + 1e-9 * (dist + np.abs([low, high]).max())), (low + high) / 2
            if not len(every):
                continue
            factors, quick = _factors(a, x, centre, width), b.fast[every]
            for near in (every[~quick], every[quick]) if quick.any() else (every,):
                for k in range(0, len(near), RUN):
                    y = near[k : k + RUN]
                    at = np.flatnonzero(_maybe(a, b, x, y, factors, _factors(b, y, centre, width), dist))
                    if len(at):
                        r = at // len(y)
                        at -= r * len(y)
                        r += x[0]
                        some.append((r, y.take(at)))
                        waiting += len(at)
                    if waiting >= ROWS:
                        yield _rows(mine, its, some, dist, since, until, rounded)
                        some, waiting = [], 0
        if some:
            yield _rows(mine, its, some, dist, since, until, rounded)


def crossing(grid: Grid, ext: Extents) -> bool:
    """Whether the mean entry is wider than a cell."""
    return any(0 < w < mean for w, mean in zip(grid.width, ext.mean))


def _windows(ext: Extents, dist: float) -> tuple[Times, int]:
    """Windows of time, and slices of each: powers of two, so that edges are exact."""
    moved = max(ext.mean[:3])
    parts = min(16, max(1, SLICES_PER_REACH * moved / dist)) if dist > 0 else 16
    whole = ext.t_max - ext.t_min
    width = 2.0 ** math.ceil(math.log2(max(ext.mean[3] / parts, whole / MOST_TIMES)))
    least = max(ext.mean[3] / 2, whole * WINDOW / ext.n)
    slices = 2 ** max(0, math.ceil(math.log2(least / width)))
    return Times(width * slices, math.floor(ext.t_min / (width * slices)), max(math.floor(ext.t_min / (width * slices)), math.ceil(ext.t_max / (width * slices)) - 1)), slices


def _dealt(q: DataFrame, d: DataFrame, times: Times) -> tuple[DataFrame, int]:
    """Both sides' rows (_mine tells queries) with the window _at and the number of the task that holds them, and how many tasks there are.

    A row goes to each window that it reaches; of full windows, to a share of the queries and a share of the entries, by hash."""
    a, z = times.range(F.col("t0"), F.col("t1"))
    rows = q.select(*COLUMNS, F.lit(True).alias("_mine")).unionByName(d.select(*COLUMNS, F.lit(False).alias("_mine"))).withColumn("_at", F.explode(F.sequence(a, z)))
    known, tasks = [], 0
    for r in sorted(rows.groupBy("_at").agg(F.count_if("_mine").alias("mine"), F.count_if(~F.col("_mine")).alias("its")).collect()):
        if r.mine and r.its:
            lots, blocks = -(-r.mine // QUERIES), -(-r.its // ENTRIES)
            known.append((r._at, lots, blocks, tasks))
            tasks += lots * blocks
    table = F.broadcast(q.sparkSession.createDataFrame(known, "_at long, _lots int, _blocks int, _first int"))
    share = lambda of: F.pmod(F.xxhash64("traj_id", "seg_id"), F.col(of)).cast("int")
    every = lambda of, task: F.transform(F.sequence(F.lit(0), F.col(of) - 1), task)
    mine = every("_blocks", lambda i: F.col("_first") + i * F.col("_lots") + share("_lots"))
    its = every("_lots", lambda i: F.col("_first") + share("_blocks") * F.col("_lots") + i)
    dealt = rows.join(table, "_at").withColumn("_task", F.explode(F.when(F.col("_mine"), mine).otherwise(its)))
    return dealt.drop("_lots", "_blocks", "_first"), tasks


def search(q: DataFrame, d: DataFrame, grid: Grid, ext: Extents, dist: float, rounded: bool = False) -> DataFrame:
    """q_traj, q_seg, traj_id, seg_id, lo, hi: pairs of other trajectories within the distance, each in the slice in which it first is.

    Results are many, and pass through the virtual machine row by row: columns are never null, and ``rounded`` times are made before it."""
    times, slices = _windows(ext, dist)
    rows, tasks = _dealt(q, d, times)
    names = ["q_traj", "q_seg", "traj_id", "seg_id", "lo", "hi"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        all_rows = pa.Table.from_batches(held).to_pandas()
        del held
        for (_, at), part in all_rows.groupby(["_task", "_at"]):
            left, right = part[part["_mine"]], part[~part["_mine"]]
            edges = times.width / slices * (at * slices + np.arange(slices + 1))
            for columns in matches(_Moves.of(left, ""), _Moves.of(right, ""), left["seg_id"].to_numpy(), right["seg_id"].to_numpy(), edges, grid, dist, rounded):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names)

    schema = ", ".join(f"{c} {'double' if c in ('lo', 'hi') else 'long'} NOT NULL" for c in names)
    return rows.repartitionById(max(1, tasks), F.col("_task")).mapInArrow(run, schema)
