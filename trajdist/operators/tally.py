"""Counts and results of boxes in space and time without a row for each pair.

Sums.  What a query meets in a directory is a difference of sums: of what begins before its end, and of what ends by
its start; of corners of a grid; of cells less the faces between them, which counts a pair of boxes once, however many cells it shares.

Sets of bits.  Entries stand in blocks of some thousands.  For each bound of a block's boxes a table tells, as bits, which
entries lie below each of its values; a query takes one row of each table, and what is left of their conjunction are the
entries that it meets.  Only these are counted.

Matrices.  Pairs within a distance are looked at as matrices of a group of queries and what comes near its box, slice by slice of time.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry
from ..functions.geometry import AXES
from .index import as_queries, entries_of

#: Words of a block's set of bits, and its entries.
WORDS = 64
BLOCK = 64 * WORDS
#: Parts of time; entries and queries that a task holds together, at most about.
PARTS, ENTRIES, QUERIES = 64, 200_000, 1 << 20
#: Queries that are looked at together.
CHUNK = 256
#: Where pairs are looked at as matrices: how many times as many a task holds, groups of queries and of entries, and entries of a matrix.
TOGETHER = 4
MINE, ITS, RUN = 128, 256, 512
#: Slices of time: how many to a mean segment at most and for each distance that it moves, and how many in all.
MOST_PARTS, PARTS_PER_REACH, MOST_SLICES = 16, 1.5, 512


# ---- sums over directories ---------------------------------------------------------------------------------------


def bin_sums(lo: np.ndarray, hi: np.ndarray, weights: np.ndarray) -> Callable[..., Column]:
    """A function of a query's start and end and four numbers of rows of ``weights`` (rows by bins): the sums w, x, y, z of these rows
    over the bins [lo, hi) that the query overlaps; 0 for a negative number."""
    a, z = np.argsort(lo, kind="stable"), np.argsort(hi, kind="stable")
    starts, ends = lo[a], hi[z]
    begun, ended = (np.concatenate([np.zeros((len(weights), 1), np.int64), np.cumsum(weights[:, o], 1, dtype=np.int64)], 1) for o in (a, z))

    @F.pandas_udf("w long, x long, y long, z long")
    def sums(t0: pd.Series, t1: pd.Series, w: pd.Series, x: pd.Series, y: pd.Series, z: pd.Series) -> pd.DataFrame:
        b, e = np.searchsorted(starts, t1.to_numpy(), "left"), np.searchsorted(ends, t0.to_numpy(), "right")
        rows = {k: r.to_numpy() for k, r in zip("wxyz", (w, x, y, z))}
        return pd.DataFrame({k: np.where(r < 0, 0, begun[r, b] - ended[r, e]) for k, r in rows.items()})

    return sums


def cell_sums(boxes: DataFrame, n: tuple[int, int, int], names: tuple[str, ...]) -> np.ndarray:
    """Of a grid of n cells by axis, for each element the boxes that hold it: elements 0, 2, 4 .. of an axis are cells, those between are
    faces that two cells share.  ``names`` are the columns of first and last cells.  At most 8 n n n rows come to the driver."""
    size = [2 * k for k in n]
    ends = [[(2 * F.col(names[2 * i]), 1), (2 * F.col(names[2 * i + 1]) + 1, -1)] for i in range(3)]
    corners = F.array(*(F.struct(((x * size[1] + y) * size[2] + z).cast("long").alias("at"), F.lit(a * b * c).alias("sign")) for x, a in ends[0] for y, b in ends[1] for z, c in ends[2]))
    same = boxes.groupBy(*names).agg(F.count(F.lit(1)).alias("_n"))
    rows = same.select("_n", F.inline(corners)).groupBy("at").agg(F.sum(F.col("_n") * F.col("sign")).alias("n")).collect()
    out = np.zeros(math.prod(size), np.int64)
    out[[r.at for r in rows]] = [r.n for r in rows]
    out = out.reshape(size)
    for axis in range(3):
        out = np.cumsum(out, axis)
    return out


def shared(mine: np.ndarray, its: np.ndarray) -> tuple[int, int]:
    """Of two results of ``cell_sums``: pairs for each cell that both touch, and pairs that touch a common cell, once."""
    both = mine * its
    sign = np.ones((1, 1, 1), np.int64)
    for i, k in enumerate(both.shape):
        sign = sign * np.where(np.arange(k) % 2, -1, 1).reshape([-1 if j == i else 1 for j in range(3)])
    return int(both[::2, ::2, ::2].sum()), int((both * sign).sum())


def box_sums(cells: np.ndarray) -> Callable[..., Column]:
    """A function of first and last cells (xa, xz, ya, yz, za, zz): the sum over all cells of the box."""
    upto = np.zeros([k + 1 for k in cells.shape], np.int64)
    upto[1:, 1:, 1:] = cells.cumsum(0).cumsum(1).cumsum(2)

    @F.pandas_udf("long")
    def sums(xa: pd.Series, xz: pd.Series, ya: pd.Series, yz: pd.Series, za: pd.Series, zz: pd.Series) -> pd.Series:
        ends = [((z.to_numpy() + 1, 1), (a.to_numpy(), -1)) for a, z in ((xa, xz), (ya, yz), (za, zz))]
        return pd.Series(sum(upto[x, y, z] * (a * b * c) for x, a in ends[0] for y, b in ends[1] for z, c in ends[2]))

    return sums


# ---- sets of bits ------------------------------------------------------------------------------------------------


class _Bounds:
    """The sets of a block's entries whose range meets another; ranges are closed, those of time open."""

    def __init__(self, lo: np.ndarray, hi: np.ndarray, is_open: bool = False):
        self.sides = ("right", "left") if is_open else ("left", "right")
        (self.lo, self.below), (self.hi, upto) = self._ranked(lo), self._ranked(hi)
        self.beyond = upto[-1] ^ upto

    @staticmethod
    def _ranked(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order, table = np.argsort(values, kind="stable"), np.zeros((len(values) + 1, WORDS), np.uint64)
        table[np.arange(1, len(values) + 1), order >> 6] = np.uint64(1) << (order & 63).astype(np.uint64)
        return values[order], np.bitwise_or.accumulate(table, axis=0)

    def meets(self, a: np.ndarray, z: np.ndarray) -> np.ndarray:
        out = self.beyond.take(np.searchsorted(self.hi, a, self.sides[0]), 0)
        out &= self.below.take(np.searchsorted(self.lo, z, self.sides[1]), 0)
        return out


def _blocks(left: pd.DataFrame, right: pd.DataFrame, ranges: tuple[str, ...], prune: tuple[str, ...], chunk: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, dict]]:
    """Entries of a block, some queries that may meet it, and the sets of bits of time and of each range.

    Blocks are slices of time, and of the pruned ranges, so that queries pass most of them by."""
    e = {r: (right[f"{r}_lo"].to_numpy(), right[f"{r}_hi"].to_numpy()) for r in ranges}
    q = {r: (left[f"q_{r}_lo"].to_numpy(), left[f"q_{r}_hi"].to_numpy()) for r in ranges}
    t0, t1, q0, q1 = (f[c].to_numpy() for f, c in ((right, "t0"), (right, "t1"), (left, "q_t0"), (left, "q_t1")))
    n, by = len(t0), [t0, *(e[r][0] for r in prune[:2])]
    slices = max(1, round((n / BLOCK) ** (1 / len(by))))
    order = np.arange(n)
    place = np.zeros(n, np.int64)
    for values in by:
        order = order[np.lexsort((values[order], place[order]))]
        # Equal slices of what stood together before.
        starts = np.flatnonzero(np.diff(place[order], prepend=-1))
        sizes = np.diff(starts, append=n)
        inside = np.arange(n) - np.repeat(starts, sizes)
        place[order] = place[order] * slices + inside * slices // np.repeat(sizes, sizes)
    for a in range(0, n, BLOCK):
        rows = order[a : a + BLOCK]
        near = (q0 < t1[rows].max()) & (t0[rows].min() < q1)
        for r in prune:
            near &= (q[r][0] <= e[r][1][rows].max()) & (e[r][0][rows].min() <= q[r][1])
        asked = np.flatnonzero(near)
        if not len(asked):
            continue
        time, bounds = _Bounds(t0[rows], t1[rows], True), {r: _Bounds(lo[rows], hi[rows]) for r, (lo, hi) in e.items()}
        for b in range(0, len(asked), chunk):
            i = asked[b : b + chunk]
            yield rows, i, time.meets(q0[i], q1[i]), {r: s.meets(q[r][0][i], q[r][1][i]) for r, s in bounds.items()}


def _dealt(q: DataFrame, e: DataFrame, work: Callable, schema: str, times: int = 1) -> DataFrame:
    """``work`` on queries (q_t0, q_t1, _q and more) and entries (t0, t1, _e and more) that may share time.

    Entries are dealt over parts of time by their start, and queries go to each part that reaches them; full parts, and many queries, are dealt
    over several tasks by the numbers _e and _q, which identify rows; a task holds ``times`` as many as usual."""
    r = e.agg(F.min("t0"), F.max("t0")).first()
    width = ((r[1] - r[0]) / PARTS if r[0] is not None else 0.0) or 1.0
    e = e.withColumn("_at", F.least(F.lit(PARTS - 1), F.floor((F.col("t0") - F.lit(r[0] or 0.0)) / F.lit(width))).cast("int"))
    parts = [(p[0], p[1], p[2], -(-p[3] // (ENTRIES * times))) for p in e.groupBy("_at").agg(F.min("t0"), F.max("t1"), F.count(F.lit(1))).collect()]
    known = F.broadcast(q.sparkSession.createDataFrame(parts, "_at int, _since double, _until double, _of int"))
    lots = max(1, -(-q.count() // (QUERIES * times)))
    left = q.withColumn("_lot", F.pmod(F.xxhash64("_q"), F.lit(lots))).join(known, (F.col("q_t0") < F.col("_until")) & (F.col("_since") < F.col("q_t1")))
    left = left.withColumn("_block", F.explode(F.sequence(F.lit(0), F.col("_of") - 1))).drop("_since", "_until", "_of", "_q")
    right = e.join(known.select("_at", "_of"), "_at").withColumn("_block", F.pmod(F.xxhash64("_e"), F.col("_of")).cast("int")).withColumn("_lot", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(lots - 1).cast("long")))).drop("_of", "_e")
    keys = ["_at", "_block", "_lot"]
    tasks = max(len(parts) * lots, int(q.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    left, right = left.repartition(tasks, *keys), right.repartition(tasks, *keys)

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return work(a, b)

    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(run, schema)


def counts(q: DataFrame, e: DataFrame, wanted: dict[str, tuple[tuple[str, ...], tuple[str, ...]]], weight: int = 0, keys: tuple[str, ...] = ("q_traj_id", "q_seg_id")) -> DataFrame:
    """For each query (its keys, _q, q_t0, q_t1 and, for each range r, q_r_lo and q_r_hi) the entries (_e, t0, t1, r_lo, r_hi) that share time with it, meet it in
    all of the first ranges and in none of the second: a column for each name in ``wanted``.  Rows with equal
    keys are added up; with ``weight``, its largest value, an entry counts as often as its column n says.  Queries that meet nothing are left out."""
    ranges = tuple(dict.fromkeys(r for must, none in wanted.values() for r in (*must, *none)))
    prune = tuple(r for r in ranges if all(r in must for must, _ in wanted.values()))
    bits = weight.bit_length()

    def work(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros((len(left), len(wanted)), np.int64)
        if len(left) and len(right):
            n = right["n"].to_numpy() if bits else None
            last, heavy = None, []
            for rows, i, time, met in _blocks(left, right, ranges, prune, CHUNK):
                if bits and rows is not last:
                    last, padded = rows, np.zeros(BLOCK, np.int64)
                    padded[: len(rows)] = n[rows]
                    heavy = [np.packbits(padded >> b & 1, bitorder="little").view(np.uint64) for b in range(bits)]
                for j, (must, none) in enumerate(wanted.values()):
                    kept = time.copy()
                    for r in must:
                        kept &= met[r]
                    for r in none:
                        kept &= ~met[r]
                    for b, w in enumerate(heavy or [None]):
                        total[i, j] += np.bitwise_count(kept if w is None else kept & w).sum(1, dtype=np.int64) << b
        some = total.any(1)
        return pd.DataFrame({k: left[k].to_numpy()[some] for k in keys} | {k: total[some, j] for j, k in enumerate(wanted)})

    kinds = dict(q.dtypes)
    found = _dealt(q, e, work, ", ".join([*(f"{k} {kinds[k]}" for k in keys), *(f"{k} long" for k in wanted)]))
    return found.groupBy(*keys).agg(*(F.sum(k).alias(k) for k in wanted))


def boxed(df: DataFrame, dist: float = 0.0, prefix: str = "") -> DataFrame:
    """Adds the ranges x, y and z of the box, grown by the distance."""
    return df.withColumns({f"{prefix}{c}_lo": F.least(f"{prefix}{c}0", f"{prefix}{c}1") - F.lit(float(dist)) for c in AXES} | {f"{prefix}{c}_hi": F.greatest(f"{prefix}{c}0", f"{prefix}{c}1") + F.lit(float(dist)) for c in AXES})


class _Moves:
    """Starts and velocities of segments, as the closed form reads them."""

    def __init__(self, traj: np.ndarray, t0: np.ndarray, t1: np.ndarray, start: list[np.ndarray], speed: list[np.ndarray]):
        self.traj, self.t0, self.t1, self.start, self.speed = traj, t0, t1, start, speed

    @classmethod
    def of(cls, f: pd.DataFrame, prefix: str) -> "_Moves":
        at = lambda c: f[f"{prefix}{c}"].to_numpy()
        t0, t1 = at("t0"), at("t1")
        return cls(at("traj_id"), t0, t1, [at(f"{c}0") for c in AXES], [(at(f"{c}1") - at(f"{c}0")) / (t1 - t0) for c in AXES])

    def meet(self, other: "_Moves", i: np.ndarray, j: np.ndarray, dist: float) -> tuple[np.ndarray, np.ndarray]:
        """Of pairs that come within the distance, the common start, and when they first are within it."""
        q0, e0 = self.t0[i], other.t0[j]
        b0, w, d = np.maximum(q0, e0), [], []
        for p, v, o, u in zip(self.start, self.speed, other.start, other.speed):
            v, u = v[i], u[j]
            w.append(v - u)
            d.append((p[i] + v * (b0 - q0)) - (o[j] + u * (b0 - e0)))
        qa, qb, qc = w[0] * w[0] + w[1] * w[1] + w[2] * w[2], d[0] * w[0] + d[1] * w[1] + d[2] * w[2], d[0] * d[0] + d[1] * d[1] + d[2] * d[2] - dist * dist
        later = (qa != 0) & (qc > 0)
        s0 = np.where(later, (-qb - np.sqrt(np.maximum(qb * qb - qa * qc, 0.0))) / np.where(later, qa, 1.0), 0.0)
        return b0, np.minimum(b0 + np.maximum(s0, 0.0), np.minimum(self.t1[i], other.t1[j]))


def _within(q: _Moves, e: _Moves, i: np.ndarray, j: np.ndarray, dists: tuple[float, ...]) -> list[np.ndarray]:
    """For each distance, the places of the pairs within it: the steps of ``geometry.approach_text``, in its order."""
    q0, e0 = q.t0.take(i), e.t0.take(j)
    b0, b1 = np.maximum(q0, e0), np.minimum(q.t1.take(i), e.t1.take(j))
    since, its, w, d = b0 - q0, b0 - e0, [], []
    for p, v, o, u in zip(q.start, q.speed, e.start, e.speed):
        v, u = v.take(i), u.take(j)
        w.append(v - u)
        d.append((p.take(i) + v * since) - (o.take(j) + u * its))
    qa, qb, far = w[0] * w[0] + w[1] * w[1] + w[2] * w[2], d[0] * w[0] + d[1] * w[1] + d[2] * w[2], d[0] * d[0] + d[1] * d[1] + d[2] * d[2]
    long, square = b1 - b0, qb * qb
    # Every step is monotone, rounding too: what a distance finds, a larger one finds.  So a smaller one looks only at what that found.
    out, at = {}, None
    for x in sorted(dists, reverse=True):
        qc = far - x * x
        disc = square - qa * qc
        # Near at the start: both roots are on their sides of 0.  Far, and not coming nearer: neither is above 0, but for roots that round to it.
        found = qc <= 0
        k = np.flatnonzero(~found & (disc >= 0) & (qa != 0) & ((qb < 0) | (disc >= 0.999 * square)))
        a, b, root = qa[k], -qb[k], np.sqrt(disc[k])
        found[k] = np.maximum(0.0, (b - root) / a) <= np.minimum(long[k], (b + root) / a)
        found = np.flatnonzero(found)
        at = out[x] = found if at is None else at[found]
        qa, qb, far, long, square = (v[found] for v in (qa, qb, far, long, square))
    return [out[x] for x in dists]


def _groups(points: np.ndarray, size: int) -> list[np.ndarray]:
    """Rows in groups of at most ``size``, by halves of the widest axis."""
    out, todo = [], [np.arange(len(points))]
    while todo:
        rows = todo.pop()
        if len(rows) <= size:
            out.append(rows)
            continue
        p = points[rows]
        half = size * -(-len(rows) // (2 * size))
        order = np.argpartition(p[:, np.ptp(p, 0).argmax()], half)
        todo += [rows[order[half:]], rows[order[:half]]]
    return out


class _Pieces:
    """Segments in one slice of time: places at its start (also where they are not there yet), speeds, and boxes; those that move much
    further than others at the end of each group, or in groups of their own."""

    def __init__(self, m: _Moves, rows: np.ndarray, since: float, width: float, fast: float, size: int, split: Callable[[np.ndarray, int], list[np.ndarray]] = _groups):
        v = np.stack([a[rows] for a in m.speed], 1)
        u0, u1 = m.t0[rows] - since, m.t1[rows] - since
        at = np.stack([a[rows] for a in m.start], 1) - v * u0[:, None]
        a, z = at + v * np.maximum(u0, 0.0)[:, None], at + v * np.minimum(u1, width)[:, None]
        moves = width * np.abs(v).sum(1)
        sets = [np.flatnonzero(moves <= fast), np.flatnonzero(moves > fast)]
        groups = [s[g] for s in sets if len(s) for g in split((a[s] + z[s]) / 2, size)]
        order = np.concatenate(groups)
        self.ends = np.cumsum([len(g) for g in groups])
        self.begins = np.concatenate([[0], self.ends[:-1]])
        self.rows, self.at, self.v, self.u0, self.u1, self.moves = rows[order], at[order], v[order], u0[order], u1[order], moves[order]
        self.t0, self.t1, self.traj = m.t0[self.rows], m.t1[self.rows], m.traj[self.rows]
        self.fast, self.old = self.moves > fast, self.u0 < 0
        self.lo, self.hi = np.minimum(a, z)[order], np.maximum(a, z)[order]
        self.low, self.high = np.minimum.reduceat(self.lo, self.begins), np.maximum.reduceat(self.hi, self.begins)

    def inside(self, group: int) -> np.ndarray:
        return np.arange(self.begins[group], self.ends[group])

    def close(self, low: np.ndarray, high: np.ndarray, dist: float) -> np.ndarray:
        """Pieces whose boxes are within the distance of a box, slow ones first."""
        def near(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
            gap = np.maximum(0.0, np.maximum(lo - high, low - hi))
            return np.flatnonzero((gap * gap).sum(1) <= dist * dist)

        groups = near(self.low, self.high)
        if not len(groups):
            return groups
        some = np.concatenate([self.inside(g) for g in groups])
        return some[near(self.lo[some], self.hi[some])]

    def factors(self, rows: np.ndarray, centre: np.ndarray, width: float) -> tuple:
        """The longest way that one has to look from the centre, and places, speeds, start and end inside the slice, and the latest start and first end."""
        p, v = self.at[rows] - centre, self.v[rows]
        scale = float((np.sqrt((p * p).sum(1)) + width * np.sqrt((v * v).sum(1))).max())
        return scale, p, v, np.maximum(self.u0[rows], 0.0), np.minimum(self.u1[rows], width), self.t0[rows].max(), self.t1[rows].min()


def _slices(q: _Moves, e: _Moves, dist: float) -> np.ndarray:
    """Edges of slices of time in which the mean entry moves not much further than the distance."""
    lo, hi = max(q.t0.min(), e.t0.min()), min(q.t1.max(), e.t1.max())
    lasts = e.t1 - e.t0
    moved = max(float(np.mean(np.abs(v) * lasts)) for v in e.speed)
    parts = int(min(MOST_PARTS, max(1, round(PARTS_PER_REACH * moved / dist)))) if dist > 0 else MOST_PARTS
    width = max(float(lasts.mean()) / parts, (hi - lo) / MOST_SLICES)
    return lo + width * np.arange(max(1, math.ceil((hi - lo) / width)) + 1)


def _found(left: pd.DataFrame, right: pd.DataFrame, dists: tuple[float, ...]) -> Iterator[tuple[np.ndarray, np.ndarray, list[np.ndarray]]]:
    """Some queries, some entries, and for each distance the matrix of their pairs that are within it: each pair of other trajectories once, in the slice
    of time in which it first is.

    Groups of queries and what comes near their boxes are looked at as matrices: the squared distance is a parabola whose coefficients are products
    of matrices.  Pairs that rounding could decide are looked at once more, by the steps of SQL."""
    q, e = _Moves.of(left, "q_"), _Moves.of(right, "")
    far = max(dists)
    edges = _slices(q, e, far)
    for since, until in zip(edges[:-1], edges[1:]):
        i, j = (np.flatnonzero((m.t0 < until) & (m.t1 > since)) for m in (q, e))
        if not len(i) or not len(j):
            continue
        width = until - since
        fast = 8 * far + 4 * width * sum(float(np.median(np.abs(v[j]))) for v in e.speed)
        a, b = _Pieces(q, i, since, width, fast, MINE), _Pieces(e, j, since, width, fast, ITS)
        for g in range(len(a.ends)):
            x, low, high = a.inside(g), a.low[g], a.high[g]
            every, centre = b.close(low, high, far + 1e-9 * (far + np.abs([low, high]).max())), (low + high) / 2
            mine = a.factors(x, centre, width)
            for some in (every[~b.fast[every]], every[b.fast[every]]):
                for k in range(0, len(some), RUN):
                    y = some[k : k + RUN]
                    yield a.rows[x], b.rows[y], _matrix(q, e, a, b, x, y, mine, b.factors(y, centre, width), edges, since, dists)


def _slack(scale: float, dist: float, kind: type) -> float:
    """Above what rounding can do to a squared distance: to its coefficients, and by the root of that to a speed that is nearly 0."""
    one = 24 * float(np.finfo(kind).eps)
    return one * scale * scale + math.sqrt(one) * dist * scale


def _matrix(q: _Moves, e: _Moves, a: _Pieces, b: _Pieces, x: np.ndarray, y: np.ndarray, mine: tuple, its: tuple, edges: np.ndarray, since: float, dists: tuple[float, ...]) -> list[np.ndarray]:
    far, scale = max(dists), mine[0] + its[0]
    kind = np.float32 if _slack(scale, far, np.float32) < far * far / 8 else np.float64
    (p, v, p0, p1), (o, u, o0, o1) = ([c.astype(kind) for c in f[1:5]] for f in (mine, its))
    n, side = lambda f, g: (f * g).sum(1, keepdims=True), lambda *f: np.concatenate(f, 1)
    one, ones = np.ones((len(x), 1), kind), np.ones((len(y), 1), kind)
    qa = side(v, n(v, v), one) @ side(-2 * u, ones, n(u, u)).T
    qb = side(p, v, n(p, v), one) @ side(-2 * u, -2 * o, 2 * ones, 2 * n(o, u)).T
    qc = side(p, n(p, p), one) @ side(-2 * o, ones, n(o, o)).T
    # The time of the nearest approach in the common part of the slice; where both move alike any time will do.
    np.maximum(qa, np.finfo(kind).tiny, out=qa)
    with np.errstate(over="ignore"):
        s = qb / qa
    s *= kind(-0.5)
    for clamp, f, g in ((np.maximum, p0, o0), (np.minimum, p1, o1)):
        clamp(s, g, out=s)
        if (f != g[0]).any() or (g != g[0]).any():
            clamp(s, f[:, None], out=s)
    near = qa
    near *= s
    near += qb
    near *= s
    near += qc
    common = a.traj[x][:, None] != b.traj[y]
    if max(mine[5], its[5]) >= min(mine[6], its[6]):
        common &= a.t0[x][:, None] < b.t1[y]
        common &= b.t0[y] < a.t1[x][:, None]
    before, out = a.old[x].any() and b.old[y].any(), []
    for d in dists:
        slack = _slack(scale, d, kind)
        low, high = kind(d * d - slack), kind(d * d + slack)
        maybe = near <= high
        maybe &= common
        if not maybe.any():
            out.append(maybe)
            continue
        sure = near <= low
        sure &= maybe
        if before:
            old = a.old[x][:, None] & b.old[y]
            began = qc <= high
            began &= old
            sure &= ~began
            began &= qc <= low
            maybe &= ~began
        maybe ^= sure
        r, c = np.divmod(np.flatnonzero(maybe), len(y))
        if len(r):
            i, j = a.rows[x[r]], b.rows[y[c]]
            (found,) = _within(q, e, i, j, (d,))
            b0, first = q.meet(e, i[found], j[found], d)
            at = np.maximum(np.searchsorted(edges, first, "left"), np.searchsorted(edges, b0, "right"))
            found = found[np.clip(at, 1, len(edges) - 1) == np.searchsorted(edges, since, "right")]
            sure[r[found], c[found]] = True
        out.append(sure)
    return out


def _sides(q: DataFrame, d: DataFrame, dists: tuple[float, ...]) -> tuple[DataFrame, DataFrame]:
    qs = boxed(as_queries(q), max(dists), "q_").withColumn("_q", F.xxhash64("q_traj_id", "q_seg_id"))
    return qs, boxed(entries_of(d)).withColumn("_e", F.xxhash64("traj_id", "seg_id"))


def reached(q: DataFrame, d: DataFrame, dists: tuple[float, ...]) -> DataFrame:
    """dist, entry_hits, query_hits, results: at each distance the entries that some query comes near, the queries that find something, and the
    pairs; distances without any are left out.  Each pair is looked at once."""
    def work(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        seen = [np.zeros(len(f), np.int64) for f in (right, left)]
        total = [0] * len(dists)
        if len(left) and len(right):
            for i, j, found in _found(left, right, dists):
                for k, f in enumerate(found):
                    total[k] += np.count_nonzero(f)
                    seen[0][j[f.any(0)]] |= 1 << k
                    seen[1][i[f.any(1)]] |= 1 << k
        out = [pd.DataFrame({"what": [2], "a": [0], "b": [0], "seen": [0]} | {f"n{k}": [n] for k, n in enumerate(total)})]
        for what, (f, prefix) in enumerate(((right, ""), (left, "q_"))):
            some = np.flatnonzero(seen[what])
            out.append(pd.DataFrame({"what": what, "a": f[f"{prefix}traj_id"].to_numpy()[some], "b": f[f"{prefix}seg_id"].to_numpy()[some], "seen": seen[what][some]} | {f"n{k}": 0 for k in range(len(dists))}))
        return pd.concat(out)

    schema = "what int, a long, b long, seen long, " + ", ".join(f"n{k} long" for k in range(len(dists)))
    each = _dealt(*_sides(q, d, dists), work, schema, TOGETHER).groupBy("what", "a", "b").agg(F.bit_or("seen").alias("seen"), *(F.sum(f"n{k}").alias(f"n{k}") for k in range(len(dists))))
    bit = lambda what, k: F.count_if((F.col("what") == what) & (F.col("seen").bitwiseAND(1 << k) != 0))
    one = each.agg(*(f for k in range(len(dists)) for f in (bit(0, k).alias(f"e{k}"), bit(1, k).alias(f"q{k}"), F.coalesce(F.sum(f"n{k}"), F.lit(0)).alias(f"r{k}"))))
    rows = F.array(*(F.struct(F.lit(float(x)).alias("dist"), F.col(f"e{k}").alias("entry_hits"), F.col(f"q{k}").alias("query_hits"), F.col(f"r{k}").alias("results")) for k, x in enumerate(dists)))
    return one.select(F.inline(rows)).where("results > 0")


def results(q: DataFrame, d: DataFrame, dist: float, more: dict[str, Callable] | None = None, keep: Callable[[DataFrame, str], DataFrame] | None = None) -> DataFrame:
    """One row: how many pairs are within the distance, as results, and the sums of further whole numbers of these pairs.

    ``keep`` adds columns to either side (with its prefix), and ``more`` names functions of two rows of columns, query's and entry's."""
    more = more or {}
    qs, es = _sides(q, d, (dist,))
    if keep is not None:
        qs, es = keep(qs, "q_"), keep(es, "")

    def work(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        total = dict.fromkeys(["results", *more], 0)
        if len(left) and len(right):
            mine, its = ({c: f[c].to_numpy() for c in f.columns} for f in (left, right))
            for i, j, (found,) in _found(left, right, (dist,)):
                total["results"] += np.count_nonzero(found)
                if more:
                    x, y = np.nonzero(found)
                    i, j = i[x], j[y]
                    for k, f in more.items():
                        total[k] += int(f(lambda c: mine[c][i], lambda c: its[c][j]).sum())  # noqa: B023
        return pd.DataFrame({k: [v] for k, v in total.items()})

    found = _dealt(qs, es, work, ", ".join(f"{k} long" for k in ["results", *more]), TOGETHER)
    return found.agg(*(F.coalesce(F.sum(k), F.lit(0)).cast("long").alias(k) for k in ["results", *more]))
