"""The closed form of contact against worked cases, dense sampling, and its Arrow twin."""

from __future__ import annotations

import math
import random

import pytest
from pyspark.sql import functions as F

from trajdist.functions import geometry
from trajdist.operators import brute
from trajdist.sources.tables import SEGMENT


def seg(traj, t0, p0, t1, p1, n=0):
    return (traj, n, float(t0), *map(float, p0), float(t1), *map(float, p1))


def found(spark, q, e, d, **options):
    qs, ds = spark.createDataFrame([q], SEGMENT), spark.createDataFrame([e], SEGMENT)
    rows = geometry.within(brute.candidates(qs, ds), d, **options).collect()
    return [(round(r.lo, 9), round(r.hi, 9)) for r in rows]


CASES = [
    ("parallel", seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 0, (0, 3, 0), 10, (10, 3, 0)), 3, [(0, 10)]),
    ("too far", seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 0, (0, 3, 0), 10, (10, 3, 0)), 2.9, []),
    ("head on", seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 0, (10, 0, 0), 10, (0, 0, 0)), 2, [(4, 6)]),
    ("tangent", seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 0, (5, 2, 0), 10, (5, 2, 0)), 2, [(5, 5)]),
    ("part of the time", seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 6, (5, 0, 0), 20, (5, 0, 0)), 2, [(6, 7)]),
    ("one instant", seg(1, 0, (0, 0, 0), 5, (5, 0, 0)), seg(2, 5, (5, 0, 0), 10, (5, 0, 0)), 100, []),
    ("fixed place", seg(1, 0, (0, 0, 0), 10, (0, 0, 0)), seg(2, 0, (-5, 0, 0), 10, (5, 0, 0)), 1, [(4, 6)]),
]


@pytest.mark.parametrize("name,q,e,d,expected", CASES, ids=[c[0] for c in CASES])
@pytest.mark.parametrize("stable", [False, True])
def test_worked_cases(spark, name, q, e, d, expected, stable):
    assert found(spark, q, e, d, stable=stable) == [tuple(map(float, x)) for x in expected]


def test_against_sampling_and_symmetry(spark):
    rng = random.Random(5)
    point = lambda: [rng.uniform(-5, 5) for _ in range(3)]
    qs = [seg(1, 0, point(), rng.uniform(3, 9), point(), i) for i in range(25)]
    es = [seg(2, rng.uniform(-3, 4), point(), rng.uniform(5, 12), point(), i) for i in range(25)]
    a, b = spark.createDataFrame(qs, SEGMENT), spark.createDataFrame(es, SEGMENT)
    got = {(r.q_seg, r.seg_id): (r.lo, r.hi) for r in brute.search(a, b, 4.0).collect()}
    back = {(r.seg_id, r.q_seg): (r.lo, r.hi) for r in brute.search(b, a, 4.0).collect()}
    assert got.keys() == back.keys()

    def at(s, t):
        f = (t - s[2]) / (s[6] - s[2])
        return [s[3 + i] + f * (s[7 + i] - s[3 + i]) for i in range(3)]

    for i, q in enumerate(qs):
        for j, e in enumerate(es):
            lo, hi = max(q[2], e[2]), min(q[6], e[6])
            for k in range(1, 200):
                t = lo + (hi - lo) * k / 200
                gap = math.dist(at(q, t), at(e, t))
                if abs(gap - 4.0) > 1e-3 and lo < hi:
                    inside = (i, j) in got and got[i, j][0] <= t <= got[i, j][1]
                    assert inside == (gap < 4.0)


def test_min_distance_and_clip_and_splice(spark):
    q, e = seg(1, 0, (0, 0, 0), 10, (10, 0, 0)), seg(2, 0, (5, 2, 0), 10, (5, 2, 0))
    pairs = brute.candidates(spark.createDataFrame([q], SEGMENT), spark.createDataFrame([e], SEGMENT))
    r = geometry.min_distance(pairs).first()
    assert (r.d_min, r.t_min) == (2.0, 5.0)
    d = spark.createDataFrame([q], SEGMENT)
    c = geometry.clip(d, 2, 4).first()
    assert (c.t0, c.x0, c.t1, c.x1) == (2.0, 2.0, 4.0, 4.0)
    parts = geometry.splice(d, 4).orderBy("part").collect()
    assert [p.x1 for p in parts] == [2.5, 5.0, 7.5, 10.0] and parts[0].x0 == 0.0


def test_hausdorff(spark):
    p = spark.sql("SELECT array(named_struct('x', 0D, 'y', 0D, 'z', 0D)) AS p, array(named_struct('x', 3D, 'y', 4D, 'z', 0D), named_struct('x', 0D, 'y', 0D, 'z', 1D)) AS o")
    assert p.select(geometry.hausdorff().alias("h")).first().h == 5.0


def test_boxes(spark):
    d = geometry.box(spark.createDataFrame([seg(1, 0, (4, 0, 1), 2, (1, 3, 1))], SEGMENT), 0.5).first()
    assert (d.xlo, d.xhi, d.ylo, d.yhi, d.zlo, d.zhi) == (0.5, 4.5, -0.5, 3.5, 0.5, 1.5)
    assert spark.range(1).select(geometry.rounded(F.lit(1.23456789)).alias("x")).first().x == 1.234568
