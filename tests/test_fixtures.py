"""The worked examples: raster, cell arrays, time bins, slab arrays, and the redo trap."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from trajdist.operators import batching, cells, slabs, timebins
from trajdist.operators.index import Extents, as_queries
from trajdist.sources.tables import SEGMENT

TIMES = [(0.0, 1.7), (0.6, 1.5), (0.7, 1.3), (1.9, 3.7), (2.5, 7.5), (2.8, 4.6), (3.9, 5.5), (4.1, 5.8), (4.8, 6.2), (6.5, 9.4), (7.0, 7.8), (8.3, 11.0), (9.3, 11.5), (10.4, 12.0), (11.6, 11.9)]
# Start and end point of each of the ten segments.
POINTS = [
    ((4, 2, 3), (5, 3, 1)), ((2, 3, 4), (1, 2, 2)), ((6, 7, 9), (4, 6, 8)), ((3, 5, 4), (4, 3, 5)), ((3, 3, 1), (5, 3, 7)),
    ((3, 6, 2), (2, 3, 2)), ((8, 9, 10), (10, 9, 8)), ((5, 5, 6), (6, 4, 5)), ((8, 8, 13), (7, 7, 10)), ((0, 3, 5), (2, 6, 7)),
]


def at_times(spark, times):
    return spark.createDataFrame([(i, 0, a, 0.0, 0.0, 0.0, b, 1.0, 1.0, 1.0) for i, (a, b) in enumerate(times)], SEGMENT)


def test_time_bins(spark):
    index = timebins.build(at_times(spark, TIMES), 4, ids=True)
    got = [(r.bin, r.bin_start, r.bin_end, r.first, r.last) for r in index.directory.orderBy("bin").collect()]
    assert got == [(0, 0.0, 7.5, 0, 5), (1, 3.0, 6.2, 6, 8), (2, 6.0, 11.0, 9, 11), (3, 9.0, 12.0, 12, 14)]
    assert [r.end_cummax for r in index.directory.orderBy("bin").collect()] == [7.5, 7.5, 11.0, 12.0]
    q = spark.createDataFrame([(99, 0, 7.0, 0.0, 0.0, 0.0, 8.0, 0.0, 0.0, 0.0)], SEGMENT)
    for how in ("scan", "bounded"):
        assert sorted(r.bin for r in timebins.overlaps(as_queries(q), index.directory, index.bins, how).collect()) == [0, 2]
    plan = timebins.schedule(q, index).first()
    assert (plan.entry_min, plan.entry_max, plan.n_candidates) == (0, 11, 12)


def test_start_at_the_very_end(spark):
    d = at_times(spark, [(0.0, 12.0), (12.0, 12.0)])
    bins = timebins.Bins(4, 0.0, 3.0)
    assert [r.bin for r in timebins.assign(d, bins).orderBy("traj_id").collect()] == [0, 3]


def slab_index(spark):
    rows = [(i, 0, float(i if i < 4 else 10 + i if i < 8 else 20 + i), *map(float, a), float(i if i < 4 else 10 + i if i < 8 else 20 + i) + 0.5, *map(float, b)) for i, (a, b) in enumerate(POINTS)]
    d = spark.createDataFrame(rows, SEGMENT)
    bins = timebins.Bins(3, 0.0, 10.0)
    binned = timebins.assign(d.withColumn("eid", F.col("traj_id")), bins)
    grid = slabs.Slabs(3, (0.0, 0.0, 0.0), (4.0, 4.0, 5.0))
    look = slabs.lookup(binned, grid)
    dirs = slabs.directory(look)
    return d, slabs.SlabIndex(timebins.TimeBinIndex(binned, timebins.directory(binned, bins), bins), look, dirs, grid)


def test_slab_arrays(spark):
    _, index = slab_index(spark)
    rows = slabs.positions(index.lookup, index.directory).orderBy("axis", "pos").collect()
    arrays = [[r.eid for r in rows if r.axis == a] for a in range(3)]
    assert arrays[0] == [1, 3, 4, 5, 9, 0, 2, 3, 4, 7, 8, 6, 8]
    assert arrays[1] == [0, 1, 3, 4, 5, 9, 2, 3, 5, 7, 8, 9, 6, 8]
    assert arrays[2] == [0, 1, 3, 4, 5, 2, 3, 4, 6, 7, 9, 6, 8]
    assert all(r.pos == i for a in range(3) for i, r in enumerate(x for x in rows if x.axis == a))
    dirs = {(r.axis, r.bin, r.slab): (r.lo, r.hi) for r in index.directory.collect()}
    assert dirs[0, 1, 1] == (8, 9) and dirs[1, 1, 1] == (8, 9) and dirs[2, 1, 1] == (7, 9) and (0, 0, 2) not in dirs


def test_slab_choice_and_tie(spark):
    _, index = slab_index(spark)
    # In bins 0 and 1, slab 0 of x, slab 1 of y, slab 0 of z: 4, 4 and 5 candidates; the tie goes to x.
    q = spark.createDataFrame([(99, 0, 5.0, 1.0, 5.0, 1.0, 15.0, 2.0, 6.0, 2.0)], SEGMENT)
    plan = slabs.schedule(q, index, 0.5).first()
    assert (plan.selector, plan.slab, plan.n_candidates) == (0, 0, 4)


def test_slab_limits(spark):
    ext = Extents(10, 0, 30, (0.0, 0.0, 0.0), (12.0, 12.0, 15.0), (2.0, 3.0, 6.0), 1.0)
    assert slabs.max_v(ext) == 2
    with pytest.raises(ValueError):
        slabs.grid(ext, 3, "strict")
    assert slabs.grid(ext, 3, "clamp").v == 2 and slabs.grid(ext, 3, "allow").v == 3


def test_raster(spark):
    rows = [(1, 0, 0.0, 2.6, 1.2, 0.5, 1.0, 1.2, 3.5, 0.5), (2, 0, 0.0, 4.1, 2.1, 0.5, 1.0, 4.8, 2.9, 0.5)]
    grid = cells.Grid((5, 4, 1), (0.0, 0.0, 0.0), (1.0, 1.0, 1.0))
    got = cells.lookup(spark.createDataFrame(rows, SEGMENT), grid).collect()
    assert {r.h for r in got if r.traj_id == 1} == {5, 6, 7, 9, 10, 11} and {r.h for r in got if r.traj_id == 2} == {18}


def test_cell_arrays(spark):
    lists = {0: [2, 100, 22], 7: [100, 867, *range(2000, 2063), 400]}
    look = spark.createDataFrame([(h, e) for h, es in lists.items() for e in es], "h long, eid long")
    dirs = {r.h: (r.a_min, r.a_max, r.n) for r in cells.directory(look).collect()}
    assert dirs == {0: (0, 2, 3), 7: (3, 68, 66)}
    asked = spark.createDataFrame([(0,), (1,), (7,)], "h long").join(look, "h")
    assert asked.count() == 69 and asked.select("eid").distinct().count() == 68


def test_too_fine_grid(spark):
    rows = [(1, 0, 0.0, 0.0, 0.0, 0.0, 1.0, 9.0, 9.0, 9.0)]
    with pytest.raises(ValueError):
        cells.build(spark.createDataFrame(rows, SEGMENT), 20)


def test_redo_rounds(spark):
    need = spark.createDataFrame([(1, 0, 8), (2, 0, 8)], "q_traj long, q_seg long, demand long")
    got = batching.cell_rounds(need, 10).orderBy("round").collect()
    assert [(r.q_traj, r.round) for r in got] == [(1, 1), (2, 2)]
    one = batching.cell_rounds(spark.createDataFrame([(1, 0, 25)], "q_traj long, q_seg long, demand long"), 10).first()
    assert (one.round, one.chunks) == (1, 3)
    even = batching.cell_rounds(spark.createDataFrame([(i, 0, i) for i in range(1, 6)], "q_traj long, q_seg long, demand long"), 10).orderBy("q_traj").collect()
    assert [r["round"] for r in even] == [1, 1, 2, 3, 3]
    some = batching.cell_rounds(spark.createDataFrame([(i, 0, i) for i in (4, 5, 6, 7)], "q_traj long, q_seg long, demand long"), 10).orderBy("q_traj").collect()
    assert [r["round"] for r in some] == [1, 1, 2, 3]


def test_batches(spark):
    need = spark.createDataFrame([(i, 0, 4) for i in range(6)], "q_traj long, q_seg long, demand long")
    got = batching.by_capacity(need, 10, ["q_traj"]).orderBy("q_traj").collect()
    assert [r.batch_id for r in got] == [0, 0, 0, 1, 1, 2]


def test_running_sum_over_parts(spark):
    demands = [(i, 0, (i * 37) % 11) for i in range(20)]
    got = batching.running_sum(spark.createDataFrame(demands, "q_traj long, q_seg long, demand long"), ["demand", "q_traj"], part=3).orderBy("_i").collect()
    before = 0
    for i, (q, _, n) in enumerate(sorted(demands, key=lambda r: (r[2], r[0]))):
        assert (got[i]["_i"], got[i].q_traj, got[i]["_before"]) == (i, q, before)
        before += n
