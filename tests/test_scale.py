"""Queries whose work grows with rows and results, not with all pairs: the plainer way is taken away, or its rows are counted."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from trajdist.operators import brute, timebins
from trajdist.operators.index import as_queries, overlapping
from trajdist.plans import registry
from trajdist.sources.tables import SEGMENT

from .test_registry import plain

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()


def same_as_sql(spark, duck, sf_dir, name):
    got = QUERIES[name](spark, sf_dir)
    columns = sorted(got.columns)
    want = duck.execute(ORACLES[name]).df()[columns]
    assert sorted(tuple(plain(r[c]) for c in columns) for r in got.collect()) == sorted(tuple(plain(v) for v in r) for r in want.itertuples(index=False, name=None))


def refuse(*_a, **_k):
    raise AssertionError("pairs are made")


@pytest.mark.parametrize("name", ["ops_o8_interval_join", "measure_all_pairs_dense"])
def test_overlaps_are_counted_without_pairs(spark, duck, sf_dir, monkeypatch, name):
    monkeypatch.setattr(timebins, "candidates", refuse)
    monkeypatch.setattr(brute, "candidates", refuse)
    same_as_sql(spark, duck, sf_dir, name)


def test_overlapping_by_key_with_ties(spark):
    """Touching times do not overlap; repeated rows count as often as they are there; other keys do not take part."""
    row = lambda k, i, a, z: (k, i, float(a), 0.0, 0.0, 0.0, float(z), 0.0, 0.0, 0.0)
    d = spark.createDataFrame([row(1, 0, 0, 2), row(1, 0, 0, 2), row(1, 1, 2, 3), row(2, 0, 1, 9), row(3, 0, 5, 6)], SEGMENT)
    q = as_queries(d)
    for keys in ((), ("traj_id",)):
        got = overlapping(q.withColumn("traj_id", F.col("q_traj_id")), d, keys)
        pairs = q.crossJoin(d).where("q_t0 < t1 AND t0 < q_t1").where("q_traj_id = traj_id" if keys else "true")
        want = pairs.groupBy("q_traj_id", "q_seg_id").count().collect()
        assert {(r.q_traj_id, r.q_seg_id): r.n for r in got.groupBy("q_traj_id", "q_seg_id").agg(F.sum("n").alias("n")).collect()} == {(r.q_traj_id, r.q_seg_id): r["count"] for r in want}


@pytest.mark.parametrize("dedup", ["owner", "early", "late"])
def test_cells_meet_in_parts_of_time_and_shuffle_no_pairs(spark, monkeypatch, dedup):
    """Segments at one place, each in a time of its own: a pair of other times is not made, and repeats need no shuffle."""
    from trajdist.functions import geometry
    from trajdist.operators import cells

    rows = [(i, 0, float(i % 200), 0.0, 0.0, float(i % 7), float(i % 200 + 1), 1.0, 1.0, float(i % 7)) for i in range(400)] + [(1000, 0, 0.0, 50.0, 50.0, 50.0, 1.0, 50.0, 50.0, 50.0)]
    d = spark.createDataFrame(rows, SEGMENT)
    monkeypatch.setattr(geometry, "repeated", refuse)
    index = cells.build(d, 10)
    got = cells.search(d, index, 9.0, dedup)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, brute.search(d, d, 9.0).collect()))
    assert cells.meeting(d, index, 9.0).count() < 401 * 20


@pytest.mark.parametrize(("name", "table"), [("ops_o32_recursive_cte", "lineitem"), ("ops_s4_generated", "customer"), ("stream_st1_rate", "events")])
def test_a_given_table_is_read(spark, duck, sf_dir, monkeypatch, name, table):
    from trajdist.plans import relational
    from trajdist.streaming import streams

    read = []
    for module in (relational, streams):
        monkeypatch.setattr(module, "table", lambda s, d, n, f=module.table: read.append(n) or f(s, d, n))
    same_as_sql(spark, duck, sf_dir, name)
    assert table in read


def test_bins_meet_in_cells(spark):
    """Entries of one time, spread in space: a query meets those around it, each once."""
    rows = [(i, 0, 0.0, float(i), float(i % 90), 0.0, 1.0, float(i) + 1, float(i % 90), 1.0) for i in range(600)]
    d = spark.createDataFrame(rows, SEGMENT)
    index = timebins.build(d, 4)
    assert timebins.near(d, index, 5.0).count() < 600 * 60
    assert sorted(map(tuple, timebins.search(d, index, 5.0).collect())) == sorted(map(tuple, brute.search(d, d, 5.0).collect()))


def test_hit_ratio_counts_overlaps_without_pairs(spark, duck, sf_dir, monkeypatch):
    monkeypatch.setattr(timebins, "candidates", lambda *a, f=timebins.candidates, **k: f(*a, **k) if "dist" in k else refuse())
    same_as_sql(spark, duck, sf_dir, "measure_hit_ratio_dense")


def without_pairs(monkeypatch):
    """Takes away every way that makes a row for each pair, or for each query and bin."""
    from trajdist.operators import cells, packed_tree, slabs

    for module, name in ((timebins, "candidates"), (timebins, "near"), (timebins, "overlaps"), (cells, "candidates"), (cells, "meeting"), (slabs, "candidates"), (slabs, "every_pair"), (packed_tree, "frontiers"), (brute, "candidates")):
        monkeypatch.setattr(module, name, refuse)


COUNTED = [
    "measure_duplicates_dense",
    "measure_duplicates_event",
    "measure_duplicates_walk",
    "measure_wasted_event",
    "measure_within_dense",
    "measure_balance_walk",
    "measure_balance_event",
    "measure_hit_ratio_dense",
    "measure_hit_ratio_event",
    "measure_interactions_event",
    "measure_interactions_walk",
    "measure_within_walk",
]


@pytest.mark.parametrize("name", COUNTED)
def test_measures_count_without_pairs(spark, duck, sf_dir, monkeypatch, name):
    without_pairs(monkeypatch)
    same_as_sql(spark, duck, sf_dir, name)


def test_sets_of_bits_count_like_pairs(spark, monkeypatch):
    """More entries than a block, and than a task holds; repeated rows and keys, touching ends, several parts; also none at all."""
    from trajdist.operators import tally

    monkeypatch.setattr(tally, "ENTRIES", 3000)
    monkeypatch.setattr(tally, "QUERIES", 200)
    rows = [(i % 90, i // 90, float(i % 40), float(i % 31), float(i % 7), float(i % 5), float(i % 40 + 1 + i % 3), float(i % 31 + 2), float(i % 7 + 1), float(i % 5)) for i in range(9000)]
    d = spark.createDataFrame(rows + rows[:20], SEGMENT)
    q = d.where("traj_id % 30 = 0").limit(250)
    for x in (1.0, 4.0):
        assert tally.results(q, d, x).first().results == brute.search(q, d, x).count()
    got = tally.reached(q, d, (1.0, 4.0)).collect()
    for r in got:
        want = brute.search(q, d, r.dist).agg(F.countDistinct("traj_id", "seg_id"), F.countDistinct("q_traj", "q_seg"), F.count(F.lit(1))).first()
        assert (r.entry_hits, r.query_hits, r.results) == tuple(want)
    assert len(got) == 2
    assert tally.results(q, d.where("false"), 4.0).first().results == 0 and tally.reached(q.where("false"), d, (1.0,)).count() == 0


def test_shared_cells_and_slabs_are_counted_from_sums(spark):
    """Boxes of many cells and slabs: with repeats and once, as from the pairs."""
    from trajdist.operators import cells, slabs

    rows = [(i, 0, float(i % 9), float(i * 7 % 50), float(i * 3 % 20), 0.0, float(i % 9 + 3), float(i * 5 % 50), float(i * 11 % 20), 0.0) for i in range(120)]
    d = spark.createDataFrame(rows, SEGMENT)
    index = cells.build(d, 6)
    pairs = cells.candidates(d, index, 2.0)
    assert cells.shared(d, index, 2.0) == (pairs.count(), cells.owned(pairs, index.grid).count())
    s = slabs.build(d, 5, 4)
    every = slabs.every_pair(d, s, 2.0, "multi")
    assert tuple(slabs.multi_counts(d, s, 2.0).agg(F.sum("repeats"), F.sum("once")).first()) == (every.count(), every.select("q_traj_id", "traj_id").distinct().count())
    assert sorted(map(tuple, slabs.schedule(d, s, 2.0).collect()), key=str) == sorted(map(tuple, slabs._again(slabs._planned(d, s, 2.0).drop("lists")).collect()), key=str)


def test_lengths_of_unions():
    """Overlapping, touching and equal intervals of several keys, against one key and one interval at a time."""
    import numpy as np

    from trajdist.plans.relational import union_lengths

    r = np.random.default_rng(3)
    keys, lo = r.integers(-3, 40, 700), r.integers(0, 50, 700) / 4
    hi = lo + r.integers(0, 9, 700) / 4
    want = {}
    for k in set(keys.tolist()):
        total, end = 0.0, float("-inf")
        for a, z in sorted((a, z) for i, a, z in zip(keys, lo, hi) if i == k):
            total += max(0.0, z - max(a, end))
            end = max(end, z)
        want[k] = total
    got = union_lengths(keys, lo, hi)
    assert dict(zip(*(a.tolist() for a in got))) == want and sorted(want) == got[0].tolist()


def test_aggregate_function_is_called_for_each_query_trajectory(spark, sf_dir):
    import re

    df = QUERIES["ops_o44_aggregate_udf"](spark, sf_dir)
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert re.findall(r"Aggregate \[([^\]]*)\]", plan)[0].count("#") == 1


def test_sql_text_meets_in_cells(spark, sf_dir, monkeypatch):
    """At distances below and above the one that the cells are made for; the join makes few of the pairs of the bins."""
    from trajdist.plans import sqlapi
    from trajdist.plans.scenarios import bounded_walk, queries_of
    from trajdist.plans.searches import shown
    from trajdist.session import kept

    d = kept(bounded_walk(spark, 1500, 4, 5, 0.02))
    monkeypatch.setattr(sqlapi, "segments", lambda *_: d)
    sqlapi.register(spark, sf_dir, reach={"dense": 3.0})
    for dist in (1.0, 3.0, 8.0):
        want = shown(brute.search(queries_of(d, "dense"), d, dist))
        got = spark.sql(sqlapi.search_text("dense", dist, 48))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    pairs = lambda q, keys: spark.sql(f"SELECT count(*) FROM {q} JOIN binned_dense USING ({keys})").first()[0]
    assert 0 < 3 * pairs(sqlapi._asked("dense", "3.0D"), "bin, h") < pairs("query_dense", "bin")


def test_most_pairs_are_decided_without_roots(monkeypatch):
    """The closed form as it stands, on pairs that rest, touch, part and come nearer, at distances in any order."""
    import numpy as np

    from trajdist.operators import tally

    r, n = np.random.default_rng(5), 20_000

    def moves():
        t0 = r.integers(0, 3, 300) / 2
        return tally._Moves(np.arange(300), t0, t0 + 1 + r.integers(0, 2, 300), [r.integers(-8, 8, 300).astype(float) for _ in "xyz"], [r.integers(-2, 2, 300) / 2 for _ in "xyz"])

    q, e, i, j = moves(), moves(), r.integers(0, 300, n), r.integers(0, 300, n)
    b0, b1 = np.maximum(q.t0[i], e.t0[j]), np.minimum(q.t1[i], e.t1[j])
    i, j = i[b0 < b1], j[b0 < b1]
    b0, b1 = np.maximum(q.t0[i], e.t0[j]), np.minimum(q.t1[i], e.t1[j])
    w = [v[i] - u[j] for v, u in zip(q.speed, e.speed)]
    d = [(p[i] + v[i] * (b0 - q.t0[i])) - (o[j] + u[j] * (b0 - e.t0[j])) for p, v, o, u in zip(q.start, q.speed, e.start, e.speed)]
    qa, qb, far = (x[0] * y[0] + x[1] * y[1] + x[2] * y[2] for x, y in ((w, w), (d, w), (d, d)))
    dists, want = (5.0, 1.0, 12.0), []
    with np.errstate(all="ignore"):
        for x in dists:
            qc = far - x * x
            root = np.sqrt(qb * qb - qa * qc)
            want.append(np.where(qa == 0, qc <= 0, np.maximum(0, (-qb - root) / qa) <= np.minimum(b1 - b0, (-qb + root) / qa)))
    sqrt, rooted = np.sqrt, []
    monkeypatch.setattr(np, "sqrt", lambda a: rooted.append(len(a)) or sqrt(a))
    got = tally._within(q, e, i, j, dists)
    assert [g.tolist() for g in got] == [np.flatnonzero(x).tolist() for x in want] and all(len(g) for g in got)
    assert (qa == 0).any() and 2 * sum(rooted) < len(i)


def test_pairs_of_long_moves_are_counted_once_in_slices_of_time(monkeypatch):
    """Few slices or many, small groups, some very fast, rest and ties on the edges of slices: the pairs of the closed form, each once; and
    far fewer places of matrices than pairs whose boxes meet."""
    import numpy as np
    import pandas as pd

    from trajdist.operators import tally

    r = np.random.default_rng(7)

    def side(n, prefix):
        t0 = r.integers(0, 160, n) / 4.0
        lasts = np.where(r.random(n) < 0.02, 1 / 1024, r.integers(1, 80, n) / 4.0)
        f = {"traj_id": r.integers(0, 50, n), "seg_id": np.arange(n), "t0": t0, "t1": t0 + lasts}
        for c in "xyz":
            a, still = r.integers(0, 100, n).astype(float), r.random(n) < 0.1
            f |= {f"{c}0": a, f"{c}1": np.where(still, a, r.integers(0, 100, n).astype(float))}
        return pd.DataFrame({f"{prefix}{k}": v for k, v in f.items()})

    left, right, dists = side(500, "q_"), side(2500, ""), (4.0, 10.0, 1.0)
    q, e = tally._Moves.of(left, "q_"), tally._Moves.of(right, "")
    shared = (q.t0[:, None] < e.t1) & (e.t0 < q.t1[:, None]) & (q.traj[:, None] != e.traj)
    i, j = np.nonzero(shared)
    want = [set(zip(i[k].tolist(), j[k].tolist())) for k in tally._within(q, e, i, j, dists)]
    gap = [np.maximum(np.minimum(left[f"q_{c}0"], left[f"q_{c}1"]).to_numpy()[i] - np.maximum(right[f"{c}0"], right[f"{c}1"]).to_numpy()[j], np.minimum(right[f"{c}0"], right[f"{c}1"]).to_numpy()[j] - np.maximum(left[f"q_{c}0"], left[f"q_{c}1"]).to_numpy()[i]) for c in "xyz"]
    boxes = int((np.max(gap, 0) <= 10.0).sum())
    for parts, mine, its, run in ((1, 128, 256, 512), (16, 4, 16, 64), (16, 1, 8, 8)):
        for name, value in (("MOST_PARTS", parts), ("MINE", mine), ("ITS", its), ("RUN", run)):
            monkeypatch.setattr(tally, name, value)
        got, places = [[] for _ in dists], 0
        for a, b, found in tally._found(left, right, dists):
            places += found[0].size
            for k, f in enumerate(found):
                x, y = np.nonzero(f)
                got[k] += zip(a[x].tolist(), b[y].tolist())
        assert [len(g) for g in got] == [len(set(g)) for g in got] and [set(g) for g in got] == want and all(want)
    assert places < boxes


def test_cells_of_events_make_no_pairs(spark, duck, sf_dir, monkeypatch):
    without_pairs(monkeypatch)
    same_as_sql(spark, duck, sf_dir, "search_cell_event")


def test_moves_through_cells_are_found_once(spark, monkeypatch):
    """Long and short moves, rest, repeated rows, meetings at the edges of slices and of segments; tasks with a share of the rows, one or many windows."""
    import numpy as np

    from trajdist.operators import cells, moving

    r, n = np.random.default_rng(11), 900
    t0 = r.integers(0, 160, n) / 4.0
    lasts = np.where(r.random(n) < 0.05, 1 / 1024, r.integers(1, 80, n) / 4.0)
    a = r.integers(0, 100, (n, 3)).astype(float)
    z = np.where(r.random((n, 1)) < 0.1, a, r.integers(0, 100, (n, 3)))
    rows = [(int(k), i, t, *p, t + m, *o) for i, (k, t, m, p, o) in enumerate(zip(r.integers(0, 50, n).tolist(), t0.tolist(), lasts.tolist(), a.tolist(), z.tolist()))]
    d = spark.createDataFrame(rows + rows[:25] + [(1001, *row[1:]) for row in rows[:99]], SEGMENT)
    q = d.where("traj_id % 5 = 0")
    index = cells.build(d, 10)
    monkeypatch.setattr(cells, "meeting", refuse)
    for window, entries, queries, dist in ((10_000, 10_000, 10_000, 10.0), (20, 60, 9, 10.0), (1, 10_000, 10_000, 0.0), (50, 500, 500, 60.0)):
        for name, value in (("WINDOW", window), ("ENTRIES", entries), ("QUERIES", queries)):
            monkeypatch.setattr(moving, name, value)
        want = brute.search(q, d, dist).collect()
        assert sorted(map(tuple, cells.search(q, index, dist).collect())) == sorted(map(tuple, want)) and want
    assert cells.search(q.where("false"), index, 10.0).count() == 0 and moving.crossing(index.grid, index.ext)


def test_few_pairs_of_moves_go_through_the_closed_form(monkeypatch):
    """Groups and matrices of any size find the same pairs; what is looked at closely is little more than what is found, and far less than the boxes that meet."""
    import numpy as np

    from trajdist.operators import moving, tally
    from trajdist.operators.meeting import Grid

    r = np.random.default_rng(13)

    def side(n):
        t0, p, o = r.uniform(0, 40, n), r.uniform(0, 100, (n, 3)), r.uniform(0, 100, (n, 3))
        lasts = r.exponential(10.0, n) + 1e-3
        return tally._Moves(r.integers(0, 60, n), t0, t0 + lasts, list(p.T.copy()), list(((o - p) / lasts[:, None]).T.copy())), np.arange(n), np.minimum(p, o), np.maximum(p, o)

    (q, qs, ql, qh), (e, es, el, eh) = side(600), side(3000)
    shared = (q.t0[:, None] < e.t1) & (e.t0 < q.t1[:, None]) & (q.traj[:, None] != e.traj)
    i, j = np.nonzero(shared)
    want = set(zip(*(x[tally._within(q, e, i, j, (10.0,))[0]].tolist() for x in (i, j))))
    boxes = int(((ql[i] - 10 <= eh[j]) & (el[j] <= qh[i] + 10)).all(1).sum())
    edges = 2.0 * np.arange(0, 120)
    closed, looked = moving._closed, []
    monkeypatch.setattr(moving, "_closed", lambda *x: looked.append(len(x[2])) or closed(*x))
    for sizes in ((64, 1024, 128, 1 << 14), (3, 8, 5, 40)):
        for name, value in zip(("MINE", "RUN", "ITS", "PAIRS"), sizes):
            monkeypatch.setattr(moving, name, value)
        looked.clear()
        found = [np.concatenate(c) for c in zip(*moving.matches(q, e, qs, es, edges, Grid((10, 10, 10), (0.0,) * 3, (10.0,) * 3), 10.0))]
        got = list(zip(found[1].tolist(), found[3].tolist()))
        assert len(got) == len(want) and set(got) == want
        assert sum(looked) < 1.5 * len(want) and 4 * sum(looked) < boxes
