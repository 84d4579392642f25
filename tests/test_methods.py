"""All methods give the same rows, whatever their parameters; edges; plans."""

from __future__ import annotations

import random
import re

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from trajdist.operators import batching, brute, cells, packed_tree, planner, search, slabs, timebins
from trajdist.operators.index import at_distances, by_trajectory, dense_ids
from trajdist.plans.scenarios import queries_of, segments
from trajdist.session import materialize
from trajdist.sources.tables import SEGMENT, load_by_time, save_by_time, segments_from


def key(df):
    return sorted((r.q_traj, r.q_seg, r.traj_id, r.seg_id, round(r.lo, 9), round(r.hi, 9)) for r in df.collect())


@pytest.fixture(scope="module")
def dense(spark, sf_dir):
    d = materialize(segments(spark, sf_dir, "dense"))
    q = materialize(queries_of(d, "dense").limit(60))
    return q, d, key(brute.search(q, d, 3.1))


METHODS = {
    "tbin": lambda q, d, x: timebins.search(q, timebins.build(d, 7), x),
    "tbin one": lambda q, d, x: timebins.search(q, timebins.build(d, 1), x),
    "tbin tight": lambda q, d, x: timebins.search(q, timebins.build(d, 100), x, tight=True),
    "tbin scan": lambda q, d, x: timebins.search(q, timebins.build(d, 13), x, how="scan"),
    "tbin range": lambda q, d, x: timebins.search(q, timebins.build(d, 13, ids=True), x, "range"),
    "classes": lambda q, d, x: timebins.search_classes(q, timebins.build_classes(d, 20), x),
    "slab": lambda q, d, x: slabs.search(q, slabs.build(d, 20, 3), x),
    "slab many": lambda q, d, x: slabs.search(q, slabs.build(d, 20, 9), x),
    "slab all": lambda q, d, x: slabs.search(q, slabs.build(d, 20, 3), x, "intersect"),
    "slab multi": lambda q, d, x: slabs.search(q, slabs.build(d, 20, 3), x, "multi"),
    "cell owner": lambda q, d, x: cells.search(q, cells.build(d, 6), x, "owner"),
    "cell late": lambda q, d, x: cells.search(q, cells.build(d, 4), x, "late"),
    "cell early": lambda q, d, x: cells.search(q, cells.build(d, 5), x, "early"),
    "tree": lambda q, d, x: packed_tree.search(q, packed_tree.build(d, 3, 5), x),
    "tree local": lambda q, d, x: packed_tree.search_local(q, d, x, 5),
    "tree by tasks": lambda q, d, x: packed_tree.search(q, packed_tree.store(packed_tree.build(d, 2)), x, tasks=3),
    "tree local blocks": lambda q, d, x: packed_tree.search_local(q, d, x, 3, block=300),
    "tbin blocks": lambda q, d, x: timebins.search(q, timebins.store(timebins.build(d, 7, block=100)), x),
    "slab blocks": lambda q, d, x: slabs.search(q, slabs.store(slabs.build(d, 5, 2, block=100)), x),
    "slab stored": lambda q, d, x: slabs.search(q, slabs.store(slabs.build(d, 20, 3)), x),
    "cell axis": lambda q, d, x: cells.search(q, cells.build(d, 6, 1, 1), x),
    "hybrid": lambda q, d, x: planner.hybrid(q, d, x, m=10, r=4),
}


@pytest.mark.parametrize("name", METHODS)
def test_same_as_brute(dense, name):
    q, d, expected = dense
    assert key(METHODS[name](q, d, 3.1)) == expected and len(expected) > 50


def test_grows_with_distance(dense):
    q, d, expected = dense
    i = timebins.build(d, 20)
    small, large = key(timebins.search(q, i, 1.0)), key(timebins.search(q, i, 5.0))
    assert len(small) < len(expected) < len(large)
    assert {r[:4] for r in small} <= {r[:4] for r in expected} <= {r[:4] for r in large}


def test_one_slab_is_the_bins(dense):
    q, d, _ = dense
    plan = slabs.schedule(q, slabs.build(d, 20, 1), 3.1)
    assert plan.where("selector < 0").count() == 0
    i = timebins.build(d, 20)
    assert plan.agg(F.sum("n_candidates")).first()[0] == timebins.candidates(q, i).count()


def test_splice_keeps_contacts(dense):
    q, d, _ = dense
    plain = search.contacts(timebins.search(q, timebins.build(d, 20), 3.1))
    cut = search.splice_search(q, d, 3.1, 3)
    total = lambda f: {(r.q_traj, r.traj_id): round(r.n, 6) for r in f.groupBy("q_traj", "traj_id").agg(F.sum(F.col("hi") - F.col("lo")).alias("n")).collect()}
    assert total(plain) == total(cut)


def test_dense_ids(spark, sf_dir):
    d = segments(spark, sf_dir, "event")
    order = ["t0", "traj_id", "seg_id"]
    a, b = dense_ids(d, order), d.withColumn("eid", F.row_number().over(Window.orderBy(*order)) - 1)
    assert a.select("traj_id", "seg_id", "eid").exceptAll(b.select("traj_id", "seg_id", "eid")).count() == 0 and a.count() == b.count()


def test_empty_and_flat(spark):
    none = spark.createDataFrame([], SEGMENT)
    flat = spark.createDataFrame([(i, 0, 0.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0) for i in range(4)], SEGMENT)
    for method in ("tbin", "slab", "cell", "tree"):
        assert search.run(none, flat, 1.0, method).count() == 0
        assert search.run(flat, flat, 0.0, method).count() == 12
    assert search.run(flat, none, 1.0, "tbin").count() == 0


def test_nulls_are_dropped(spark):
    rows = [(1, 0, 0.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0), (1, 1, None, 1.0, 1.0, 1.0, 2.0, 1.0, 1.0, 1.0), (1, 2, 3.0, 1.0, 1.0, 1.0, 3.0, 1.0, 1.0, 1.0)]
    assert segments_from(spark.createDataFrame(rows, SEGMENT)).count() == 1


def test_random_walks_agree(spark):
    rng = random.Random(11)
    rows = []
    for t in range(12):
        x = [rng.uniform(0, 20) for _ in range(3)]
        at = rng.uniform(0, 5)
        for s in range(rng.randint(1, 12)):
            y, end = [v + rng.gauss(0, 2) for v in x], at + rng.choice([0.2, 1.0, 9.0])
            rows.append((t, s, at, *x, end, *y))
            x, at = y, end
    d = materialize(spark.createDataFrame(rows, SEGMENT))
    expected = key(brute.search(d, d, 3.0))
    for name in ("tbin", "classes", "slab", "slab multi", "cell owner", "tree", "tree local"):
        assert key(METHODS[name](d, d, 3.0)) == expected, name


def test_repeated_rows_and_clashing_names(dense, spark):
    """A row is a segment by itself, in every method; columns beyond the segment's do not take part."""
    q, d, _ = dense
    q = q.limit(12).withColumns({"axis": F.lit("a"), "_times": F.lit(1), "bin": F.lit(7), "q_t0": F.lit(0)})
    d = d.where("traj_id % 3 = 0").withColumns({c: F.lit(3) for c in ("b0", "axis", "slab", "bin", "h", "leaf", "node", "eid", "s0", "_arises", "n")})
    q, d = materialize(q.unionByName(q.limit(4))), materialize(d.unionByName(d.where("seg_id % 2 = 0")))
    expected = key(brute.search(q, d, 3.1))
    assert len(expected) > len(set(expected)) > 5
    for name, method in METHODS.items():
        assert key(method(q, d, 3.1)) == expected, name


def test_distances_at_once(dense):
    """One pass over queries that carry their distances gives the rows of a pass for each."""
    q, d, _ = dense
    both = at_distances(q, (1.0, 3.1))
    for found in (timebins.search(both, timebins.build(d, 20), "dist"), slabs.search(both, slabs.build(d, 20, 3), "dist"), cells.search(both, cells.build(d, 5), "dist", "late"), packed_tree.search(both, packed_tree.build(d, 3), "dist")):
        for x in (1.0, 3.1):
            assert key(found.where(F.col("dist") == x)) == key(brute.search(q, d, x))


def test_batches_and_rounds_answer_all(dense):
    q, d, _ = dense
    q = materialize(q.limit(10))
    expected = key(brute.search(q, d, 3.1))
    index, grid = slabs.build(d, 20, 2), cells.build(d, 5)
    need = materialize(slabs.schedule(q, index, 3.1).select(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), F.col("q_t0").alias("t0"), F.col("n_candidates").alias("demand")))
    batched = batching.by_capacity(need, int(need.agg(F.sum("demand")).first()[0] // 3), ["t0", "q_traj", "q_seg"])
    assert batching.rounds(batched) > 1
    assert key(batching.run_batches(q, batched, lambda part: slabs.search(part, index, 3.1))) == expected
    demand = materialize(cells.demand(q, grid, 3.1))
    planned = batching.cell_rounds(demand, int(demand.agg(F.max("demand")).first()[0]) - 1)
    assert planned.agg(F.max("chunks")).first()[0] == 2 and planned.agg(F.max("round")).first()[0] > 1
    found = batching.run_batches(q, planned, lambda part: cells.search(part, grid, 3.1), "round", lambda part, i, k: cells.search(part, cells.chunk(grid, i, k), 3.1))
    assert key(found) == expected


def test_nearest_ends(spark):
    """Fewer trajectories than asked for, and queries that finish at different radii."""
    rows = [(i, 0, 0.0, float(10**i), 0.0, 0.0, 1.0, float(10**i), 0.0, 0.0) for i in range(5)]
    d = spark.createDataFrame(rows, SEGMENT)
    got = sorted((r.q_traj, r["rank"], r.traj_id, round(r.d_min, 6)) for r in search.nearest(d, d, 2, 0.5).collect())
    want = []
    for i in range(5):
        near = sorted((abs(10.0**i - 10.0**j), j) for j in range(5) if j != i)[:2]
        want += [(i, k + 1, j, round(x, 6)) for k, (x, j) in enumerate(near)]
    assert got == want
    assert search.nearest(d, d, 9, 0.5).count() == 20


def test_tree_visits(dense):
    """Nodes visited level by level, against all nodes whose own and upper boxes the queries meet."""
    q, d, _ = dense
    tree = packed_tree.build(d, 4, 5)
    got = {r.level: r.nodes for r in packed_tree.visited(q, tree, 3.1).collect()}
    queries = [r.asDict() for r in q.collect()]
    levels = [[r.asDict() for r in level.collect()] for level in tree.levels]
    assert [len(x) for x in levels] == tree.sizes
    want = {i: 0 for i in range(len(levels))}
    for a in queries:
        reached = {0}
        for i, level in enumerate(levels):
            met = {
                n["node"] for n in level
                if n["parent"] in reached and n["tlo"] < a["t1"] and a["t0"] < n["thi"] and all(n[f"{c}lo"] <= max(a[f"{c}0"], a[f"{c}1"]) + 3.1 and n[f"{c}hi"] >= min(a[f"{c}0"], a[f"{c}1"]) - 3.1 for c in "xyz")
            }
            want[i] += len(met)
            reached = met
    assert got == want


def test_by_trajectory(dense):
    q, _, _ = dense
    parts = by_trajectory(q, 3).withColumn("_p", F.spark_partition_id()).groupBy("traj_id").agg(F.countDistinct("_p").alias("n"))
    assert parts.where("n > 1").isEmpty()


def test_choose_v(dense):
    q, d, _ = dense
    each = {v: slabs.schedule(q, slabs.build(d, 20, v), 1.0).agg(F.sum("n_candidates")).first()[0] for v in (1, 2, 4)}
    assert slabs.choose_v(q, d, 1.0, 20, (1, 2, 4)) == min(each, key=lambda v: (each[v], v))


def test_plans_have_no_nested_loops(dense):
    q, d, _ = dense
    for name in ("tbin", "slab", "cell owner"):
        plan = METHODS[name](q, d, 3.1)._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan, name


def test_recommend(dense):
    q, d, _ = dense
    indexes = planner.prepare(d, m=20, v=2, k=5, r=4)
    counts = {r.method: r.candidates for r in planner.estimates(q, indexes, 3.1).collect()}
    assert counts == {
        "tbin": timebins.candidates(q, indexes.tbin).count(), "slab": slabs.candidates(q, indexes.slab, 3.1).count(),
        "tree": packed_tree.candidates(q, indexes.tree, 3.1).count(), "cell": cells.candidates(q, indexes.cell, 3.1).count(),
    }
    assert planner.recommend(q, indexes, 3.1) == planner.cheapest(counts)
    assert planner.cheapest({"tbin": 9, "tree": 4, "slab": 9}) == "slab" and planner.cheapest({"tbin": 90, "tree": 4}) == "tree"
    assert planner.describe(d)["slab_cap"] >= 1


def test_partitioned_search_reads_what_queries_reach(spark, tmp_path):
    entries = spark.createDataFrame([(i, 0, float(i), 0.0, 0.0, 0.0, i + 1.5, 1.0, 0.0, 0.0) for i in range(20)], SEGMENT)
    path = f"{tmp_path}/by_time"
    save_by_time(entries, path, 2.0)
    assert tuple(load_by_time(spark, path)[1]) == (1.5, 0, 9)
    queries = spark.createDataFrame([(100, 0, 7.0, 0.0, 0.0, 0.0, 8.0, 1.0, 0.0, 0.0), (101, 0, 90.0, 0.0, 0.0, 0.0, 91.0, 1.0, 0.0, 0.0)], SEGMENT)
    got = search.partitioned(queries, path, 2.0, 5.0)
    assert sorted(got.collect()) == sorted(search.run(queries, entries, 5.0, "brute").select(got.columns).collect())
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert re.search(r"PartitionFilters: \[[^\]]*coarse#\d+L? IN \([\d,]+\)", plan), plan
    assert search.partitioned(queries.where("traj_id = 101"), path, 2.0, 5.0).isEmpty()
    save_by_time(entries.limit(0), path, 2.0)
    assert search.partitioned(queries, path, 2.0, 5.0).isEmpty()
