"""Cost measures and answers about whole trajectories, registered with their SQL."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry
from ..operators import batching, cells, packed_tree, planner, search, slabs, tally, timebins
from ..operators.index import as_queries, entries_of, overlapping
from ..session import materialize
from . import counts as c
from . import oracle_parts as sql
from .scenarios import BINS, CELLS, DISTANCE, LEAF, SCENARIOS, SLABS, segments
from .searches import _EXT, Query, bins_cte, both, cell_expr, cells_of, shown, slab_expr, slab_schedule_cte, slabs_cte


def _interactions(n: str):
    """Candidates of each method at the registered settings."""
    x = DISTANCE[n]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        got = {"tbin": c.tbin(q, d, BINS[n]), "tight": c.tbin(q, d, BINS[n], True), "slab": c.slab(q, d, BINS[n], SLABS[n], (x,)), "cell": c.cell(q, d, CELLS[n], (x,)), "tree": c.tree(q, d, LEAF[n], (x,))}
        return c.rows([c.row(f.select("candidates"), method=k) for k, f in got.items()])

    tight = f"(WITH {bins_cte(BINS[n])}, r AS (SELECT bin, min(t0) AS lo, max(t1) AS hi, count(*) AS n FROM b GROUP BY bin) SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM q JOIN r ON q.t0 < hi AND lo < q.t1)"
    one = lambda s: f"(SELECT candidates FROM ({s}))"
    got = {"tbin": c.tbin_sql(BINS[n]), "tight": tight, "slab": one(c.slab_sql(BINS[n], SLABS[n])), "cell": one(c.cell_sql(CELLS[n])), "tree": one(c.tree_sql(LEAF[n]))}
    return run, c.sweep_sql(n, [c.select({"method": k}, {"candidates": s}) for k, s in got.items()], (x,))


def _hit_ratio(n: str):
    """Results over candidates of the time bins, over pairs that overlap in time, and the index's selectivity."""
    x = DISTANCE[n]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        one = c.with_all([c.tbin(q, d, BINS[n]), c.overlapping(q, d), tally.results(q, d, x), q.agg(F.count(F.lit(1)).alias("k")), d.agg(F.count(F.lit(1)).alias("n"))])
        return one.select("candidates", "pairs", "results", (F.col("results") / F.col("candidates")).alias("hit_ratio"), (F.col("results") / F.col("pairs")).alias("pair_fraction"), (F.col("candidates") / (F.col("k") * F.col("n"))).alias("selectivity"))

    return run, f"""WITH {sql.ctes(n)}, o AS (SELECT {c.tbin_sql(BINS[n])} AS candidates, {c.OVERLAPPING_SQL} AS pairs, {c.found_sql(x)} AS results)
        SELECT candidates, pairs, results, results / candidates AS hit_ratio, results / pairs AS pair_fraction, candidates / CAST((SELECT count(*) FROM q) * (SELECT count(*) FROM d) AS DOUBLE) AS selectivity FROM o"""


def _served(n: str):
    x = DISTANCE[n]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        total = q.count()
        return c.rows([c.row(c.slab(q, d, BINS[n], v, (x,)).select((F.col("served") / F.lit(total)).alias("served_fraction")), v=v) for v in (1, 2, 4)])

    return run, c.sweep_sql(n, [c.select({"v": v}, {"served_fraction": f"(SELECT served FROM ({c.slab_sql(BINS[n], v)})) / (SELECT count(*) FROM q)"}) for v in (1, 2, 4)], (x,))


#: The range of distances of each scenario.
RANGE = {"walk": (5.0, 20.0, 50.0), "event": (1.0, 10.0, 50.0), "dense": (0.31, 3.1, 9.4, 15.6, 28.1)}


def _fraction_within(n: str):
    """At each distance: entries that some query comes near, over all entries; queries that find something."""
    dists = RANGE[n]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        got = tally.reached(q, d, dists).withColumnRenamed("dist", "q_dist")
        return c.per_distance(got, dists, "entry_hits", "query_hits", "results").withColumn("entry_fraction", F.col("entry_hits") / F.lit(d.count()))

    got = f"SELECT dist, count(DISTINCT (traj_id, seg_id)) AS entry_hits, count(DISTINCT (q_traj, q_seg)) AS query_hits, count(*) AS results FROM ({sql.match('dist')}) GROUP BY 1"
    return run, f"WITH {sql.ctes(n)}, {c.asked_sql(dists)} SELECT *, entry_hits / (SELECT count(*) FROM d) AS entry_fraction FROM ({c.per_distance_sql(got, 'entry_hits', 'query_hits', 'results')})"


_AXIS_MISS = {a: f"(greatest({a}0, {a}1) < least(q_{a}0, q_{a}1) - {{x}} OR least({a}0, {a}1) > greatest(q_{a}0, q_{a}1) + {{x}})" for a in "xyz"}
_TIME_MISS = "NOT (q_t0 < t1 AND t0 < q_t1)"


def _wasted(n: str):
    """Candidates that the time test, or the box test in space, throws away; and of the latter those that are inside on one
    axis at least, the one that a slab could have looked at."""
    x = DISTANCE[n]
    misses = [m.format(x=f"CAST({x} AS DOUBLE)") for m in _AXIS_MISS.values()]
    space = f"NOT ({_TIME_MISS}) AND ({' OR '.join(misses)})"
    counted = {"time_misses": _TIME_MISS, "space_misses": space, "off_axis_misses": f"{space} AND NOT ({' AND '.join(misses)})"}

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        grid, index = cells.build(d, CELLS[n]), slabs.build(d, BINS[n], SLABS[n])
        number = lambda i, a, f, p, by, numbers: numbers(i, f(f"{p}{a}0", f"{p}{a}1") + F.lit(by)).cast("double")
        ends = (("lo", F.least, -1), ("hi", F.greatest, 1))
        # Candidates are the pairs whose ranges of cells, or whose slab of the chosen axis, meet; time and the box are looked at beside them.
        plan = tally.boxed(slabs.schedule(q, index, x), x, "q_").withColumns({f"q_c{a}_{e}": number(i, a, f, "q_", s * x, grid.grid.number) for i, a in enumerate("xyz") for e, f, s in ends})
        chosen = {f"q_s{a}_{e}": F.when(F.col("selector") == i, F.col("slab").cast("double")).otherwise(F.lit(-s * math.inf)) for i, a in enumerate("xyz") for e, s in (("lo", 1), ("hi", -1))}
        asked = plan.withColumns(chosen).withColumn("_q", F.xxhash64("q_traj_id", "q_seg_id"))
        held = tally.boxed(entries_of(d)).withColumn("_e", F.xxhash64("traj_id", "seg_id"))
        held = held.withColumns({f"{k}{a}_{e}": number(i, a, f, "", 0.0, numbers) for k, numbers in (("c", grid.grid.number), ("s", index.slabs.number)) for i, a in enumerate("xyz") for e, f, _ in ends})
        box, cell, slab = tuple("xyz"), ("cx", "cy", "cz"), ("sx", "sy", "sz")
        wanted = {"inside": (box, ()), "slab_inside": (box + slab, ())} | {f"{k}_{what}": (places, none) for k, places in (("tbin", ()), ("slab", slab), ("cell", cell)) for what, none in (("time", ()), ("off", box))}
        ranged = lambda df, p: [f"{p}{r}_{e}" for r in box + cell + slab for e in ("lo", "hi")]
        got = tally.counts(asked.select("q_traj_id", "q_seg_id", "_q", "q_t0", "q_t1", *ranged(asked, "q_")), held.select("_e", "t0", "t1", *ranged(held, "")), wanted).agg(*(F.coalesce(F.sum(k), F.lit(0)).alias(k) for k in wanted)).first()
        all_ = {"tbin": c.n(timebins.counted(as_queries(q), index.time), "n", F.col("n")).first()[0], "slab": c.n(plan, "n", F.col("n_candidates")).first()[0], "cell": cells.shared(q, grid, x)[1]}
        out = []
        for k, total in all_.items():
            inside, meet = got["slab_inside" if k == "slab" else "inside"], got[f"{k}_time"]
            out.append((k, total - meet, meet - inside, meet - inside - got[f"{k}_off"]))
        return spark.createDataFrame(out, "method string, time_misses long, space_misses long, off_axis_misses long")

    names = "traj_id seg_id t0 x0 y0 z0 t1 x1 y1 z1".split()
    mine, its = ", ".join(f"q.{a} AS q_{a}" for a in names), lambda t: ", ".join(f"{t}.{a}" for a in names)
    tbin = f"SELECT {mine}, {its('b')} FROM q JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 JOIN b ON b.bin = dir.bin"
    slab = f"""SELECT {mine}, {its('look')} FROM q JOIN chosen p ON p.traj_id = q.traj_id AND p.seg_id = q.seg_id JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 JOIN look ON look.axis = p.axis AND look.slab = p.slab AND look.bin = dir.bin
        UNION ALL SELECT {mine}, {its('b')} FROM q JOIN plan p ON p.q_traj = q.traj_id AND p.q_seg = q.seg_id AND p.selector = -1 JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 JOIN b ON b.bin = dir.bin"""
    met = f"SELECT DISTINCT c.traj_id AS q1, c.seg_id AS q2, a.traj_id AS e1, a.seg_id AS e2 FROM ({cells_of(CELLS[n], 'q', d=x)}) c JOIN ({cells_of(CELLS[n], 'd')}) a USING (h)"
    cell = f"SELECT {mine}, {its('d')} FROM ({met}) JOIN q ON q.traj_id = q1 AND q.seg_id = q2 JOIN d ON d.traj_id = e1 AND d.seg_id = e2"
    chosen = "chosen AS (SELECT elig.* FROM elig JOIN plan ON plan.q_traj = elig.traj_id AND plan.q_seg = elig.seg_id AND plan.selector = elig.axis)"
    count = ", ".join(f"count(*) FILTER (WHERE {e}) AS {k}" for k, e in counted.items())
    body = " UNION ALL ".join(f"SELECT '{k}' AS method, {count} FROM ({s})" for k, s in (("tbin", tbin), ("slab", slab), ("cell", cell)))
    return run, f"WITH {sql.ctes(n)}, {slab_schedule_cte(BINS[n], SLABS[n], x)}, {chosen} {body}"


def _duplicates(n: str):
    """Candidates and results, before and after repeats are removed, of the cells and of several slabs of one axis."""
    x, k = (3.1, 10) if n == "dense" else (DISTANCE[n] / 4, CELLS[n])
    m, v = BINS[n], 4

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        grid, index = cells.build(d, k), slabs.build(d, m, v)
        slab = slabs.multi_counts(q, index, x).agg(F.coalesce(F.sum("repeats"), F.lit(0)), F.coalesce(F.sum("once"), F.lit(0))).first()

        def keep(df: DataFrame, prefix: str) -> DataFrame:
            """First and last cells and slabs of either side's box."""
            by = x if prefix else 0.0
            at = {f"{prefix}s{a}{e}": index.slabs.number(i, f(f"{prefix}{a}0", f"{prefix}{a}1") + F.lit(s * by)) for i, a in enumerate("xyz") for e, f, s in (("a", F.least, -1), ("z", F.greatest, 1))}
            return cells.corners(df, grid.grid, by, prefix).withColumns({k: e.cast("long") for k, e in at.items()})

        def common(q_, d_, a: str):
            return np.minimum(q_(f"q_{a}z"), d_(f"{a}z")) - np.maximum(q_(f"q_{a}a"), d_(f"{a}a")) + 1

        def of_slabs(q_, d_):
            widths = np.stack([q_(f"q_s{a}z") - q_(f"q_s{a}a") for a in "xyz"])
            return np.choose(widths.argmin(0), [common(q_, d_, f"s{a}") for a in "xyz"])

        hits = tally.results(q, d, x, {"cell": lambda q_, d_: common(q_, d_, "x") * common(q_, d_, "y") * common(q_, d_, "z"), "slabs": of_slabs}, keep).first()
        out = [("cell", *cells.shared(q, grid, x), hits["cell"], hits["results"]), ("slabs", *slab, hits["slabs"], hits["results"])]
        return spark.createDataFrame(out, "method string, candidates long, distinct_candidates long, results long, distinct_results long").withColumn("duplicates", F.col("candidates") - F.col("distinct_candidates"))

    shared = lambda c_: f"least(least({n_slab(f'greatest(q_{c_}0, q_{c_}1) + {x}', c_)}, {n_slab(f'greatest({c_}0, {c_}1)', c_)}) - greatest({n_slab(f'least(q_{c_}0, q_{c_}1) - {x}', c_)}, {n_slab(f'least({c_}0, {c_}1)', c_)}) + 1, 1000000)"
    n_slab = lambda e, c_: slab_expr(v, e, c_)
    n_cell = lambda e, c_: cell_expr(k, e, c_)
    cells_shared = " * ".join(f"(least({n_cell(f'greatest(q_{a}0, q_{a}1) + {x}', a)}, {n_cell(f'greatest({a}0, {a}1)', a)}) - greatest({n_cell(f'least(q_{a}0, q_{a}1) - {x}', a)}, {n_cell(f'least({a}0, {a}1)', a)}) + 1)" for a in "xyz")
    width = lambda a: f"{n_slab(f'greatest(q_{a}0, q_{a}1) + {x}', a)} - {n_slab(f'least(q_{a}0, q_{a}1) - {x}', a)}"
    axis = f"CASE WHEN {width('x')} <= {width('y')} AND {width('x')} <= {width('z')} THEN {shared('x')} WHEN {width('y')} <= {width('z')} THEN {shared('y')} ELSE {shared('z')} END"
    hit = f"SELECT * FROM {sql.approached(sql.pairs(), x)}, e WHERE s0 <= s1"
    one = lambda s: f"(SELECT candidates FROM ({s}))"
    rows = [
        ("cell", one(c.cell_sql(k)), one(c.cell_distinct_sql(k)), f"(SELECT CAST(coalesce(sum({cells_shared}), 0) AS BIGINT) FROM hit)"),
        ("slabs", one(c.slab_pairs_sql(m, v, "multi repeats")), one(c.slab_pairs_sql(m, v, "multi")), f"(SELECT CAST(coalesce(sum({axis}), 0) AS BIGINT) FROM hit)"),
    ]
    body = " UNION ALL ".join(f"SELECT '{name}' AS method, {a} AS candidates, {b} AS distinct_candidates, {r} AS results, (SELECT count(*) FROM hit) AS distinct_results" for name, a, b, r in rows)
    return run, f"WITH {sql.ctes(n)}, {c.asked_sql((x,))}, {_EXT}, hit AS MATERIALIZED ({hit}) SELECT *, candidates - distinct_candidates AS duplicates FROM ({body})"


def _index_size(n: str):
    """Rows of each index's arrays, and bytes at four for an id."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = materialize(segments(spark, sf_dir, n))
        cell, slab = cells.build(d, CELLS[n]), slabs.build(d, BINS[n], SLABS[n])
        count = lambda f: f.agg(F.count(F.lit(1)).alias("n"))
        got = {"cells": cell.directory, "cell_lookup": cell.lookup, "slab_lookup": slab.lookup, "bins": slab.time.directory}
        return c.rows([c.row(count(f), part=k) for k, f in got.items()]).withColumn("bytes", 4 * F.col("n"))

    got = {"cells": "(SELECT count(DISTINCT h) FROM a)", "cell_lookup": "(SELECT count(*) FROM a)", "slab_lookup": "(SELECT count(*) FROM look)", "bins": "(SELECT count(*) FROM dir)"}
    body = " UNION ALL ".join(f"SELECT '{k}' AS part, {s} AS n" for k, s in got.items())
    return run, f"WITH {sql.ctes(n)}, {slabs_cte(BINS[n], SLABS[n])}, a AS ({cells_of(CELLS[n], 'd')}) SELECT *, 4 * n AS bytes FROM ({body})"


def _balance(n: str):
    """Largest and mean number of candidates of a query, by method."""
    x = DISTANCE[n]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, n)
        i, key = timebins.build(d, BINS[n]), ["q_traj_id", "q_seg_id"]
        per = {
            "tbin": timebins.counted(as_queries(q), i).groupBy(*key).agg(F.sum("n").alias("n")), "slab": slabs.schedule(q, slabs.build(d, BINS[n], SLABS[n]), x).select(F.col("n_candidates").alias("n")),
            "cell": cells.demand(q, cells.build(d, CELLS[n]), x).select(F.col("demand").alias("n")), "tree": packed_tree.demand(q, materialize(packed_tree.leaves(d, LEAF[n])), LEAF[n], x),
        }
        out = c.rows([c.row(f.where("n > 0").agg(F.max("n").cast("long").alias("most"), F.sum("n").cast("long").alias("total"), F.count(F.lit(1)).alias("queries")), method=k) for k, f in per.items()])
        return out.withColumn("imbalance", F.col("most") * F.col("queries") / F.col("total"))

    space = " AND ".join(f"{a}lo <= greatest(qx.{a}0, qx.{a}1) + dist AND {a}hi >= least(qx.{a}0, qx.{a}1) - dist" for a in "xyz")
    per = {
        "tbin": "SELECT n FROM allb", "slab": "SELECT n_candidates AS n FROM plan", "cell": f"SELECT demand AS n FROM ({c.cell_demand_sql(CELLS[n])})",
        "tree": f"SELECT sum(n) AS n FROM qx JOIN leaf ON tlo < qx.t1 AND qx.t0 < thi AND {space} GROUP BY qx.traj_id, qx.seg_id",
    }
    body = " UNION ALL ".join(f"SELECT '{k}' AS method, CAST(max(n) AS BIGINT) AS most, CAST(sum(n) AS BIGINT) AS total, count(*) AS queries, CAST(max(n) * count(*) AS DOUBLE) / CAST(sum(n) AS DOUBLE) AS imbalance FROM ({s}) WHERE n > 0" for k, s in per.items())
    return run, f"WITH {sql.ctes(n)}, {slab_schedule_cte(BINS[n], SLABS[n], x)}, ds AS (SELECT CAST({x} AS DOUBLE) AS dist), {c.leaves_cte(LEAF[n])} {body}"


def _occupancy(n: str):
    """Bins and cells that are not empty, and the fullest of each."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = materialize(segments(spark, sf_dir, n))
        b = timebins.build(d, BINS[n]).directory.agg(F.count(F.lit(1)).alias("filled"), F.max("n").alias("fullest"))
        g = cells.build(d, CELLS[n]).directory.agg(F.count(F.lit(1)).alias("filled"), F.max("n").alias("fullest"))
        return c.rows([c.row(b, part="bins"), c.row(g, part="cells")])

    return run, f"""WITH {sql.ctes(n)}, {bins_cte(BINS[n])}, a AS ({cells_of(CELLS[n], 'd')}), g AS (SELECT h, count(*) AS n FROM a GROUP BY h)
        SELECT 'bins' AS part, count(*) AS filled, max(n) AS fullest FROM dir UNION ALL SELECT 'cells', count(*), max(n) FROM g"""


def _rounds_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds of the candidate buffer: queries, demand and capacity of each."""
    q, d = both(spark, sf_dir, "dense")
    done = batching.cell_rounds(cells.demand(q, cells.build(d, 10), 3.1), 300 * c.total_entries(d))
    return done.groupBy(F.col("round").cast("long").alias("round")).agg(F.count(F.lit(1)).alias("queries"), F.sum("demand").cast("long").alias("demand"))


def _rounds_sql() -> str:
    """The same rounds: sets of queries in the order of their demand, cut where the recursion says."""
    need = c.cell_demand_sql(10)
    cut = c.rounds_sql(need, "(SELECT 300 * count(*) FROM d)").replace("SELECT dist, max(round) AS rounds FROM (", "SELECT dist, round, p AS z FROM (").replace("SELECT dist, round FROM r) GROUP BY dist", "SELECT dist, round, p FROM r)")
    return f"""WITH {sql.ctes('dense')}, {c.asked_sql((3.1,))}, cut AS MATERIALIZED ({cut}), o AS (SELECT dist, demand, row_number() OVER (ORDER BY demand, traj_id, seg_id) - 1 AS i FROM ({need}))
        SELECT CAST(round AS BIGINT) AS round, count(*) AS queries, CAST(sum(demand) AS BIGINT) AS demand FROM (SELECT demand, (SELECT min(round) FROM cut WHERE z > i) AS round FROM o) GROUP BY 1"""


def _groups_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries by the size of their demand."""
    q, d = both(spark, sf_dir, "dense")
    return batching.grouped(cells.demand(q, cells.build(d, 10), 3.1)).withColumn("class", F.col("class").cast("long"))


_GROUPS_SQL = f"""WITH {sql.ctes('dense')}, {c.asked_sql((3.1,))} SELECT CAST(CASE WHEN demand > 0 THEN floor(log2(CAST(demand AS DOUBLE))) ELSE -1 END AS BIGINT) AS class, count(*) AS queries, CAST(sum(demand) AS BIGINT) AS total
    FROM ({c.cell_demand_sql(10)}) GROUP BY 1"""


def _all_pairs_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs without a look at time, and those that overlap in it: counted, not made."""
    q, d = c.prepared(spark, sf_dir, "dense")
    every = c.with_all([q.agg(F.count(F.lit(1)).alias("k")), d.agg(F.count(F.lit(1)).alias("n"))]).select((F.col("k") * F.col("n")).alias("pairs"))
    return c.rows([c.row(every, time="none"), c.row(c.n(overlapping(as_queries(q), d), "pairs", F.col("n")), time="overlap")])


_ALL_PAIRS_SQL = f"WITH {sql.ctes('dense')} SELECT 'none' AS time, count(*) AS pairs FROM q, d UNION ALL SELECT 'overlap', count(*) FROM q JOIN d ON q.t0 < d.t1 AND d.t0 < q.t1"


def _choose_v_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates of each number of slabs; the first of the smallest is the choice."""
    q, d = c.prepared(spark, sf_dir, "dense")
    got = materialize(slabs.totals(q, d, 3.1, 48))
    best = slabs.choose_v(q, d, 3.1, 48)
    return got.select(F.col("v").cast("long").alias("v"), "candidates", (F.col("v") == best).alias("chosen"))


_CHOOSE_PARTS = " UNION ALL ".join(c.label_sql({"v": v}, f"SELECT candidates FROM ({c.slab_sql(48, v)})") for v in (1, 2, 4, 8, 16))
_CHOOSE_SQL = f"WITH {sql.ctes('dense')}, {c.asked_sql((3.1,))}, t AS MATERIALIZED ({_CHOOSE_PARTS}) SELECT v, candidates, v = (SELECT arg_min(v, (candidates, v)) FROM t) AS chosen FROM t"


def _tree_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d = both(spark, sf_dir, "dense")
    return packed_tree.visited(q, packed_tree.build(d, 4), 3.1)


def _plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d = both(spark, sf_dir, "dense")
    return planner.estimates(q, planner.prepare(d, m=48, v=2, k=10, r=4), 9.4)


def _plan_sql() -> str:
    one = lambda s: f"(SELECT candidates FROM ({s}))"
    got = {"tbin": c.tbin_sql(48), "slab": one(c.slab_sql(48, 2)), "tree": one(c.tree_sql(4)), "cell": one(c.cell_sql(10))}
    return c.sweep_sql("dense", [c.select({"method": k}, {"candidates": s}) for k, s in got.items()], (9.4,))


def _hybrid(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d = both(spark, sf_dir, "dense")
    return shown(planner.hybrid(q, d, 9.4, m=48, r=4))


# ---- answers about trajectories ------------------------------------------------------------------------------


def _contacts(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d = both(spark, sf_dir, "dense")
    return shown(search.contacts(timebins.search(q, timebins.build(d, 48), 3.1)))


def contacts_sql(matches: str) -> str:
    return f"""SELECT q_traj, traj_id, min(lo) AS lo, max(hi) AS hi FROM (SELECT *, sum(fresh) OVER (PARTITION BY q_traj, traj_id ORDER BY lo, hi ROWS UNBOUNDED PRECEDING) AS k FROM (
        SELECT *, CASE WHEN lo <= max(hi) OVER (PARTITION BY q_traj, traj_id ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS fresh FROM ({matches}))) GROUP BY q_traj, traj_id, k"""


_CONTACTS_SQL = f"WITH {sql.ctes('dense')} SELECT q_traj, traj_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({contacts_sql(sql.match(3.1))})"
_TS, _TE = 10.25, 12.5


def clip_sql(table: str, ts: float, te: float) -> str:
    a, b = f"greatest(t0, CAST({ts} AS DOUBLE))", f"least(t1, CAST({te} AS DOUBLE))"
    at = lambda x, t, end: f"CASE WHEN {t} = {end} THEN {x}{end[1]} ELSE {x}0 + ({x}1 - {x}0) / (t1 - t0) * ({t} - t0) END"
    return f"SELECT traj_id, seg_id, {a} AS t0, {', '.join(f'{at(x, a, 't0')} AS {x}0' for x in 'xyz')}, {b} AS t1, {', '.join(f'{at(x, b, 't1')} AS {x}1' for x in 'xyz')} FROM {table} WHERE t1 > {ts} AND t0 < {te}"


def _within(mode: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = both(spark, sf_dir, "dense")
        return search.trajectories_within(q, d, 9.4, _TS, _TE, mode, m=48)

    return run


_CLIPPED = f"WITH {sql.ctes('dense')}, cq AS ({clip_sql('q', _TS, _TE)}), cd AS ({clip_sql('d', _TS, _TE)})"
_WITHIN_SQL = f"{_CLIPPED} SELECT DISTINCT q_traj, traj_id FROM ({sql.match(9.4, sql.pairs('cq', 'cd'))})"
_ALWAYS_SQL = f"{_CLIPPED} SELECT q_traj, traj_id FROM ({contacts_sql(sql.match(9.4, sql.pairs('cq', 'cd')))}) GROUP BY 1, 2 HAVING sum(hi - lo) >= {_TE - _TS} - 1e-9"


def _fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    point = search.fixed_point(spark, 10.0, 10.0, 10.0, 5.0, 25.0)
    return shown(search.run(point, segments(spark, sf_dir, "dense"), 4.0, m=48))


_POINT = "SELECT CAST(-1 AS BIGINT) AS traj_id, CAST(0 AS BIGINT) AS seg_id, " + ", ".join(f"CAST({v} AS DOUBLE) AS {k}" for k, v in dict(t0=5, x0=10, y0=10, z0=10, t1=25, x1=10, y1=10, z1=10).items())
_FIXED_SQL = f"WITH {sql.ctes('dense')}, pt AS ({_POINT}) SELECT q_traj, q_seg, traj_id, seg_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({sql.match(4.0, sql.pairs('pt'))})"


def _self_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(search.self_join(segments(spark, sf_dir, "event"), 1.0))


_SELF_SQL = f"WITH {sql.ctes('event')} SELECT q_traj, q_seg, traj_id, seg_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({sql.match(1.0, sql.pairs('d', 'd', 'qs.traj_id < es.traj_id'))})"


def _predator_prey(spark: SparkSession, sf_dir: str) -> DataFrame:
    event = segments(spark, sf_dir, "event")
    return search.trajectories_within(event.where("traj_id % 3 = 0"), event.where("traj_id % 3 <> 0"), 5.0, 0.0, 744.0)


_PREY_SQL = f"WITH {sql.ctes('event')}, cd AS ({clip_sql('d', 0.0, 744.0)}) SELECT DISTINCT q_traj, traj_id FROM ({sql.match(5.0, sql.pairs('cd', 'cd', 'qs.traj_id % 3 = 0 AND es.traj_id % 3 <> 0'))})"


def _knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d = both(spark, sf_dir, "dense")
    got = search.nearest(q, d, 3, 0.5, m=48)
    return got.select("q_traj", "traj_id", geometry.rounded(F.col("d_min")).alias("d_min"), F.col("rank").cast("long").alias("rank"))


_NEAR = f"SELECT *, CASE WHEN qa = 0 THEN CAST(0 AS DOUBLE) ELSE greatest(CAST(0 AS DOUBLE), least(b1 - b0, -qb / qa)) END AS s FROM {sql.approached(sql.pairs(), 0.0, 3)}"
_KNN_SQL = f"""WITH {sql.ctes('dense')}, near AS (SELECT q_traj_id AS q_traj, traj_id, min(sqrt(greatest(qa * s * s + 2 * qb * s + qc, CAST(0 AS DOUBLE)))) AS d_min FROM ({_NEAR}) GROUP BY 1, 2)
    SELECT q_traj, traj_id, {sql.rounded('d_min')} AS d_min, rank FROM (SELECT *, row_number() OVER (PARTITION BY q_traj ORDER BY d_min, traj_id) AS rank FROM near) WHERE rank <= 3"""


_SINGLE = {
    "traj_contacts": (_contacts, _CONTACTS_SQL),
    "traj_within": (_within("any"), _WITHIN_SQL),
    "traj_always": (_within("always"), _ALWAYS_SQL),
    "traj_fixed_point": (_fixed, _FIXED_SQL),
    "traj_self_join": (_self_join, _SELF_SQL),
    "traj_predator_prey": (_predator_prey, _PREY_SQL),
    "traj_knn": (_knn, _KNN_SQL),
    "search_hybrid_dense": (_hybrid, sql.search("dense", 9.4)),
    "batch_rounds_dense": (_rounds_dense, _rounds_sql()),
    "batch_groups_dense": (_groups_dense, _GROUPS_SQL),
    "measure_all_pairs_dense": (_all_pairs_dense, _ALL_PAIRS_SQL),
    "measure_choose_v_dense": (_choose_v_dense, _CHOOSE_SQL),
    "measure_tree_visits_dense": (_tree_visits, None),
    "measure_plan_dense": (_plan, _plan_sql()),
}
_EACH = {"interactions": _interactions, "hit_ratio": _hit_ratio, "served": _served, "within": _fraction_within, "wasted": _wasted, "index_size": _index_size, "balance": _balance, "occupancy": _occupancy}


def _all() -> dict:
    out = dict(_SINGLE)
    for n in SCENARIOS:
        out |= {f"measure_{k}_{n}": f(n) for k, f in _EACH.items()}
    return out | {"measure_duplicates_dense": _duplicates("dense"), "measure_duplicates_walk": _duplicates("walk"), "measure_duplicates_event": _duplicates("event")}


_FOUND = _all()


def queries() -> dict[str, Query]:
    return {k: f for k, (f, _) in _FOUND.items()}


def oracles() -> dict[str, str]:
    return {k: s for k, (_, s) in _FOUND.items() if s}
