"""The experiment workloads: one row for each parameter setting, with counts.  Times are bench.py's."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..operators import cells, search, slabs, timebins
from ..operators.index import as_queries, at_distances
from ..session import materialize
from . import counts as c
from . import oracle_parts as sql
from . import searches
from .scenarios import SCENARIOS, segments
from .searches import Query

# The distances of the three scenarios.
WALK_D = tuple(float(x) for x in range(5, 55, 5))
EVENT_D = (1.0, 5.0, 10.0, 20.0, 50.0)
DENSE_D = (0.31, 3.1, 9.4, 15.6, 28.1)
#: Distances that stand for the three questions about habitability: the first two lie near zero, as in the experiment.
DOMAIN_D = {"close encounter": 0.1, "supernova": 0.5, "gamma ray burst": 10.0}


def _tree_sweep(name: str, leaf_sizes: tuple[int, ...], dists: tuple[float, ...], m: int):
    """Leaf size by distance: candidates and results."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, name)
        hits = materialize(c.found(q, d, m, dists))
        return c.rows([c.row(c.tree(q, d, r, dists).join(hits, "d"), r=r) for r in leaf_sizes])

    body = " UNION ALL ".join(c.label_sql({"r": r}, c.tree_sql(r)) for r in leaf_sizes)
    return run, f"WITH {sql.ctes(name)}, {c.asked_sql(dists)}, hits AS MATERIALIZED ({c.FOUND_SQL}) SELECT * FROM ({body}) JOIN hits USING (d)"


def _bins_sweep(name: str, ms: tuple[int, ...]):
    """Bins: candidates do not depend on the distance."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, name)
        return c.rows([c.row(c.with_all([c.tbin(q, d, m), c.tbin_range(q, d, m).withColumnRenamed("candidates", "range_candidates")]), m=m) for m in ms])

    return run, c.sweep_sql(name, [c.select({"m": m}, {"candidates": c.tbin_sql(m), "range_candidates": c.tbin_range_sql(m)}) for m in ms])


def _slab_sweep(name: str, m: int, vs: tuple[int, ...], dists: tuple[float, ...]):
    """Slabs by distance: candidates, and how many queries a slab serves."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, name)
        return c.rows([c.row(c.slab(q, d, m, v, dists), v=v) for v in vs])

    return run, c.sweep_sql(name, [c.label_sql({"v": v}, c.slab_sql(m, v)) for v in vs], dists)


def _compare(name: str, dists: tuple[float, ...], rs: tuple[int, ...], m: int, v: int, k: int | None, domain: dict[str, float] | None = None):
    """All methods at the settings of the comparison: candidates and rounds of each, results, and the share of entries and of
    pairs that overlap in time that they are.  The optimistic cells are launched once, whatever the buffer."""
    dists = tuple(sorted({*dists, *(domain or {}).values()}))

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, name)
        once = F.lit(1).cast("long").alias("rounds")
        methods = {f"tree r={r}": c.tree(q, d, r, dists).select("d", "candidates", once) for r in rs}
        methods["tbin"] = c.tbin(q, d, m).select(F.explode(F.array(*map(F.lit, dists))).alias("d"), "candidates", once)
        methods["slab"] = c.slab(q, d, m, v, dists).select("d", "candidates", once)
        if k:
            cell = materialize(c.cell_rounds(q, d, k, dists))
            methods |= {"cell": cell, "cell optimistic": cell.select("d", "candidates", once)}
        hits, pairs, n = materialize(c.found(q, d, m, dists)), c.overlapping(q, d).first()[0], c.total_entries(d)
        out = c.rows([c.row(f, method=name_) for name_, f in methods.items()]).join(F.broadcast(hits), "d")
        marks = F.create_map(*(F.lit(x) for kv in (domain or {"": -1.0}).items() for x in (kv[1], kv[0])))
        return out.select("method", "d", "candidates", "rounds", "results", (F.col("entries") / n).alias("entry_fraction"), (F.col("results") / pairs).alias("pair_fraction"), F.coalesce(F.try_element_at(marks, F.col("d")), F.lit("")).alias("domain"))

    once = "CAST(1 AS BIGINT) AS rounds"
    methods = {f"tree r={r}": f"SELECT *, {once} FROM ({c.tree_sql(r)})" for r in rs}
    methods["tbin"] = f"SELECT dist AS d, {c.tbin_sql(m)} AS candidates, {once} FROM ds"
    methods["slab"] = f"SELECT * EXCLUDE (served), {once} FROM ({c.slab_sql(m, v)})"
    if k:
        methods |= {"cell": "SELECT * FROM cr", "cell optimistic": f"SELECT d, candidates, {once} FROM cr"}
    body = " UNION ALL ".join(c.label_sql({"method": n}, s) for n, s in methods.items())
    mark = "CASE " + " ".join(f"WHEN d = CAST({x!r} AS DOUBLE) THEN '{n}'" for n, x in (domain or {}).items()) + " ELSE '' END" if domain else "''"
    more = f", cr AS MATERIALIZED ({c.cell_rounds_sql(k)})" if k else ""
    return run, f"""WITH {sql.ctes(name)}, {c.asked_sql(dists)}{more}, hits AS MATERIALIZED ({c.FOUND_SQL}) SELECT method, d, candidates, rounds, results, entries / (SELECT count(*) FROM d) AS entry_fraction,
        results / {c.OVERLAPPING_SQL} AS pair_fraction, {mark} AS domain FROM ({body}) JOIN hits USING (d)"""


def _w2():
    """Cells by distance: candidates, and rounds with a buffer that is scaled to the entries."""
    ks = (10, 20, 50)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, "walk")
        return c.rows([c.row(c.cell_rounds(q, d, k, WALK_D), cells=k) for k in ks])

    return run, c.sweep_sql("walk", [c.label_sql({"cells": k}, c.cell_rounds_sql(k)) for k in ks], WALK_D)


def _w5():
    """One slab for an axis is the time bins with an indirection."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, "walk")
        return c.rows([c.row(c.tbin(q, d, 10000), method="tbin"), c.row(c.slab(q, d, 10000, 1, (50.0,)).select("candidates"), method="slab")])

    slab = c.label_sql({"method": "slab"}, f"SELECT candidates FROM ({c.slab_sql(10000, 1)})")
    return run, c.sweep_sql("walk", [c.select({"method": "tbin"}, {"candidates": c.tbin_sql(10000)}), slab], (50.0,))


def _w14():
    """Result buffers: how many invocations a search needs with a buffer, and with one that is 1.84 times as large.

    The buffer is scaled to the entries.  A query's demand is its schedule's number of candidates, the bound that is known
    before; beside it stands how many the results themselves would need."""
    share, m, v = 50_000_000 / 12_582_912, 1000, 2

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, "dense")
        asked, n, key = at_distances(q, DENSE_D), c.total_entries(d), ["q_traj", "q_seg"]
        bins, index = timebins.build(d, m), slabs.build(d, m, v)
        ids = [F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), F.col("q_t0").alias("t0"), F.col("q_dist").alias("dist")]
        tbin = timebins.overlaps(as_queries(asked, "dist"), bins.directory, bins.bins).groupBy(*ids).agg(F.sum("n").alias("demand"))
        slab = slabs.schedule(asked, index, "dist").select(*ids, F.col("n_candidates").alias("demand"))
        hits = timebins.search(asked, bins, "dist").groupBy(*key, "dist").agg(F.count(F.lit(1)).alias("results"))
        both = tbin.withColumn("method", F.lit("tbin")).unionByName(slab.withColumn("method", F.lit("slab"))).join(hits, [*key, "dist"], "left").fillna(0, ["results"])
        # Running sums of each method and distance, whose queries are few; batching.by_capacity is the way for many.
        w = Window.partitionBy("method", "dist").orderBy("t0", *key).rowsBetween(Window.unboundedPreceding, -1)
        sums = both.select("method", F.col("dist").alias("d"), "demand", "results", *(F.coalesce(F.sum(x).over(w), F.lit(0)).alias(f"_{x}") for x in ("demand", "results")))
        out = []
        for scale in (1.0, 1.84):
            size = max(1, int(n * share * scale))
            batches = [F.countDistinct(F.expr(f"_{x} div {size}")).alias(name) for x, name in (("demand", "batches"), ("results", "result_batches"))]
            out.append(sums.groupBy("method", "d").agg(*batches, F.sum("demand").cast("long").alias("demand"), F.sum("results").cast("long").alias("results")).withColumn("scale", F.lit(scale)))
        return c.rows(out)

    w = "(PARTITION BY method, dist ORDER BY t0, q_traj, q_seg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
    one = lambda scale: f"""SELECT method, dist AS d, count(DISTINCT sd // {size(scale)}) AS batches, count(DISTINCT sr // {size(scale)}) AS result_batches, CAST(sum(demand) AS BIGINT) AS demand, CAST(sum(results) AS BIGINT) AS results, CAST({scale} AS DOUBLE) AS scale FROM sums GROUP BY 1, 2"""
    size = lambda scale: f"(SELECT greatest(1, CAST(floor(count(*) * CAST({share!r} AS DOUBLE) * CAST({scale} AS DOUBLE)) AS BIGINT)) FROM d)"
    return run, f"""WITH {sql.ctes('dense')}, {c.asked_sql(DENSE_D)}, {searches.slab_schedule_cte(m, v)}, hits AS (SELECT dist, q_traj, q_seg, count(*) AS results FROM ({sql.match('dist')}) GROUP BY 1, 2, 3),
        need AS (SELECT 'slab' AS method, dist, q_traj, q_seg, n_candidates AS demand FROM plan UNION ALL SELECT 'tbin', dist, traj_id, seg_id, n FROM allb, ds),
        sums AS MATERIALIZED (SELECT method, dist, demand, coalesce(results, 0) AS results, CAST(coalesce(sum(demand) OVER w, 0) AS BIGINT) AS sd, CAST(coalesce(sum(coalesce(results, 0)) OVER w, 0) AS BIGINT) AS sr
            FROM need LEFT JOIN hits USING (dist, q_traj, q_seg) JOIN q ON q.traj_id = q_traj AND q.seg_id = q_seg WINDOW w AS {w}) {one(1.0)} UNION ALL {one(1.84)}"""


#: Settings of the summary: scenario, distances, leaf size, bins, slabs, cells.
SUMMARY = (("walk", (5.0, 20.0, 50.0), 10, 10000, 4, 50), ("event", (1.0, 10.0, 50.0), 1, 1000, 16, 10), ("dense", (0.31, 9.4, 28.1), 4, 1000, 2, 10))


def _w16():
    """Candidates of each method, and of all pairs, over those of TREE; null where the tree has none."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = []
        for name, dists, r, m, v, k in SUMMARY:
            q, d = c.prepared(spark, sf_dir, name)
            base = c.tree(q, d, r, dists).withColumnRenamed("candidates", "tree")
            each = {"slab": c.slab(q, d, m, v, dists).drop("served"), "cell": c.cell(q, d, k, dists)}
            flat = c.with_all([c.tbin(q, d, m).withColumnRenamed("candidates", "tbin"), q.agg((F.count(F.lit(1)) * c.total_entries(d)).alias("brute"))])
            for method, n in each.items():
                base = base.join(n.withColumnRenamed("candidates", method), "d")
            out.append(c.row(base.crossJoin(flat), scenario=name))
        return c.rows(out).select("scenario", "d", *(F.try_divide(F.col(x).cast("double"), F.col("tree")).alias(x) for x in ("tbin", "slab", "cell", "brute")))

    parts = []
    for name, dists, r, m, v, k in SUMMARY:
        joined = f"({c.tree_sql(r)}) t JOIN ({c.slab_sql(m, v)}) s USING (d) JOIN ({c.cell_sql(k)}) g USING (d)"
        values = {"tbin": c.tbin_sql(m), "slab": "s.candidates", "cell": "g.candidates", "brute": "((SELECT count(*) FROM q) * (SELECT count(*) FROM d))"}
        ratios = ", ".join(f"CAST({e} AS DOUBLE) / nullif(t.candidates, 0) AS {n}" for n, e in values.items())
        parts.append(f"SELECT * FROM (WITH {sql.ctes(name)}, {c.asked_sql(dists)} SELECT '{name}' AS scenario, d, {ratios} FROM {joined})")
    return run, " UNION ALL ".join(parts)


def _w17():
    """What the data sets are: trajectories, entries, extents, and trajectories in a unit of volume."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = []
        for name in SCENARIOS:
            d = segments(spark, sf_dir, name)
            box = [f"max(greatest({a}0, {a}1)) - min(least({a}0, {a}1))" for a in "xyz"]
            out.append(c.row(d.agg(F.countDistinct("traj_id").alias("trajectories"), F.count(F.lit(1)).alias("entries"), *(F.expr(b).alias(f"{a}_extent") for a, b in zip("xyz", box)), F.expr("max(t1) - min(t0)").alias("t_extent")), scenario=name))
        return c.rows(out).withColumn("density", F.col("trajectories") / (F.col("x_extent") * F.col("y_extent") * F.col("z_extent")))

    box = ", ".join(f"max(greatest({a}0, {a}1)) - min(least({a}0, {a}1)) AS {a}_extent" for a in "xyz")
    parts = [f"SELECT * FROM (WITH {sql.ctes(n)} SELECT '{n}' AS scenario, count(DISTINCT traj_id) AS trajectories, count(*) AS entries, {box}, max(t1) - min(t0) AS t_extent FROM d)" for n in SCENARIOS]
    return run, f"SELECT *, trajectories / (x_extent * y_extent * z_extent) AS density FROM ({' UNION ALL '.join(parts)})"


def _w18():
    """Entries cut into parts before TREE, so that a box holds less than a segment: boxes that queries reach, what these
    stand for in whole segments, and the pairs of trajectories found."""
    dists, cuts = (0.31, 3.1), (1, 2, 4)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = c.prepared(spark, sf_dir, "dense")
        out = []
        for k in cuts:
            cut = geometry.splice(d, k).withColumn("seg_id", F.col("seg_id") * k + F.col("part")).drop("part") if k > 1 else d
            reached = c.tree(q, cut, 1, dists)
            for x in dists:
                pairs = search.splice_search(q, d, x, k).select("q_traj", "traj_id").distinct().agg(F.count(F.lit(1)).alias("pairs"))
                out.append(c.row(c.with_all([reached.where(F.col("d") == x), pairs]), parts=k))
        return c.rows(out).withColumn("segments", F.col("candidates") / F.col("parts"))

    parts = []
    for k in cuts:
        at = lambda a, i: f"CASE WHEN {i} = 0 THEN {a}0 WHEN {i} = {k} THEN {a}1 ELSE {a}0 + ({a}1 - {a}0) * ({i}) / CAST({k} AS DOUBLE) END"
        cut = ", ".join(f"{at(a, 'i')} AS {a}0, {at(a, 'i + 1')} AS {a}1" for a in "txyz")
        source = f"(SELECT traj_id, seg_id * {k} + i AS seg_id, {cut} FROM d, unnest(range({k})) u(i))"
        pairs = f"SELECT dist AS d, count(*) AS pairs FROM (SELECT DISTINCT dist, q_traj, traj_id FROM ({sql.match('dist')})) GROUP BY 1"
        parts.append(c.label_sql({"parts": k}, f"SELECT *, candidates / CAST({k} AS DOUBLE) AS segments FROM ({c.tree_sql(1, source)}) JOIN ({pairs}) USING (d)"))
    return run, c.sweep_sql("dense", parts, dists)


def _w19():
    """Near a fixed place, all against all, and two classes of users."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        dense, event = segments(spark, sf_dir, "dense"), segments(spark, sf_dir, "event")
        point = search.fixed_point(spark, 10.0, 10.0, 10.0, 5.0, 25.0)
        hunters, prey = event.where("traj_id % 3 = 0"), event.where("traj_id % 3 <> 0")
        n = lambda f: f.agg(F.count(F.lit(1)).alias("n"))
        return c.rows([c.row(n(search.run(point, dense, 4.0, m=48)), search="fixed"), c.row(n(search.self_join(event, 1.0)), search="all"), c.row(n(search.run(hunters, prey, 10.0).select("q_traj", "traj_id").distinct()), search="classes")])

    point = "SELECT -1 AS traj_id, 0 AS seg_id, CAST(5 AS DOUBLE) AS t0, CAST(10 AS DOUBLE) AS x0, CAST(10 AS DOUBLE) AS y0, CAST(10 AS DOUBLE) AS z0, CAST(25 AS DOUBLE) AS t1, CAST(10 AS DOUBLE) AS x1, CAST(10 AS DOUBLE) AS y1, CAST(10 AS DOUBLE) AS z1"
    one = f"SELECT * FROM (WITH {sql.ctes('dense')}, pt AS ({point}) SELECT 'fixed' AS search, count(*) AS n FROM ({sql.match(4.0, sql.pairs('pt'))}))"
    two = f"SELECT * FROM (WITH {sql.ctes('event')} SELECT 'all' AS search, count(*) AS n FROM ({sql.match(1.0, sql.pairs('d', 'd', 'qs.traj_id < es.traj_id'))}))"
    three = f"SELECT * FROM (WITH {sql.ctes('event')} SELECT 'classes' AS search, count(*) AS n FROM (SELECT DISTINCT q_traj, traj_id FROM ({sql.match(10.0, sql.pairs('d', 'd', 'qs.traj_id % 3 = 0 AND es.traj_id % 3 <> 0'))})))"
    return run, f"{one} UNION ALL {two} UNION ALL {three}"


def _w20():
    """Where everything is at three times, on an x-y grid."""
    times = (5.5, 12.25, 20.75)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = segments(spark, sf_dir, "dense")
        return c.rows([c.row(search.snapshot(d, t, 4.0), t=t) for t in times])

    at = lambda a, t: f"{a}0 + ({a}1 - {a}0) / (t1 - t0) * (CAST({t} AS DOUBLE) - t0)"
    one = lambda t: f"SELECT CAST({t} AS DOUBLE) AS t, CAST(floor(({at('x', t)}) / CAST(4 AS DOUBLE)) AS BIGINT) AS cx, CAST(floor(({at('y', t)}) / CAST(4 AS DOUBLE)) AS BIGINT) AS cy, count(*) AS n FROM d WHERE t0 <= {t} AND t1 > {t} GROUP BY 1, 2, 3"
    return run, c.sweep_sql("dense", [one(t) for t in times])


#: Distance, bins, slabs, cells of the ablations.
ABLATION = {"walk": (20.0, 1000, 4, 20), "event": (5.0, 1000, 2, 4), "dense": (3.1, 48, 2, 10)}


def _w21():
    """What each way compares: cells with repeats (late), without (early, owner); slabs of one axis, of all three axes
    (intersect), several slabs of one axis with and without repeats; no axis; all pairs that overlap in time."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = []
        for name, (x, m, v, k) in ABLATION.items():
            q, d = c.prepared(spark, sf_dir, name)
            index, one = cells.build(d, k), lambda f: f.select("candidates")
            met = cells.candidates(q, index, x)
            early = geometry.repeated(met.drop("h"), "_arises")
            variants = {
                "late": one(c.cell(q, d, k, (x,))), "early": early.agg(F.count(F.lit(1)).alias("candidates")), "owner": one(c.cell_distinct(q, d, k, (x,))), "one axis": one(c.slab(q, d, m, v, (x,))),
                "no axis": c.tbin(q, d, m), **{mode: one(c.slab_pairs(q, d, m, v, (x,), mode)) for mode in ("intersect", "multi", "multi repeats")},
            }
            out += [c.row(f, scenario=name, variant=n) for n, f in variants.items()]
        return c.rows(out)

    parts = []
    for name, (x, m, v, k) in ABLATION.items():
        one = lambda s: f"(SELECT candidates FROM ({s}))"
        distinct = one(c.cell_distinct_sql(k))
        variants = {"late": one(c.cell_sql(k)), "early": distinct, "owner": distinct, "one axis": one(c.slab_sql(m, v)), "no axis": c.tbin_sql(m), **{mode: one(c.slab_pairs_sql(m, v, mode)) for mode in ("intersect", "multi", "multi repeats")}}
        rows = " UNION ALL ".join(c.select({"scenario": name, "variant": n}, {"candidates": s}) for n, s in variants.items())
        parts.append(f"SELECT * FROM (WITH {sql.ctes(name)}, {c.asked_sql((x,))} {rows})")
    return run, " UNION ALL ".join(parts)


_ALL = {
    "workload_w1": _tree_sweep("walk", (1, 2, 4, 8, 10, 16), WALK_D, 1000),
    "workload_w2": _w2(),
    "workload_w3": _bins_sweep("walk", (100, 1000, 5000, 10000)),
    "workload_w4": _slab_sweep("walk", 10000, (1, 2, 4, 8, 16), WALK_D),
    "workload_w5": _w5(),
    "workload_w6": _compare("walk", WALK_D, (10,), 10000, 4, 50),
    "workload_w7": _tree_sweep("event", (1, 2, 4, 8), EVENT_D[:3], 1000),
    "workload_w8": _bins_sweep("event", (100, 1000, 5000)),
    "workload_w9": _slab_sweep("event", 1000, (1, 2, 4, 8, 16), EVENT_D),
    "workload_w10": _compare("event", EVENT_D, (1,), 1000, 16, None, DOMAIN_D),
    "workload_w11": _tree_sweep("dense", (1, 2, 4, 8), DENSE_D, 48),
    "workload_w12": _bins_sweep("dense", (10, 100, 1000)),
    "workload_w13": _slab_sweep("dense", 1000, (1, 2, 4, 7, 8, 16), DENSE_D),
    "workload_w14": _w14(),
    "workload_w15": _compare("dense", DENSE_D, (1, 4), 1000, 2, None),
    "workload_w16": _w16(),
    "workload_w17": _w17(),
    "workload_w18": _w18(),
    "workload_w19": _w19(),
    "workload_w20": _w20(),
    "workload_w21": _w21(),
}


def queries() -> dict[str, Query]:
    return {k: f for k, (f, _) in _ALL.items()}


def oracles() -> dict[str, str]:
    return {k: s for k, (_, s) in _ALL.items()}
