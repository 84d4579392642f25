"""Registered searches, indexes and schedules on the scenarios, with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.geometry import AXES, rounded
from ..operators import batching, brute, cells, packed_tree, search, slabs, timebins
from ..operators.index import by_start, by_trajectory, extents
from ..session import kept, shared_folder
from ..sources.tables import save_by_time
from . import oracle_parts as sql
from .scenarios import BINS, CELLS, DISTANCE, LEAF, SCENARIOS, SLABS, queries_of, segments

Query = Callable[[SparkSession, str], DataFrame]


def both(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Queries and entries; the segments are made once."""
    d = kept(segments(spark, sf_dir, name))
    return queries_of(d, name), d


def shown(found: DataFrame) -> DataFrame:
    return found.withColumn("lo", rounded(F.col("lo"))).withColumn("hi", rounded(F.col("hi")))


def _search(name: str, method: Callable[[DataFrame, DataFrame, float], DataFrame], rounds: bool = False) -> Query:
    """With ``rounds`` the method itself makes its times as they are shown."""

    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = both(spark, sf_dir, name)
        found = method(q, d, DISTANCE[name])
        return found if rounds else shown(found)

    return f


def _methods(n: str) -> dict[str, Callable]:
    return {
        "tbin": lambda q, d, x: timebins.search(q, timebins.build(d, BINS[n]), x),
        "slab": lambda q, d, x: slabs.search(q, slabs.build(d, BINS[n], SLABS[n]), x),
        "cell": lambda q, d, x: cells.search(q, cells.build(d, CELLS[n]), x, rounded=True),
        "tree": lambda q, d, x: packed_tree.search(q, packed_tree.build(d, LEAF[n]), x),
    }


def searches() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for n in SCENARIOS:
        out |= {f"search_{k}_{n}": _search(n, f, k == "cell") for k, f in _methods(n).items()}
    m, v, c = BINS["dense"], SLABS["dense"], CELLS["dense"]
    variants = {
        "search_brute_dense": brute.search,
        "search_cell_late_dense": lambda q, d, x: cells.search(q, cells.build(d, c), x, "late"),
        "search_cell_early_dense": lambda q, d, x: cells.search(q, cells.build(d, c), x, "early"),
        "search_cell_owner_dense": lambda q, d, x: cells.search(q, cells.build(d, c), x, "owner"),
        "search_cell_axis_dense": lambda q, d, x: cells.search(q, cells.build(d, c, 1, 1), x),
        "search_slab_intersect_dense": lambda q, d, x: slabs.search(q, slabs.build(d, m, v), x, "intersect"),
        "search_slab_multi_dense": lambda q, d, x: slabs.search(q, slabs.build(d, m, v), x, "multi"),
        "search_slab_one_dense": lambda q, d, x: slabs.search(q, slabs.build(d, m, 1), x),
        "search_tbin_range_dense": lambda q, d, x: timebins.search(q, timebins.build(d, m, ids=True), x, "range"),
        "search_tbin_tight_dense": lambda q, d, x: timebins.search(q, timebins.build(d, m), x, tight=True),
        "search_tbin_scan_dense": lambda q, d, x: timebins.search(q, timebins.build(d, m), x, how="scan"),
        "search_tbin_classes_dense": lambda q, d, x: timebins.search_classes(q, timebins.build_classes(d, m), x),
        "search_cell_points_dense": lambda q, d, x: cells.search(q, cells.build(d, c, points=True), x),
        "search_tree_tasks_dense": lambda q, d, x: packed_tree.search(q, packed_tree.build(d, LEAF["dense"]), x, tasks=16),
        "search_tree_local_dense": lambda q, d, x: packed_tree.search_local(q, d, x, 16),
    }
    out |= {k: _search("dense", f) for k, f in variants.items()}
    out["search_tbin_classes_event"] = _search("event", lambda q, d, x: timebins.search_classes(q, timebins.build_classes(d, BINS["event"]), x))

    def spliced(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = both(spark, sf_dir, "dense")
        return search.splice_search(q, d, DISTANCE["dense"], 2).select("q_traj", "traj_id").distinct()

    def batched(spark: SparkSession, sf_dir: str) -> DataFrame:
        """SLAB with a result buffer: invocation by invocation, in the order of starts."""
        q, d = both(spark, sf_dir, "dense")
        x, index = DISTANCE["dense"], slabs.build(d, m, v)
        need = slabs.schedule(q, index, x).select(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), F.col("q_t0").alias("t0"), F.col("n_candidates").alias("demand"))
        plan = batching.by_capacity(need, 4 * index.time.entries.count(), ["t0", "q_traj", "q_seg"])
        return shown(batching.run_batches(q, plan, lambda part: slabs.search(part, index, x)))

    def by_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
        """CELL with a candidate buffer for each query: those whose buffer is too small go again, with fewer beside them."""
        q, d = both(spark, sf_dir, "dense")
        x, index = DISTANCE["dense"], cells.build(d, c)
        plan = batching.cell_rounds(cells.demand(q, index, x), 300 * extents(d).n)
        return shown(batching.run_batches(q, plan, lambda part: cells.search(part, index, x), "round", lambda part, i, k: cells.search(part, cells.chunk(index, i, k), x)))

    def partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Entries in folders of coarse time: only those that queries reach are read."""
        q, d = both(spark, sf_dir, "dense")
        path = shared_folder(spark, "by_time")
        save_by_time(d, path, 4.0)
        return shown(search.partitioned(q, path, 4.0, DISTANCE["dense"]))

    return out | {"search_tree_splice_dense": spliced, "search_slab_batched_dense": batched, "search_cell_rounds_dense": by_rounds, "search_partitioned_dense": partitioned}


def search_sql() -> dict[str, str]:
    out = {k: sql.search(k.rsplit("_", 1)[1], DISTANCE[k.rsplit("_", 1)[1]]) for k in searches()}
    still = ", ".join(f"{a}0 AS {a}1" for a in AXES)
    points = f"ps AS (SELECT traj_id, seg_id, t0, x0, y0, z0, t1, {still} FROM d)"
    out["search_cell_points_dense"] = f"WITH {sql.ctes('dense')}, {points} SELECT q_traj, q_seg, traj_id, seg_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({sql.match(DISTANCE['dense'], sql.pairs('q', 'ps'))})"
    out["search_tree_splice_dense"] = f"WITH {sql.ctes('dense')} SELECT DISTINCT q_traj, traj_id FROM ({sql.match(DISTANCE['dense'])})"
    return out


# ---- indexes -------------------------------------------------------------------------------------------------


def _extents(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = extents(segments(spark, sf_dir, n))
        row = [e.n, e.t_min, e.t_max, *e.lo, *e.hi, *e.largest, slabs.max_v(e)]
        names = ["n", "t_min", "t_max", *(f"{c}_lo" for c in AXES), *(f"{c}_hi" for c in AXES), *(f"{c}_largest" for c in AXES), "slab_cap"]
        return spark.createDataFrame([tuple(row)], ", ".join(f"{c} {'long' if c in ('n', 'slab_cap') else 'double'}" for c in names))

    return f


_EXT = "e AS (SELECT count(*) AS n, min(t0) AS t_min, max(t1) AS t_max, " + ", ".join(f"min(least({c}0, {c}1)) AS {c}_lo, max(greatest({c}0, {c}1)) AS {c}_hi, max(abs({c}1 - {c}0)) AS {c}_largest" for c in AXES) + " FROM d)"


def _bin(m: int, t: str = "t0") -> str:
    return f"least({m - 1}, greatest(0, CAST(floor(({t} - t_min) / ((t_max - t_min) / {m})) AS INTEGER)))"


def bins_cte(m: int) -> str:
    """e, b (entries with eid and bin) and dir (the directory)."""
    return f"""{_EXT}, b AS MATERIALIZED (SELECT d.*, row_number() OVER (ORDER BY t0, traj_id, seg_id) - 1 AS eid, {_bin(m)} AS bin FROM d, e),
    dir AS MATERIALIZED (SELECT bin, t_min + bin * ((t_max - t_min) / {m}) AS bin_start, greatest(t_min + (bin + 1) * ((t_max - t_min) / {m}), max(t1)) AS bin_end,
        min(eid) AS first, max(eid) AS last, count(*) AS n FROM b, e GROUP BY bin, t_min, t_max)"""


def _bins(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = timebins.build(segments(spark, sf_dir, n), BINS[n], ids=True)
        return index.directory.select("bin", "bin_start", "bin_end", "first", "last", "n", "end_cummax")

    return f


def _bins_sql(n: str) -> str:
    return f"WITH {sql.ctes(n)}, {bins_cte(BINS[n])} SELECT bin, bin_start, bin_end, first, last, n, max(bin_end) OVER (ORDER BY bin) AS end_cummax FROM dir"


def slab_expr(v: int, x: str, c: str) -> str:
    return f"CASE WHEN {c}_hi <= {c}_lo THEN 0 ELSE least({v - 1}, greatest(0, CAST(floor((({x}) - {c}_lo) / (({c}_hi - {c}_lo) / {v})) AS INTEGER))) END"


def slabs_cte(m: int, v: int) -> str:
    rows = " UNION ALL ".join(
        f"SELECT {i} AS axis, unnest(range({slab_expr(v, f'least({c}0, {c}1)', c)}, {slab_expr(v, f'greatest({c}0, {c}1)', c)} + 1)) AS slab, b.* FROM b, e" for i, c in enumerate(AXES)
    )
    return f"{bins_cte(m)}, look AS MATERIALIZED ({rows}), sdir AS MATERIALIZED (SELECT axis, slab, bin, count(*) AS n FROM look GROUP BY 1, 2, 3)"


def _slabs(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        i = slabs.build(segments(spark, sf_dir, n), BINS[n], SLABS[n])
        return i.directory.select("axis", F.col("slab").cast("int").alias("slab"), "bin", "lo", "hi", "n")

    return f


def _slabs_sql(n: str) -> str:
    return f"""WITH {sql.ctes(n)}, {slabs_cte(BINS[n], SLABS[n])} SELECT CAST(axis AS INTEGER) AS axis, CAST(slab AS INTEGER) AS slab, CAST(bin AS INTEGER) AS bin,
        CAST(sum(n) OVER w - n AS BIGINT) AS lo, CAST(sum(n) OVER w - 1 AS BIGINT) AS hi, n FROM sdir WINDOW w AS (PARTITION BY axis ORDER BY slab, bin)"""


def cell_expr(k: int, x: str, c: str) -> str:
    return f"CAST(CASE WHEN {c}_hi <= {c}_lo THEN 0 ELSE least({k - 1}, greatest(0, floor((({x}) - {c}_lo) / (({c}_hi - {c}_lo) / {k})))) END AS BIGINT)"


def cells_of(k: int, source: str, prefix: str = "", d: float | str = 0.0, keep: str = "traj_id, seg_id") -> str:
    """SELECT of each cell of each box."""
    names = {c: (f"{prefix}{c}0", f"{prefix}{c}1") for c in AXES}
    ranges = ", ".join(f"{cell_expr(k, f'least({a}, {b}) - CAST({d} AS DOUBLE)', c)} AS {c}a, {cell_expr(k, f'greatest({a}, {b}) + CAST({d} AS DOUBLE)', c)} AS {c}z" for c, (a, b) in names.items())
    return f"""SELECT {keep}, (cx * {k} + cy) * {k} + cz AS h FROM (SELECT *, unnest(range(za, zz + 1)) AS cz FROM (SELECT *, unnest(range(ya, yz + 1)) AS cy FROM
        (SELECT *, unnest(range(xa, xz + 1)) AS cx FROM (SELECT {source}.*, {ranges} FROM {source}, e))))"""


def _cells(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        return cells.build(segments(spark, sf_dir, n), CELLS[n]).directory

    return f


def _cells_sql(n: str) -> str:
    return f"""WITH {sql.ctes(n)}, {_EXT}, a AS ({cells_of(CELLS[n], 'd')}), g AS (SELECT h, count(*) AS n FROM a GROUP BY h)
        SELECT h, CAST(sum(n) OVER (ORDER BY h) - n AS BIGINT) AS a_min, CAST(sum(n) OVER (ORDER BY h) - 1 AS BIGINT) AS a_max, n FROM g"""


def _leaves(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        return packed_tree.leaves(segments(spark, sf_dir, n), LEAF[n])

    return f


def _leaves_sql(n: str) -> str:
    boxes = ", ".join(f"min(least({c}0, {c}1)) AS {c}lo, max(greatest({c}0, {c}1)) AS {c}hi" for c in AXES)
    return f"""WITH {sql.ctes(n)} SELECT traj_id, leaf, min(t0) AS tlo, max(t1) AS thi, {boxes}, count(*) AS n FROM
        (SELECT *, (row_number() OVER (PARTITION BY traj_id ORDER BY seg_id) - 1) // {LEAF[n]} AS leaf FROM d) GROUP BY traj_id, leaf"""


def _extents_sql(n: str) -> str:
    cap = ", ".join(f"CASE WHEN {c}_largest > 0 THEN floor(({c}_hi - {c}_lo) / {c}_largest) END" for c in AXES)
    names = ", ".join(f"{c}_{k}" for k in ("lo", "hi", "largest") for c in AXES)
    return f"WITH {sql.ctes(n)}, {_EXT} SELECT n, t_min, t_max, {names}, CAST(greatest(1, least({cap})) AS BIGINT) AS slab_cap FROM e"


def _segments(n: str) -> Query:
    return lambda spark, sf_dir: segments(spark, sf_dir, n)


# ---- schedules -----------------------------------------------------------------------------------------------


def _tbin_schedule(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = both(spark, sf_dir, n)
        return timebins.schedule(q, timebins.build(d, BINS[n], ids=True))

    return f


def _tbin_schedule_sql(n: str) -> str:
    return f"""WITH {sql.ctes(n)}, {bins_cte(BINS[n])} SELECT q.traj_id AS q_traj, q.seg_id AS q_seg, min(first) AS entry_min, max(last) AS entry_max, max(last) - min(first) + 1 AS n_candidates
        FROM q JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 GROUP BY 1, 2"""


def slab_schedule_cte(m: int, v: int, dist: float | None = None) -> str:
    """plan: q_traj, q_seg, dist, selector, n_candidates; for the one distance, or for those of qx."""
    asked = "" if dist is None else f"qx AS (SELECT q.*, CAST({dist} AS DOUBLE) AS dist FROM q), "
    axes = " UNION ALL ".join(
        f"SELECT qx.traj_id, qx.seg_id, qx.dist, qx.t0, qx.t1, {i} AS axis, {slab_expr(v, f'least({c}0, {c}1) - dist', c)} AS slab, {slab_expr(v, f'greatest({c}0, {c}1) + dist', c)} AS last_slab FROM qx, e" for i, c in enumerate(AXES)
    )
    return f"""{asked}{slabs_cte(m, v)}, elig AS (SELECT * FROM ({axes}) WHERE slab = last_slab),
    cnt AS (SELECT l.traj_id, l.seg_id, l.dist, l.axis, coalesce(sum(s.n), 0) AS n FROM elig l JOIN dir ON l.t0 < bin_end AND bin_start < l.t1 LEFT JOIN sdir s ON s.axis = l.axis AND s.slab = l.slab AND s.bin = dir.bin GROUP BY 1, 2, 3, 4),
    best AS (SELECT traj_id, seg_id, dist, min(struct_pack(n := n, axis := axis)) AS b FROM cnt GROUP BY 1, 2, 3),
    allb AS (SELECT q.traj_id, q.seg_id, sum(n) AS n FROM q JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 GROUP BY 1, 2),
    plan AS (SELECT qx.traj_id AS q_traj, qx.seg_id AS q_seg, qx.dist, CAST(coalesce(b.axis, -1) AS INTEGER) AS selector, CAST(CASE WHEN b IS NULL THEN coalesce(allb.n, 0) ELSE b.n END AS BIGINT) AS n_candidates
        FROM qx LEFT JOIN best USING (traj_id, seg_id, dist) LEFT JOIN allb USING (traj_id, seg_id))"""


def _slab_schedule(n: str) -> Query:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, d = both(spark, sf_dir, n)
        plan = slabs.schedule(q, slabs.build(d, BINS[n], SLABS[n]), DISTANCE[n])
        return plan.select(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), "selector", F.col("n_candidates").cast("long").alias("n_candidates"))

    return f


def _slab_schedule_sql(n: str) -> str:
    return f"WITH {sql.ctes(n)}, {slab_schedule_cte(BINS[n], SLABS[n], DISTANCE[n])} SELECT * EXCLUDE (dist) FROM plan"


def _ordered(how: Callable[[DataFrame], DataFrame], order: list[str]) -> Query:
    """Queries as they are laid out for a search: each row's place in its part."""

    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, _ = both(spark, sf_dir, "dense")
        laid = how(q).select(*order, F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_at"))
        before = F.lag(F.struct(*order)).over(Window.partitionBy("_part").orderBy("_at"))
        return laid.withColumn("in_order", F.coalesce(before <= F.struct(*order), F.lit(True))).select(*order, "in_order")

    return f


def queries() -> dict[str, Query]:
    out = searches() | {"layout_by_start_dense": _ordered(by_start, ["t0", "traj_id", "seg_id"]), "layout_by_trajectory_dense": _ordered(by_trajectory, ["traj_id", "seg_id"])}
    for n in SCENARIOS:
        out |= {f"segments_{n}": _segments(n), f"index_extents_{n}": _extents(n), f"index_bins_{n}": _bins(n), f"index_slabs_{n}": _slabs(n), f"index_cells_{n}": _cells(n), f"index_tree_leaves_{n}": _leaves(n)}
        out |= {f"schedule_tbin_{n}": _tbin_schedule(n), f"schedule_slab_{n}": _slab_schedule(n)}
    return out


def oracles() -> dict[str, str]:
    out = search_sql() | {"layout_by_start_dense": f"WITH {sql.ctes('dense')} SELECT t0, traj_id, seg_id, true AS in_order FROM q", "layout_by_trajectory_dense": f"WITH {sql.ctes('dense')} SELECT traj_id, seg_id, true AS in_order FROM q"}
    for n in SCENARIOS:
        out |= {
            f"segments_{n}": f"WITH {sql.ctes(n)} SELECT * FROM d", f"index_extents_{n}": _extents_sql(n), f"index_bins_{n}": _bins_sql(n), f"index_slabs_{n}": _slabs_sql(n),
            f"index_cells_{n}": _cells_sql(n), f"index_tree_leaves_{n}": _leaves_sql(n), f"schedule_tbin_{n}": _tbin_schedule_sql(n), f"schedule_slab_{n}": _slab_schedule_sql(n),
        }
    return out
