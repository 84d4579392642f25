"""Candidate and result counts of every method, in Spark and as SQL: the parts of measures and workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import AXES
from ..operators import batching, cells, index, packed_tree, slabs, tally, timebins
from ..operators.index import as_queries, at_distances, extents
from ..session import materialize
from . import oracle_parts as sql
from .searches import _EXT, bins_cte, both, cells_of, slab_expr, slab_schedule_cte, slabs_cte

OTHERS = "q_traj_id <> traj_id"


def prepared(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Queries and entries, built once for a sweep."""
    return both(spark, sf_dir, name)


def row(df: DataFrame, **labels) -> DataFrame:
    """One row of counts with its parameters before it."""
    kinds = {int: "long", float: "double", str: "string"}
    return df.select(*(F.lit(v).cast(kinds[type(v)]).alias(k) for k, v in labels.items()), "*")


def rows(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def n(df: DataFrame, name: str, expr=None) -> DataFrame:
    return df.agg(F.coalesce(F.sum(expr) if expr is not None else F.count(F.lit(1)), F.lit(0)).cast("long").alias(name))


#: Candidates that the buffer holds for each entry: 2 GiB of four-byte ids over 997,500 entries.
BUFFER_SHARE = 538


def per_distance(df: DataFrame, dists: tuple[float, ...], *names: str) -> DataFrame:
    """d and the named counts, a row for each distance; 0 where nothing was counted."""
    spark = df.sparkSession
    every = spark.createDataFrame([(float(x),) for x in dists], "d double")
    return every.join(df.withColumnRenamed("q_dist", "d"), "d", "left").select("d", *(F.coalesce(n, F.lit(0)).cast("long").alias(n) for n in names))


def asked_sql(dists: tuple[float, ...]) -> str:
    """ds (the distances) and qx (each query at each distance)."""
    values = ", ".join(f"(CAST({float(x)!r} AS DOUBLE))" for x in dists)
    return f"ds AS (SELECT * FROM (VALUES {values}) v(dist)), qx AS MATERIALIZED (SELECT q.*, dist FROM q, ds)"


def per_distance_sql(source: str, *names: str) -> str:
    """SELECT of d and the named counts from a source that has dist and may lack some."""
    return f"SELECT dist AS d, {', '.join(f'CAST(coalesce({n}, 0) AS BIGINT) AS {n}' for n in names)} FROM ds LEFT JOIN ({source}) USING (dist)"


# In each pair below, the first counts in Spark, the second is SQL over the tables d, q, ds and qx.


def tbin(q: DataFrame, d: DataFrame, m: int, tight: bool = False) -> DataFrame:
    return n(timebins.counted(as_queries(q), timebins.build(d, m), tight), "candidates", F.col("n"))


def tbin_sql(m: int) -> str:
    return f"(WITH {bins_cte(m)} SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM q JOIN dir ON q.t0 < bin_end AND bin_start < q.t1)"


def tbin_range(q: DataFrame, d: DataFrame, m: int) -> DataFrame:
    return n(timebins.schedule(q, timebins.build(d, m, ids=True)), "candidates", F.col("n_candidates"))


def tbin_range_sql(m: int) -> str:
    return f"(WITH {bins_cte(m)} SELECT CAST(sum(c) AS BIGINT) FROM (SELECT max(last) - min(first) + 1 AS c FROM q JOIN dir ON q.t0 < bin_end AND bin_start < q.t1 GROUP BY q.traj_id, q.seg_id))"


def slab(q: DataFrame, d: DataFrame, m: int, v: int, dists: tuple[float, ...]) -> DataFrame:
    """d, candidates, and how many queries a slab serves."""
    plan = slabs.schedule(at_distances(q, dists), slabs.build(d, m, v), "dist")
    return per_distance(plan.groupBy("q_dist").agg(F.sum("n_candidates").alias("candidates"), F.count_if(F.col("selector") >= 0).alias("served")), dists, "candidates", "served")


def slab_sql(m: int, v: int) -> str:
    plan = f"WITH {slab_schedule_cte(m, v)} SELECT dist, sum(n_candidates) AS candidates, count(*) FILTER (WHERE selector >= 0) AS served FROM plan GROUP BY dist"
    return per_distance_sql(plan, "candidates", "served")


def cell(q: DataFrame, d: DataFrame, k: int, dists: tuple[float, ...], limit: float = cells.REPLICATION) -> DataFrame:
    """d, candidates, once for each shared cell, from the directory."""
    need = cells.demand(at_distances(q, dists), cells.build(d, k, limit=limit), "dist")
    return per_distance(need.groupBy("dist").agg(F.sum("demand").alias("candidates")).withColumnRenamed("dist", "q_dist"), dists, "candidates")


def cell_demand_sql(k: int) -> str:
    """Demand of each query at each distance."""
    return f"""SELECT qx.traj_id, qx.seg_id, qx.dist, coalesce(sum(n), 0) AS demand FROM qx LEFT JOIN (WITH {_EXT}, a AS ({cells_of(k, 'd')}), g AS (SELECT h, count(*) AS n FROM a GROUP BY h), c AS ({cells_of(k, 'qx', d='dist', keep='traj_id, seg_id, dist')})
        SELECT traj_id, seg_id, dist, n FROM c JOIN g USING (h)) USING (traj_id, seg_id, dist) GROUP BY 1, 2, 3"""


def cell_sql(k: int) -> str:
    return per_distance_sql(f"SELECT dist, sum(demand) AS candidates FROM ({cell_demand_sql(k)}) GROUP BY dist", "candidates")


def cell_rounds(q: DataFrame, d: DataFrame, k: int, dists: tuple[float, ...]) -> DataFrame:
    """d, candidates, rounds: how often queries are launched with a buffer of BUFFER_SHARE candidates for an entry."""
    need = materialize(cells.demand(at_distances(q, dists), cells.build(d, k), "dist"))
    size = BUFFER_SHARE * total_entries(d)
    out = []
    for x in dists:
        mine = need.where(F.col("dist") == x)
        done = batching.cell_rounds(mine, size).agg(F.coalesce(F.max("round"), F.lit(0)).cast("long").alias("rounds"))
        out.append(with_all([mine.agg(F.lit(x).alias("d"), F.coalesce(F.sum("demand"), F.lit(0)).cast("long").alias("candidates")), done]))
    return rows(out)


def rounds_sql(need: str, size: str) -> str:
    """SELECT of dist and rounds: the redo rounds once more, as a recursion over how many queries are done."""
    return f"""SELECT dist, max(round) AS rounds FROM (WITH RECURSIVE s AS MATERIALIZED (SELECT dist, demand, row_number() OVER w - 1 AS i, sum(demand) OVER w - demand AS before, count(*) OVER (PARTITION BY dist) AS n FROM ({need}) WINDOW w AS (PARTITION BY dist ORDER BY demand, traj_id, seg_id)),
        r AS (SELECT DISTINCT dist, 0 AS round, CAST(0 AS BIGINT) AS p FROM s UNION ALL
        SELECT r.dist, r.round + 1, CASE WHEN count(*) FILTER (s.demand <= {size} // (s.n - r.p)) > r.p THEN count(*) FILTER (s.demand <= {size} // (s.n - r.p))
            ELSE r.p + greatest(1, count(*) FILTER (s.i >= r.p AND s.before + s.demand - f.before <= {size})) END
        FROM r JOIN s ON s.dist = r.dist JOIN s f ON f.dist = r.dist AND f.i = r.p GROUP BY r.dist, r.round, r.p) SELECT dist, round FROM r) GROUP BY dist"""


BUFFER_SQL = f"(SELECT {BUFFER_SHARE} * count(*) FROM d)"


def cell_rounds_sql(k: int) -> str:
    need = cell_demand_sql(k)
    return per_distance_sql(f"SELECT * FROM (SELECT dist, sum(demand) AS candidates FROM ({need}) GROUP BY dist) JOIN ({rounds_sql(need, BUFFER_SQL)}) USING (dist)", "candidates", "rounds")


def cell_distinct(q: DataFrame, d: DataFrame, k: int, dists: tuple[float, ...]) -> DataFrame:
    i = cells.build(d, k)
    if cells.summed(i):
        return q.sparkSession.createDataFrame([(float(x), cells.shared(q, i, x)[1]) for x in dists], "d double, candidates long")
    pairs = cells.owned(cells.candidates(at_distances(q, dists), i, "dist"), i.grid)
    return per_distance(pairs.groupBy("q_dist").agg(F.count(F.lit(1)).alias("candidates")), dists, "candidates")


def cell_distinct_sql(k: int) -> str:
    pairs = f"WITH {_EXT}, a AS ({cells_of(k, 'd')}), c AS ({cells_of(k, 'qx', d='dist', keep='traj_id, seg_id, dist')}) SELECT DISTINCT c.dist, c.traj_id, c.seg_id, a.traj_id AS t, a.seg_id AS s FROM c JOIN a USING (h)"
    return per_distance_sql(f"SELECT dist, count(*) AS candidates FROM ({pairs}) GROUP BY dist", "candidates")


def slab_pairs(q: DataFrame, d: DataFrame, m: int, v: int, dists: tuple[float, ...], mode: str) -> DataFrame:
    """d, candidates that stand in the lists of all axes (``intersect``), or in some slab of the axis with the fewest
    (``multi``; with repeats, ``multi repeats``)."""
    index = slabs.build(d, m, v)
    if mode != "intersect" and slabs.summed(index):
        got = slabs.multi_counts(at_distances(q, dists), index, "dist").groupBy("q_dist").agg(F.sum("repeats" if mode.endswith("repeats") else "once").alias("candidates"))
        return per_distance(got, dists, "candidates")
    pairs = slabs.every_pair(at_distances(q, dists), index, "dist", mode.split()[0])
    # A pair arises so often: its rows weigh one together.  Summed as whole numbers of rows for each weight.
    weighed = pairs.where("_arises IS NOT NULL").groupBy("q_dist", "_arises").agg(F.count(F.lit(1)).alias("n"))
    n = F.sum("n") if mode.endswith("repeats") else F.sum(F.expr("n div _arises"))
    return per_distance(weighed.groupBy("q_dist").agg(n.alias("candidates")), dists, "candidates")


def slab_pairs_sql(m: int, v: int, mode: str) -> str:
    spans = " UNION ALL ".join(
        f"SELECT qx.traj_id, qx.seg_id, qx.dist, qx.t0, qx.t1, {i} AS axis, {slab_expr(v, f'least({c}0, {c}1) - dist', c)} AS a, {slab_expr(v, f'greatest({c}0, {c}1) + dist', c)} AS z FROM qx, e" for i, c in enumerate(AXES)
    )
    met = "SELECT s.dist, s.traj_id, s.seg_id, l.traj_id AS t, l.seg_id AS u, l.axis FROM {} s JOIN dir ON s.t0 < bin_end AND bin_start < s.t1 JOIN look l ON l.axis = s.axis AND l.bin = dir.bin AND l.slab BETWEEN s.a AND s.z"
    if mode == "intersect":
        pairs = f"SELECT dist FROM ({met.format('spans')}) GROUP BY dist, traj_id, seg_id, t, u HAVING count(DISTINCT axis) = 3"
    else:
        one = "(SELECT * FROM spans QUALIFY row_number() OVER (PARTITION BY traj_id, seg_id, dist ORDER BY z - a, axis) = 1)"
        pairs = f"SELECT {'' if mode.endswith('repeats') else 'DISTINCT'} * FROM ({met.format(one)})"
    return per_distance_sql(f"WITH {slabs_cte(m, v)}, spans AS ({spans}) SELECT dist, count(*) AS candidates FROM ({pairs}) GROUP BY dist", "candidates")


def tree(q: DataFrame, d: DataFrame, r: int, dists: tuple[float, ...]) -> DataFrame:
    """d, and members of the leaves that queries reach."""
    met = packed_tree.demand(at_distances(q, dists), materialize(packed_tree.leaves(d, r)), r, "dist")
    return per_distance(met.groupBy("q_dist").agg(F.sum("n").alias("candidates")), dists, "candidates")


def leaves_cte(r: int, source: str = "d") -> str:
    boxes = ", ".join(f"min(least({c}0, {c}1)) AS {c}lo, max(greatest({c}0, {c}1)) AS {c}hi" for c in AXES)
    return f"leaf AS MATERIALIZED (SELECT traj_id, k, min(t0) AS tlo, max(t1) AS thi, {boxes}, count(*) AS n FROM (SELECT *, (row_number() OVER (PARTITION BY traj_id ORDER BY seg_id) - 1) // {r} AS k FROM {source}) GROUP BY 1, 2)"


def tree_sql(r: int, source: str = "d") -> str:
    space = " AND ".join(f"{c}lo <= greatest(qx.{c}0, qx.{c}1) + dist AND {c}hi >= least(qx.{c}0, qx.{c}1) - dist" for c in AXES)
    return per_distance_sql(f"WITH {leaves_cte(r, source)} SELECT dist, sum(n) AS candidates FROM qx JOIN leaf ON tlo < qx.t1 AND qx.t0 < thi AND {space} GROUP BY dist", "candidates")


def overlapping(q: DataFrame, d: DataFrame) -> DataFrame:
    """Pairs of other trajectories whose times overlap: all that do, less those of the same one; none is made."""
    qs = as_queries(q)
    own = index.overlapping(qs.withColumn("traj_id", F.col("q_traj_id")), d, ("traj_id",)).select((-F.col("n")).alias("n"))
    return n(index.overlapping(qs, d).select("n").unionByName(own), "pairs", F.col("n"))


OVERLAPPING_SQL = "(SELECT count(*) FROM q JOIN d ON q.t0 < d.t1 AND d.t0 < q.t1 AND q.traj_id <> d.traj_id)"


def found(q: DataFrame, d: DataFrame, m: int, dists: tuple[float, ...]) -> DataFrame:
    """d, results, and entries that some query comes near."""
    hits = tally.reached(q, d, dists)
    return per_distance(hits.select(F.col("dist").alias("q_dist"), "results", F.col("entry_hits").alias("entries")), dists, "results", "entries")


FOUND_SQL = per_distance_sql(f"SELECT dist, count(*) AS results, count(DISTINCT (traj_id, seg_id)) AS entries FROM ({sql.match('dist')}) GROUP BY dist", "results", "entries")


def found_sql(dist: float) -> str:
    return f"(SELECT count(*) FROM ({sql.match(dist)}))"


def with_all(parts: list[DataFrame]) -> DataFrame:
    """Counts of one setting side by side (each is one row)."""
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)
    return out


def total_entries(d: DataFrame) -> int:
    return extents(d).n


def select(labels: dict, values: dict[str, str]) -> str:
    """SELECT of one row: labels as literals, values as subqueries."""
    kinds = {int: "BIGINT", float: "DOUBLE", str: "VARCHAR"}
    head = [f"CAST({v!r} AS {kinds[type(v)]}) AS {k}" for k, v in labels.items()]
    return "SELECT " + ", ".join(head + [f"{v} AS {k}" for k, v in values.items()])


def label_sql(labels: dict, select_: str) -> str:
    """Parameters as literals before the columns of a SELECT."""
    kinds = {int: "BIGINT", float: "DOUBLE", str: "VARCHAR"}
    return "SELECT " + ", ".join(f"CAST({v!r} AS {kinds[type(v)]}) AS {k}" for k, v in labels.items()) + f", * FROM ({select_})"


def sweep_sql(name: str, parts: list[str], dists: tuple[float, ...] = ()) -> str:
    more = f", {asked_sql(dists)}" if dists else ""
    return f"WITH {sql.ctes(name)}{more} " + " UNION ALL ".join(parts)
