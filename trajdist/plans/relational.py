"""The relational and function surface around the searches: one query for each operator."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry
from ..operators import timebins
from ..operators.index import as_queries, overlapping
from ..session import materialize
from ..sources.tables import table
from . import oracle_parts as sql
from . import sqlapi
from .scenarios import segments
from .searches import _EXT, Query, both, cells_of

_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}

Tables = Callable[[str], DataFrame]


def op(name: str, oracle: str | None = None):
    """Registers f(t, spark), where t reads a table."""

    def add(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(lambda n: table(spark, sf_dir, n), spark)

        _QUERIES[f"ops_{name}"] = run
        if oracle:
            _SQL[f"ops_{name}"] = oracle
        return f

    return add


def op_dir(name: str, oracle: str | None = None):
    """Registers f(spark, sf_dir)."""

    def add(f):
        _QUERIES[f"ops_{name}"] = f
        if oracle:
            _SQL[f"ops_{name}"] = oracle
        return f

    return add


@op("o1_project", "SELECT event_id, value * 2 AS twice, CASE WHEN value > 100 THEN 'high' WHEN value > 30 THEN 'mid' ELSE 'low' END AS band FROM events")
def _(t, spark):
    return t("events").select("event_id", (F.col("value") * 2).alias("twice"), F.when(F.col("value") > 100, "high").when(F.col("value") > 30, "mid").otherwise("low").alias("band"))


@op("o2_filter", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '%-%' AND regexp_matches(o_orderpriority, '^[12]') AND o_orderdate IS NOT NULL")
def _(t, spark):
    c = F.col
    return t("orders").where(c("o_totalprice").between(1000, 200000) & c("o_orderstatus").isin("F", "O") & c("o_orderpriority").like("%-%") & c("o_orderpriority").rlike("^[12]") & c("o_orderdate").isNotNull()).select("o_orderkey", "o_orderpriority")


@op_dir("o3_interval", f"WITH {sql.ctes('event')} SELECT traj_id, seg_id, t0, t1 FROM d WHERE t1 > 100 AND t0 < 200")
def _(spark, sf_dir):
    return segments(spark, sf_dir, "event").where("t1 > 100 AND t0 < 200").select("traj_id", "seg_id", "t0", "t1")


_LABELS = "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@op("o4_broadcast_join", _LABELS)
def _(t, spark):
    # Nations and regions are tables of fixed, small size.
    return t("supplier").join(F.broadcast(t("nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", "n_name", "r_name")


@op("o5_merge_join", "SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def _(t, spark):
    return t("orders").join(t("lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"))


@op("o6_hash_join", "SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(t, spark):
    return t("orders").join(t("customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"))


@op("o7_theta_join", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_name < b.n_name")
def _(t, spark):
    a, b = t("nation").alias("a"), t("nation").alias("b")
    return a.join(b, (F.col("a.n_regionkey") < F.col("b.n_regionkey")) & (F.col("a.n_name") < F.col("b.n_name"))).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@op_dir("o8_interval_join", f"WITH {sql.ctes('event')} SELECT q.traj_id AS q_traj, q.seg_id AS q_seg, count(*) AS n FROM q JOIN d ON q.t0 < d.t1 AND d.t0 < q.t1 GROUP BY 1, 2")
def _(spark, sf_dir):
    q, d = both(spark, sf_dir, "event")
    met = overlapping(as_queries(q), d).where("n > 0")
    return met.groupBy(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg")).agg(F.sum("n").alias("n"))


def _asof(t, orders: DataFrame) -> DataFrame:
    """Each order with its customer's last event before it.

    Rows meet inside a customer's day, so a customer of very many rows is spread over tasks; what the days before leave
    is carried over one row for each day.  An order without customer or date has no event."""
    o = orders.select((F.col("o_custkey") % 15).alias("k"), F.col("o_orderdate").alias("ts"), "o_orderkey", F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("side"))
    known = t("events").where("user_id is not null and ts is not null").groupBy(F.col("user_id").alias("k"), "ts").agg(F.max("event_id").alias("event_id"))
    rows = o.unionByName(known.select("k", "ts", F.lit(None).cast("long").alias("o_orderkey"), "event_id", F.lit(0).alias("side"))).withColumn("day", F.to_date("ts"))
    last = F.max(F.when(F.col("side") == 0, F.struct("ts", "event_id")))["event_id"]
    before = Window.partitionBy("k").orderBy("day").rowsBetween(Window.unboundedPreceding, -1)
    carried = rows.groupBy("k", "day").agg(last.alias("last")).select("k", "day", F.last("last", ignorenulls=True).over(before).alias("carried"))
    inside = Window.partitionBy("k", "day").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    met = rows.withColumn("event_id", F.last("event_id", ignorenulls=True).over(inside)).where("side = 1")
    return met.join(carried, ["k", "day"], "left").select("o_orderkey", F.coalesce("event_id", "carried").alias("event_id"))


@op("o9_asof_join", "SELECT o.o_orderkey, e.event_id FROM orders o ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY 1, 2) e ON o.o_custkey % 15 = e.user_id AND o.o_orderdate >= e.ts")
def _(t, spark):
    return _asof(t, t("orders"))


@op("o10_outer_join", "SELECT c_custkey, o_orderkey FROM customer FULL OUTER JOIN orders ON c_custkey = o_custkey")
def _(t, spark):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "full_outer").select("c_custkey", "o_orderkey")


@op("o10_left_join", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
def _(t, spark):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", "o_orderkey")


@op("o10_right_join", "SELECT vec_id, l.doc_id, quality FROM embeddings e RIGHT JOIN labels l ON e.vec_id = l.doc_id")
def _(t, spark):
    return t("embeddings").join(t("labels"), F.col("vec_id") == F.col("doc_id"), "right").select("vec_id", "doc_id", "quality")


@op("o11_semi_anti", "SELECT doc_id, doc_id IN (SELECT doc_id FROM labels) AS labelled FROM documents")
def _(t, spark):
    d, l = t("documents"), t("labels").select("doc_id")
    return d.join(l, "doc_id", "left_semi").select("doc_id", F.lit(True).alias("labelled")).union(d.join(l, "doc_id", "left_anti").select("doc_id", F.lit(False)))


@op("o12_cross_self_join", "SELECT r_name, n_name, (SELECT count(*) FROM nation m WHERE m.n_regionkey = n.n_regionkey) AS mates FROM region, nation n")
def _(t, spark):
    n, m = t("nation").alias("n"), t("nation").select("n_regionkey").alias("m")
    mates = n.join(m, "n_regionkey").groupBy("n_name").agg(F.count(F.lit(1)).alias("mates"))
    return t("region").select("r_name").crossJoin(mates).select("r_name", "n_name", "mates")


@op("o13_explode", "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, CAST(embedding[i] AS DOUBLE) AS x FROM embeddings, unnest(range(1, len(embedding) + 1)) AS u(i)")
def _(t, spark):
    return t("embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "x")).withColumn("x", F.col("x").cast("double"))


@op("o13_explode_outer", "SELECT conv_id, turn, unnest(CASE WHEN len(w) = 0 THEN [NULL] ELSE w END) AS word FROM (SELECT conv_id, turn, list_filter(string_split(coalesce(text, ''), ' '), lambda x: x <> '') AS w FROM conversations)")
def _(t, spark):
    words = F.filter(F.split(F.coalesce("text", F.lit("")), " "), lambda x: x != "")
    return t("conversations").select("conv_id", "turn", F.explode_outer(words).alias("word"))


@op("o13_inline", "SELECT n_nationkey, v.k, v.label FROM nation, LATERAL (VALUES (n_nationkey, n_name), (n_regionkey, 'region')) v(k, label)")
def _(t, spark):
    n = t("nation")
    return n.select("n_nationkey", F.inline(F.array(F.struct(F.col("n_nationkey").alias("k"), F.col("n_name").alias("label")), F.struct(F.col("n_regionkey").alias("k"), F.lit("region").alias("label")))))


@op("o13_stack", "SELECT s_suppkey, v.name, v.value FROM supplier, LATERAL (VALUES ('nation', CAST(s_nationkey AS DOUBLE)), ('balance', s_acctbal)) v(name, value)")
def _(t, spark):
    return t("supplier").select("s_suppkey", F.stack(F.lit(2), F.lit("nation"), F.col("s_nationkey").cast("double"), F.lit("balance"), F.col("s_acctbal")).alias("name", "value"))


@op("o13_lateral_join", "SELECT r_regionkey, count(n_nationkey) AS nations, min(n_name) AS first FROM region LEFT JOIN nation ON n_regionkey = r_regionkey GROUP BY 1")
def _(t, spark):
    inner = "LATERAL (SELECT count(*) AS nations, min(n_name) AS first FROM {n} WHERE n_regionkey = r_regionkey)"
    return spark.sql(f"SELECT r_regionkey, nations, first FROM {{r}}, {inner}", r=t("region"), n=t("nation"))


@op("o14_hash_aggregate", "SELECT event_type, count(*) AS n, min(value) AS lo, max(value) AS hi, min(event_id) AS first FROM events GROUP BY event_type")
def _(t, spark):
    return t("events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.min("event_id").alias("first"))


@op("o15_sort_aggregate", "SELECT user_id, string_agg(CAST(event_id AS VARCHAR), ',' ORDER BY event_id) AS path FROM events GROUP BY user_id")
def _(t, spark):
    return t("events").groupBy("user_id").agg(F.concat_ws(",", F.transform(F.array_sort(F.collect_list("event_id")), lambda x: x.cast("string"))).alias("path"))


@op("o16_count_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT (l_orderkey, l_linenumber)) AS lines FROM lineitem")
def _(t, spark):
    return t("lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_orderkey", "l_linenumber").alias("lines"))


@op("o17_approximate")
def _(t, spark):
    return t("events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


@op("o18_filtered_aggregate", "SELECT user_id, count(*) FILTER (WHERE value > 30) AS high, count(*) FILTER (WHERE event_type = 'error') AS errors FROM events GROUP BY user_id")
def _(t, spark):
    return t("events").groupBy("user_id").agg(F.count_if(F.col("value") > 30).alias("high"), F.count_if(F.col("event_type") == "error").alias("errors"))


_SETS = "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS gid, count(*) AS n FROM lineitem GROUP BY {}"


@op("o19_cube", _SETS.format("CUBE (l_returnflag, l_linestatus)"))
def _(t, spark):
    return t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"))


@op("o19_rollup", _SETS.format("ROLLUP (l_returnflag, l_linestatus)"))
def _(t, spark):
    return t("lineitem").rollup("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"))


@op("o19_grouping_sets", _SETS.format("GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def _(t, spark):
    li = t("lineitem")
    return li.groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], "l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"))


@op("o20_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events WHERE event_type IN ('click', 'view') GROUP BY user_id")
def _(t, spark):
    return t("events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0).where("click > 0 OR view > 0")


@op("o20_unpivot", "SELECT doc_id, name, CAST(value AS INTEGER) AS value FROM (UNPIVOT (SELECT doc_id, CAST(quality AS INTEGER) AS quality, CAST(toxic AS INTEGER) AS toxic FROM labels) ON quality, toxic INTO NAME name VALUE value)")
def _(t, spark):
    return t("labels").select("doc_id", F.col("quality").cast("int"), F.col("toxic").cast("int")).unpivot("doc_id", ["quality", "toxic"], "name", "value")


@op("o21_arg_min_max", "SELECT user_id, arg_max(event_id, (value, event_id)) AS highest, arg_min(event_id, (value, event_id)) AS lowest FROM events GROUP BY user_id")
def _(t, spark):
    key = F.struct("value", "event_id")
    return t("events").groupBy("user_id").agg(F.max_by("event_id", key).alias("highest"), F.min_by("event_id", key).alias("lowest"))


def _places(e: str, n: int = 6) -> str:
    return f"CAST(round({e}, {n}) AS DOUBLE)"


@op("o22_statistics", f"SELECT event_type, {_places('stddev(value)')} AS sd, {_places('var_samp(value)')} AS var, {_places('corr(value, event_id)', 9)} AS corr, {_places('covar_samp(value, user_id)')} AS cov FROM events GROUP BY event_type")
def _(t, spark):
    r = lambda e, n=6: F.round(e, n)
    return t("events").groupBy("event_type").agg(r(F.stddev("value")).alias("sd"), r(F.variance("value")).alias("var"), r(F.corr("value", "event_id"), 9).alias("corr"), r(F.covar_samp("value", "user_id")).alias("cov"))


@op("o22_shape", f"""SELECT user_id, {_places('(sum(pow(value - m, 3)) / count(*)) / pow(sum(pow(value - m, 2)) / count(*), 1.5)', 5)} AS skew,
    {_places('(sum(pow(value - m, 4)) / count(*)) / pow(sum(pow(value - m, 2)) / count(*), 2) - 3', 5)} AS kurt FROM (SELECT *, avg(value) OVER (PARTITION BY user_id) AS m FROM events) GROUP BY user_id""")
def _(t, spark):
    return t("events").groupBy("user_id").agg(F.round(F.skewness("value"), 5).alias("skew"), F.round(F.kurtosis("value"), 5).alias("kurt"))


@op("o22_histogram", "SELECT CAST(least(9, greatest(0, floor((value - lo) / ((hi - lo) / 10)))) AS BIGINT) AS bucket, count(*) AS n FROM events, (SELECT min(value) AS lo, max(value) AS hi FROM events) GROUP BY 1")
def _(t, spark):
    e = t("events")
    r = e.agg(F.min("value").alias("lo"), F.max("value").alias("hi")).first()
    return e.groupBy(F.least(F.lit(9), F.greatest(F.lit(0), F.floor((F.col("value") - r.lo) / ((r.hi - r.lo) / 10)))).cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@op("o23_ranking", """SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd
    FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value, event_id)""")
def _(t, spark):
    w = Window.partitionBy("user_id").orderBy("value", "event_id")
    return t("events").select("event_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


@op("o24_analytic", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(t, spark):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t("events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("value").over(w).alias("first"), F.nth_value("value", 2).over(w).alias("second"))


@op("o25_frames", """SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running,
    max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS recent FROM events""")
def _(t, spark):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    r = Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-100, 0)
    return t("events").select("event_id", F.sum("event_id").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.max("value").over(w.rowsBetween(-2, 2)).alias("near"), F.count(F.lit(1)).over(r).alias("recent"))


@op("o26_islands", """SELECT user_id, island, count(*) AS n, min(event_id) AS first FROM (SELECT *, CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS island FROM (
    SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) < 14400000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY 1, 2""")
def _(t, spark):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.expr("timestampdiff(MICROSECOND, before, ts)")
    e = t("events").withColumn("before", F.lag("ts").over(w)).withColumn("fresh", F.when(gap < 14400000000, 0).otherwise(1))
    return e.withColumn("island", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0))).groupBy("user_id", "island").agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("first"))


@op("o27_sort", "SELECT doc_id, row_number() OVER (ORDER BY lang DESC NULLS LAST, n_chars ASC NULLS FIRST, doc_id) AS place FROM documents")
def _(t, spark):
    # One order over the whole table, numbered by range parts instead of one window.
    from ..operators.index import dense_ids

    d = t("documents").select("doc_id", "lang", "n_chars")
    # The languages are few; their order comes to the driver.
    langs = sorted((r[0] for r in d.select("lang").distinct().collect() if r[0] is not None), reverse=True)
    rank = F.coalesce(*(F.when(F.col("lang") == l, F.lit(i)) for i, l in enumerate(langs)), F.lit(len(langs)))
    return dense_ids(d.withColumn("_k", rank), ["_k", "n_chars", "doc_id"], "_i").select("doc_id", (F.col("_i") + 1).alias("place"))


@op("o28_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def _(t, spark):
    return t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20).select("o_orderkey", "o_totalprice")


@op("o28_top_k_per_group", "SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 3")
def _(t, spark):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return t("events").withColumn("r", F.row_number().over(w)).where("r <= 3").select("user_id", "event_id")


@op("o29_union", "SELECT user_id AS id, 'event' AS kind FROM events UNION SELECT c_custkey, 'customer' FROM customer")
def _(t, spark):
    a = t("events").select(F.col("user_id").alias("id"), F.lit("event").alias("kind"))
    b = t("customer").select(F.lit("customer").alias("kind"), F.col("c_custkey").alias("id"))
    return a.unionByName(b).distinct()


@op("o30_set_operations", "(SELECT l_partkey AS k, 'both' AS side FROM (SELECT l_partkey FROM lineitem WHERE l_tax > 0.04 INTERSECT ALL SELECT l_partkey FROM lineitem WHERE l_discount > 0.05)) UNION ALL (SELECT l_partkey, 'rest' FROM (SELECT l_partkey FROM lineitem WHERE l_tax > 0.04 EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_discount > 0.05))")
def _(t, spark):
    a, b = t("lineitem").where("l_tax > 0.04").select("l_partkey"), t("lineitem").where("l_discount > 0.05").select("l_partkey")
    return a.intersectAll(b).select(F.col("l_partkey").alias("k"), F.lit("both").alias("side")).union(a.exceptAll(b).select("l_partkey", F.lit("rest")))


_SUBQUERY = """SELECT c_custkey, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS n FROM customer
    WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000) AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3) AND c_acctbal > (SELECT avg(c_acctbal) / 2 FROM customer)"""


@op("o31_subqueries", _SUBQUERY)
def _(t, spark):
    for n in ("customer", "orders", "nation"):
        t(n).createOrReplaceTempView(f"sub_{n}")
    text = _SUBQUERY
    for n in ("customer", "orders", "nation"):
        text = text.replace(f"FROM {n}", f"FROM sub_{n}")
    return spark.sql(text)


_RECURSIVE = "WITH RECURSIVE steps(n, size) AS (SELECT 0 AS n, count(l_orderkey) AS size FROM {lineitem} UNION ALL SELECT n + 1, {up} FROM steps WHERE size > 1) SELECT n, size FROM steps"


@op("o32_recursive_cte", _RECURSIVE.format(lineitem="lineitem", up="(size + 15) // 16"))
def _(t, spark):
    """Nodes of each level of a packed tree over the rows of lineitem, sixteen to a node."""
    return spark.sql(_RECURSIVE.replace("{up}", "(size + 15) div 16"), lineitem=t("lineitem"))


@op("o33_strings", """SELECT p_partkey, lower(p_name) AS low, substr(p_type, 1, 5) AS head, instr(p_name, 'a') AS at, regexp_extract(p_brand, '[0-9]+') AS digits, lpad(CAST(p_size AS VARCHAR), 4, '0') AS size,
    concat_ws('-', p_brand, p_type) AS both, levenshtein(p_brand, p_type) AS distance, split_part(p_type, ' ', 1) AS first FROM part""")
def _(t, spark):
    c = F.col
    return t("part").select(
        "p_partkey", F.lower("p_name").alias("low"), F.substring("p_type", 1, 5).alias("head"), F.instr("p_name", "a").cast("long").alias("at"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("digits"), F.lpad(c("p_size").cast("string"), 4, "0").alias("size"),
        F.concat_ws("-", "p_brand", "p_type").alias("both"), F.levenshtein("p_brand", "p_type").cast("long").alias("distance"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("first"),
    )


@op("o34_dates", """SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS month, extract(year FROM o_orderdate) AS year, extract(dow FROM o_orderdate) + 1 AS day, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days,
    o_orderdate + INTERVAL 36 HOUR AS later FROM orders""")
def _(t, spark):
    d = F.col("o_orderdate")
    return t("orders").select(
        "o_orderkey", F.date_trunc("month", d).cast("timestamp_ntz").alias("month"), F.year(d).cast("long").alias("year"), F.dayofweek(d).cast("long").alias("day"), F.datediff(d, F.lit("1992-01-01").cast("date")).cast("long").alias("days"),
        (d + F.expr("INTERVAL '36' HOUR")).alias("later"),
    )


@op("o35_math", """SELECT event_id, floor(value) AS lo, ceil(value) AS hi, sqrt(value) AS root, CAST(round(pow(value, 2), 6) AS DOUBLE) AS square, CAST(round(sqrt(value * value + 9), 6) AS DOUBLE) AS far, ((event_id - 50) % 7 + 7) % 7 AS mod, event_id // 7 AS div, greatest(value, 30) AS most, least(value, 30) AS least,
    CAST(CASE WHEN value < 0 THEN 0 WHEN value >= 600 THEN 7 ELSE floor(value / 100) + 1 END AS BIGINT) AS bucket FROM events""")
def _(t, spark):
    v = F.col("value")
    return t("events").select(
        "event_id", F.floor(v).cast("double").alias("lo"), F.ceil(v).cast("double").alias("hi"), F.sqrt(v).alias("root"), F.round(F.pow(v, F.lit(2)), 6).alias("square"), F.round(F.hypot(v, F.lit(3.0)), 6).alias("far"), F.expr("pmod(event_id - 50, 7)").alias("mod"), F.expr("event_id div 7").alias("div"),
        F.greatest(v, F.lit(30.0)).alias("most"), F.least(v, F.lit(30.0)).alias("least"), F.expr("width_bucket(value, 0, 600, 6)").alias("bucket"),
    )


@op("o36_arrays", """SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, CAST(list_max(embedding) AS DOUBLE) AS most, len(list_distinct(embedding)) AS different, len(list_filter(embedding, lambda x: x > 3)) > 0 AS far, CAST(list_sort(embedding)[1] AS DOUBLE) AS least, CAST(embedding[2:3][1] AS DOUBLE) AS second FROM embeddings""")
def _(t, spark):
    e = F.col("embedding")
    return t("embeddings").select(
        "vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.array_max(e).cast("double").alias("most"), F.size(F.array_distinct(e)).cast("long").alias("different"), F.exists(e, lambda x: x > 3).alias("far"),
        F.array_sort(e)[0].cast("double").alias("least"), F.slice(e, 2, 2)[0].cast("double").alias("second"),
    )


@op("o36_array_functions", """SELECT vec_id, CAST(round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))), 6) AS DOUBLE) AS total, CAST(round(list_sum(list_transform(list_zip(embedding[1:32], embedding[33:64]), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE))), 6) AS DOUBLE) AS halves,
    len(list_intersect(range(CAST(label AS BIGINT), CAST(label AS BIGINT) + 5), [3, 4, 5, 6])) AS shared, CAST(list_sum(range(0, CAST(label AS BIGINT) + 1)) AS BIGINT) AS steps FROM embeddings""")
def _(t, spark):
    e, k = F.transform("embedding", lambda x: x.cast("double")), F.col("label").cast("long")
    total = lambda a: F.round(F.aggregate(a, F.lit(0.0), lambda s, x: s + x), 6)
    return t("embeddings").select(
        "vec_id", total(e).alias("total"), total(F.zip_with(F.slice(e, 1, 32), F.slice(e, 33, 32), lambda a, b: a * b)).alias("halves"),
        F.size(F.array_intersect(F.sequence(k, k + 4), F.array(*(F.lit(x).cast("long") for x in (3, 4, 5, 6))))).cast("long").alias("shared"), F.aggregate(F.sequence(F.lit(0).cast("long"), k), F.lit(0).cast("long"), lambda s, x: s + x).alias("steps"),
    )


@op("o37_maps", "SELECT user_id, 2 * max(value) FILTER (WHERE event_type = 'click') + 5 AS click, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def _(t, spark):
    best = t("events").groupBy("user_id", "event_type").agg(F.max("value").alias("v"))
    m = best.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "v"))).alias("m"))
    return m.select("user_id", F.transform_values("m", lambda k, v: 2 * v + F.length(k))["click"].alias("click"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@op("o38_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, json_extract_string(props, '$.k') AS text FROM events")
def _(t, spark):
    return t("events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object(F.to_json(F.from_json("props", "k int")), "$.k").alias("text"))


@op("o38_json_tuple", "SELECT event_id, json_extract_string(props, '$.k') AS k, CAST(NULL AS VARCHAR) AS none FROM events")
def _(t, spark):
    return t("events").select("event_id", F.json_tuple("props", "k", "none").alias("k", "none"))


@op("o39_casts", "SELECT p_partkey, try_cast(split_part(p_brand, '#', 2) AS INTEGER) AS brand, try_cast(p_name AS DOUBLE) AS none, CAST(CAST(p_retailprice AS DECIMAL(18, 4)) AS DOUBLE) AS price FROM part")
def _(t, spark):
    return t("part").select("p_partkey", F.expr("try_cast(split_part(p_brand, '#', 2) AS INT)").alias("brand"), F.expr("try_cast(p_name AS DOUBLE)").alias("none"), F.col("p_retailprice").cast("decimal(18,4)").cast("double").alias("price"))


@op("o40_sample")
def _(t, spark):
    a = t("events").sample(0.1, seed=7).agg(F.count(F.lit(1)).alias("n"))
    b = t("events").sampleBy("event_type", {"click": 0.2, "view": 0.1}, seed=7).agg(F.count(F.lit(1)).alias("n"))
    return a.select(F.lit("rows").alias("how"), "n").union(b.select(F.lit("strata"), "n"))


@op("o41_partitioning", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(t, spark):
    return t("events").repartitionByRange(8, "ts").repartition(4, "event_type").coalesce(2).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@op("o42_checkpoint", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def _(t, spark):
    return materialize(t("events").select("user_id")).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@op_dir("o43_scalar_udf", f"WITH {sql.ctes('dense')} SELECT q_traj, q_seg, traj_id, seg_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({sql.match(3.1)})")
def _(spark, sf_dir):
    q, d = both(spark, sf_dir, "dense")
    pairs = timebins.near(q, timebins.build(d, 48), 3.1).where(geometry.hints(3.1)).where("q_traj_id <> traj_id")
    base = geometry._quadratic(pairs, geometry.approach_text(3.1)[:3])
    out = base.withColumn("r", geometry.within_arrow("qa", "qb", "qc", "b0", F.col("b1") - F.col("b0"))).where("r.lo IS NOT NULL")
    return out.select(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), "traj_id", "seg_id", geometry.rounded(F.col("r.lo")).alias("lo"), geometry.rounded(F.col("r.hi")).alias("hi"))


def union_lengths(keys: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each key, and the length of the union of its intervals."""
    order = np.lexsort((hi, lo, keys))
    keys, lo, hi = keys[order], lo[order], hi[order]
    ids, group = np.unique(keys, return_inverse=True)
    # The latest end before, among intervals of the same key: a running maximum of ranks, a key's above those of keys before it.
    ends, rank = np.unique(hi, return_inverse=True)
    latest = np.maximum.accumulate(group * len(ends) + rank)
    first = np.diff(group, prepend=-1) > 0
    before = np.where(first, -np.inf, ends[np.where(first, 0, np.roll(latest, 1) - group * len(ends))])
    return ids, np.bincount(group, np.maximum(0.0, hi - np.maximum(lo, before)))


@op_dir("o44_aggregate_udf", f"WITH {sql.ctes('dense')} SELECT q_traj, traj_id, CAST(round(sum(hi - lo), 6) AS DOUBLE) AS covered FROM ({sql.match(3.1)}) GROUP BY 1, 2")
def _(spark, sf_dir):
    @F.arrow_udf("array<struct<traj_id: long, covered: double>>")
    def unions(traj: pa.Array, lo: pa.Array, hi: pa.Array) -> list:
        ids, covered = union_lengths(*(a.to_numpy(zero_copy_only=False) for a in (traj, lo, hi)))
        return [{"traj_id": i, "covered": x} for i, x in zip(ids.tolist(), covered.tolist())]

    q, d = both(spark, sf_dir, "dense")
    hits = timebins.search(q, timebins.build(d, 48), 3.1)
    # One call for each query trajectory, not for each pair of trajectories: these are many, and meet a few times each.
    met = hits.groupBy("q_traj").agg(unions("traj_id", "lo", "hi").alias("met")).select("q_traj", F.inline("met"))
    return met.withColumn("covered", F.round("covered", 6))


@op("o45_table_udf", "SELECT n, bin FROM (SELECT n_nationkey AS n, unnest(range(n_nationkey, n_nationkey + 3)) AS bin FROM nation)")
def _(t, spark):
    sqlapi.register_functions(spark)
    t("nation").createOrReplaceTempView("udtf_nation")
    return spark.sql("SELECT CAST(n_nationkey AS INT) AS n, CAST(b.bin AS BIGINT) AS bin FROM udtf_nation, LATERAL bins_of_interval(CAST(n_nationkey AS DOUBLE), CAST(n_nationkey AS DOUBLE) + 2.5D, 0.0D, 1.0D) b")


@op("o45_cells_and_parts", """SELECT n_nationkey AS n, 'cells' AS kind, count(*) AS k, CAST(sum(cx + cy + cz) AS DOUBLE) AS total FROM (SELECT n_nationkey, unnest(range(n_nationkey // 4, (n_nationkey + 5) // 4 + 1)) AS cx, cy, cz FROM nation, unnest(range(0, 2)) a(cy), unnest(range(1, 3)) b(cz)) GROUP BY 1
    UNION ALL SELECT n_nationkey, 'parts', count(*), sum(n_nationkey + 2 * i / 4.0) FROM nation, unnest(range(0, 4)) u(i) GROUP BY 1""")
def _(t, spark):
    sqlapi.register_functions(spark)
    t("nation").createOrReplaceTempView("udtf_nation")
    return spark.sql("""SELECT n_nationkey AS n, 'cells' AS kind, count(*) AS k, CAST(sum(c.cx + c.cy + c.cz) AS DOUBLE) AS total FROM udtf_nation, LATERAL cells_of_box(CAST(n_nationkey AS DOUBLE), CAST(n_nationkey AS DOUBLE) + 5D, 1D, 6D, 5D, 9.5D, 4D) c GROUP BY 1
        UNION ALL SELECT n_nationkey, 'parts', count(*), sum(p.t0) FROM udtf_nation, LATERAL splice_interval(CAST(n_nationkey AS DOUBLE), CAST(n_nationkey AS DOUBLE) + 2D, 4) p GROUP BY 1""")


@op("o46_cogrouped_map", "SELECT c.k AS c_custkey, coalesce(c.n, 0) AS rows, coalesce(o.n, 0) AS orders FROM (SELECT c_custkey AS k, count(*) AS n FROM customer GROUP BY 1) c LEFT JOIN (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1) o USING (k)")
def _(t, spark):
    import pyarrow as pa

    def meet(key, left: pa.Table, right: pa.Table) -> pa.Table:
        none = left.num_rows == 0
        return pa.table({"c_custkey": pa.array([] if none else [key[0].as_py()], pa.int64()), "rows": pa.array([] if none else [left.num_rows], pa.int64()), "orders": pa.array([] if none else [right.num_rows], pa.int64())})

    left, right = t("customer").select("c_custkey").groupBy("c_custkey"), t("orders").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey").groupBy("c_custkey")
    return left.cogroup(right).applyInArrow(meet, "c_custkey long, rows long, orders long")


@op("o46_arrow_maps", "SELECT user_id, sum(twice) AS twice, count(*) AS n FROM (SELECT user_id, 2 * event_id AS twice FROM events) GROUP BY 1")
def _(t, spark):
    import pyarrow as pa
    import pyarrow.compute as pc

    def double(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.multiply(b.column(1), 2)], ["user_id", "twice"])

    def total(rows: pa.Table) -> pa.Table:
        return pa.table({"user_id": rows["user_id"][:1], "twice": [pc.sum(rows["twice"]).as_py()], "n": [rows.num_rows]})

    doubled = t("events").select("user_id", "event_id").mapInArrow(double, "user_id long, twice long")
    return doubled.groupBy("user_id").applyInArrow(total, "user_id long, twice long, n long")


@op("o46_grouped_map", "SELECT user_id, count(*) AS n, max(value) - min(value) AS spread FROM events GROUP BY user_id")
def _(t, spark):
    def spread(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [pdf.user_id.iloc[0]], "n": [len(pdf)], "spread": [pdf.value.max() - pdf.value.min()]})

    return t("events").select("user_id", "value").groupBy("user_id").applyInPandas(spread, "user_id long, n long, spread double")


@op_dir("o47_sql", sql.search("dense", 3.1))
def _(spark, sf_dir):
    sqlapi.register(spark, sf_dir, reach={"dense": 3.1})
    return spark.sql(sqlapi.search_text("dense", 3.1, 48))


def _round_trip(fmt: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from ..session import shared_folder

        path = shared_folder(spark, fmt)
        rows = table(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_acctbal")
        rows.write.format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(path)
        return spark.read.schema(rows.schema).format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).load(path)

    return run


for _fmt in ("csv", "json", "orc", "parquet"):
    op_dir(f"s3_{_fmt}", "SELECT s_suppkey, s_name, s_acctbal FROM supplier")(_round_trip(_fmt))


@op_dir("s3_text", "SELECT s_suppkey, s_name FROM supplier")
def _(spark, sf_dir):
    from ..session import shared_folder

    path = shared_folder(spark, "text")
    table(spark, sf_dir, "supplier").select(F.concat_ws("\t", "s_suppkey", "s_name").alias("value")).write.text(path)
    parts = F.split("value", "\t")
    return spark.read.text(path).select(parts[0].cast("long").alias("s_suppkey"), parts[1].alias("s_name"))


@op_dir("s7_python_source", f"WITH {sql.ctes('dense')}, {_EXT}, a AS ({cells_of(10, 'd')}) SELECT h, traj_id, seg_id FROM a WHERE h BETWEEN 0 AND 99 OR h BETWEEN 500 AND 749")
def _(spark, sf_dir):
    from ..operators import cells
    from ..session import shared_folder
    from ..sources.cell_source import read_cells, save_lookup

    path = shared_folder(spark, "cells")
    save_lookup(cells.build(segments(spark, sf_dir, "dense"), 10).lookup, path)
    return read_cells(spark, path, [(0, 99), (500, 749)])


@op_dir("s2_bucketed_index", f"WITH {sql.ctes('dense')} SELECT q_traj, q_seg, traj_id, seg_id, {sql.rounded('lo')} AS lo, {sql.rounded('hi')} AS hi FROM ({sql.match(3.1)})")
def _(spark, sf_dir):
    from ..sources.tables import load_index, save_index
    import uuid

    q, d = both(spark, sf_dir, "dense")
    built = timebins.placed(timebins.build(d, 48), 3.1)
    name = f"bins_{uuid.uuid4().hex[:12]}"
    save_index(built.entries, name, ["bin", "h"], 8, {"bins": built.bins._asdict(), "grid": built.grid._asdict(), "block": built.block}, ("t0",))
    save_index(built.directory, f"{name}_directory", "bin", 1, {})
    entries, meta = load_index(spark, name)
    index = timebins.TimeBinIndex(entries, load_index(spark, f"{name}_directory")[0], timebins.Bins(**meta["bins"]), meta["block"], grid=timebins.Grid(**meta["grid"]))
    found = timebins.search(q, index, 3.1)
    return found.withColumn("lo", geometry.rounded(F.col("lo"))).withColumn("hi", geometry.rounded(F.col("hi")))


@op_dir("s4_vector_segments", "SELECT CAST(label AS BIGINT) AS traj_id, count(*) - 1 AS segments FROM embeddings GROUP BY 1")
def _(spark, sf_dir):
    from .scenarios import seg_vector

    return seg_vector(spark, sf_dir).groupBy("traj_id").agg(F.count(F.lit(1)).alias("segments"))


@op("s4_generated", "SELECT walk, 39 * count(DISTINCT c_custkey) AS segments FROM customer, (VALUES ('random'), ('bounded')) v(walk) GROUP BY 1")
def _(t, spark):
    """Walks of forty points, one for each customer."""
    from .scenarios import bounded_walk, random_walk

    keys = t("customer").select("c_custkey").distinct()
    n = keys.count()
    a = random_walk(spark, n, 40, 1, keys=keys).agg(F.count(F.lit(1)).alias("segments"))
    b = bounded_walk(spark, n, 40, 1, keys=keys).agg(F.count(F.lit(1)).alias("segments"))
    return a.select(F.lit("random").alias("walk"), "segments").union(b.select(F.lit("bounded"), "segments"))


@op_dir("a8_splice", f"WITH {sql.ctes('dense')} SELECT count(*) * 4 AS parts, CAST(round(sum(t1 - t0), 3) AS DOUBLE) AS time FROM d")
def _(spark, sf_dir):
    return geometry.splice(segments(spark, sf_dir, "dense"), 4).agg(F.count(F.lit(1)).alias("parts"), F.round(F.sum(F.col("t1") - F.col("t0")), 3).alias("time"))


@op_dir("a2_boxes", f"WITH {sql.ctes('walk')} SELECT traj_id, seg_id, " + ", ".join(f"least({a}0, {a}1) - 2 AS {a}lo, greatest({a}0, {a}1) + 2 AS {a}hi" for a in "xyz") + ", t1 - t0 AS extent FROM d")
def _(spark, sf_dir):
    d = geometry.box(segments(spark, sf_dir, "walk"), 2.0)
    return d.select("traj_id", "seg_id", *(f"{a}{k}" for a in "xyz" for k in ("lo", "hi")), geometry.duration(d).alias("extent"))


@op_dir("a6_dense_ids", f"WITH {sql.ctes('event')} SELECT traj_id, seg_id, row_number() OVER (ORDER BY t0, traj_id, seg_id) - 1 AS eid FROM d")
def _(spark, sf_dir):
    from ..operators.index import ENTRY_ORDER, dense_ids

    return dense_ids(segments(spark, sf_dir, "event"), ENTRY_ORDER).select("traj_id", "seg_id", "eid")


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracles() -> dict[str, str]:
    return dict(_SQL)
