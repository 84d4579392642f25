"""Geometry of uniformly moving points, as Column arithmetic.

A segment moves from (x0,y0,z0) at t0 to (x1,y1,z1) at t1.  Pairs carry the query's columns with
the prefix ``q_``.  Two segments meet in time only if their intervals share more than an instant.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

AXES = "xyz"
MICRO = 1e6


def amount(d: float | str) -> Column:
    """A distance: a number, or the name of a query column that holds it (so that one pass answers several distances)."""
    return F.col(f"q_{d}") if isinstance(d, str) else F.lit(float(d))


def _amount_text(d: float | str) -> str:
    return f"q_{d}" if isinstance(d, str) else f"CAST({float(d)!r} AS DOUBLE)"


def box(df: DataFrame, d: float = 0.0) -> DataFrame:
    """Adds xlo..zhi, the bounding box grown by d on each spatial side."""
    for c in AXES:
        df = df.withColumn(f"{c}lo", F.least(f"{c}0", f"{c}1") - F.lit(float(d))).withColumn(f"{c}hi", F.greatest(f"{c}0", f"{c}1") + F.lit(float(d)))
    return df


def duration(df: DataFrame) -> Column:
    return df["t1"] - df["t0"]


def clip(df: DataFrame, ts: float, te: float) -> DataFrame:
    """Segments cut to [ts, te]; endpoints are interpolated, what lies outside is dropped."""
    part = df.where((F.col("t1") > F.lit(float(ts))) & (F.col("t0") < F.lit(float(te))))
    a, b = F.greatest("t0", F.lit(float(ts))), F.least("t1", F.lit(float(te)))

    def at(c: str, t: Column, end: str) -> Column:
        moved = F.col(f"{c}0") + (F.col(f"{c}1") - F.col(f"{c}0")) / (F.col("t1") - F.col("t0")) * (t - F.col("t0"))
        return F.when(t == F.col(end), F.col(f"{c}{end[1]}")).otherwise(moved)

    return part.select(
        *(c for c in df.columns if c not in ("t0", "t1", *(f"{x}{i}" for x in AXES for i in "01"))),
        a.alias("t0"), *(at(c, a, "t0").alias(f"{c}0") for c in AXES), b.alias("t1"), *(at(c, b, "t1").alias(f"{c}1") for c in AXES),
    )


def splice(df: DataFrame, k: int) -> DataFrame:
    """Each segment as k equal parts; ``part`` numbers them."""
    rows = df.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))

    def at(c: str, i: Column) -> Column:
        return F.when(i == 0, F.col(f"{c}0")).when(i == k, F.col(f"{c}1")).otherwise(F.col(f"{c}0") + (F.col(f"{c}1") - F.col(f"{c}0")) * i / F.lit(float(k)))

    i = F.col("part")
    return rows.select("traj_id", "seg_id", "part", *(at(c, i).alias(f"{c}0") for c in "txyz"), *(at(c, i + 1).alias(f"{c}1") for c in "txyz"))


def hints(d: float | str, query: str = "q_", entry: str = "") -> Column:
    """Early rejection: time overlap, then overlap of the entry's box with the query's grown box."""
    q, e = (lambda c: F.col(query + c)), (lambda c: F.col(entry + c))
    keep = (q("t0") < e("t1")) & (e("t0") < q("t1"))
    for c in AXES:
        keep &= (F.greatest(e(f"{c}0"), e(f"{c}1")) >= F.least(q(f"{c}0"), q(f"{c}1")) - amount(d)) & (F.least(e(f"{c}0"), e(f"{c}1")) <= F.greatest(q(f"{c}0"), q(f"{c}1")) + amount(d))
    return keep


def approach_text(d: float | str) -> list[dict[str, str]]:
    """Layers of expressions for the squared distance a*s*s + 2*b*s + c - d*d after s from the start of the common time.

    Each layer reads the one before; the same text runs in Spark and in the SQL oracles, so both round alike.
    """
    first = {"b0": "greatest(q_t0, t0)", "b1": "least(q_t1, t1)"}
    second = {}
    for c in AXES:
        second[f"w{c}"] = f"(q_{c}1 - q_{c}0) / (q_t1 - q_t0) - ({c}1 - {c}0) / (t1 - t0)"
        second[f"d{c}"] = f"(q_{c}0 + (q_{c}1 - q_{c}0) / (q_t1 - q_t0) * (b0 - q_t0)) - ({c}0 + ({c}1 - {c}0) / (t1 - t0) * (b0 - t0))"
    third = {"qa": "wx * wx + wy * wy + wz * wz", "qb": "dx * wx + dy * wy + dz * wz", "qc": f"dx * dx + dy * dy + dz * dz - {_amount_text(d)} * {_amount_text(d)}"}
    fourth = {"disc": "qb * qb - qa * qc"}
    zero = "CAST(0 AS DOUBLE)"
    fifth = {
        "s0": f"CASE WHEN qa = 0 THEN CASE WHEN qc <= 0 THEN {zero} END WHEN disc >= 0 THEN greatest({zero}, (-qb - sqrt(greatest(disc, {zero}))) / qa) END",
        "s1": f"CASE WHEN qa = 0 THEN CASE WHEN qc <= 0 THEN b1 - b0 END WHEN disc >= 0 THEN least(b1 - b0, (-qb + sqrt(greatest(disc, {zero}))) / qa) END",
    }
    return [first, second, third, fourth, fifth]


def rounded(c: Column) -> Column:
    """Six places, by the same steps in every engine."""
    return F.floor(c * MICRO + 0.5) / MICRO


def _quadratic(pairs: DataFrame, layers: list[dict[str, str]]) -> DataFrame:
    """Adds b0, b1 and the coefficients qa, qb, qc of the squared distance.

    They pass through a generator of one row: the optimiser does not move later filters below it, which would
    write the whole arithmetic out again in each of them."""
    out = pairs.where("q_t0 < t1 AND t0 < q_t1")
    for layer in layers:
        out = out.withColumns({k: F.expr(v) for k, v in layer.items()})
    return out.select(*pairs.columns, F.inline(F.array(F.struct("b0", "b1", "qa", "qb", "qc"))))


def within(pairs: DataFrame, d: float | str, keep: tuple[str, ...] = ("q_traj_id", "q_seg_id", "traj_id", "seg_id"), stable: bool = False) -> DataFrame:
    """The time interval [lo, hi] of each pair in which its distance is at most d; pairs without one are dropped.

    Squared distance is convex, so each pair has one interval at most.  ``stable`` takes the roots in the
    form that does not cancel.
    """
    layers = approach_text(d)
    if stable:
        q = "-(qb + CASE WHEN qb < 0 THEN -sqrt(greatest(disc, CAST(0 AS DOUBLE))) ELSE sqrt(greatest(disc, CAST(0 AS DOUBLE))) END)"
        one, other = f"({q}) / qa", f"CASE WHEN ({q}) = 0 THEN CAST(0 AS DOUBLE) ELSE qc / ({q}) END"
        layers[-1] = {
            "s0": f"CASE WHEN qa = 0 THEN CASE WHEN qc <= 0 THEN CAST(0 AS DOUBLE) END WHEN disc >= 0 THEN greatest(CAST(0 AS DOUBLE), least({one}, {other})) END",
            "s1": f"CASE WHEN qa = 0 THEN CASE WHEN qc <= 0 THEN b1 - b0 END WHEN disc >= 0 THEN least(b1 - b0, greatest({one}, {other})) END",
        }
    out = _quadratic(pairs, layers[:3])
    for layer in layers[3:]:
        out = out.withColumns({k: F.expr(v) for k, v in layer.items()})
    return out.where("s0 <= s1").select(*keep, (F.col("b0") + F.col("s0")).alias("lo"), (F.col("b0") + F.col("s1")).alias("hi"))


def matches(pairs: DataFrame, d: float | str, keep: tuple[str, ...] = ()) -> DataFrame:
    """``within`` with the columns of a result; a distance from a column stays beside them, and so does ``keep``."""
    more = ([f"q_{d}"] if isinstance(d, str) else []) + list(keep)
    found = within(pairs, d, ("q_traj_id", "q_seg_id", "traj_id", "seg_id", *more))
    return found.select(F.col("q_traj_id").alias("q_traj"), F.col("q_seg_id").alias("q_seg"), "traj_id", "seg_id", "lo", "hi", *(F.col(c).alias(c.removeprefix("q_")) for c in more))


def repeated(found: DataFrame, arises: str) -> DataFrame:
    """Rows that arose ``arises`` times each, once: rows that were there twice to begin with stay twice."""
    keys = [c for c in found.columns if c != arises]
    once = found.groupBy(*keys, arises).agg(F.count(F.lit(1)).alias("_n"))
    return once.select(*keys, F.explode(F.sequence(F.lit(1).cast("long"), F.expr(f"_n div {arises}"))).alias("_k")).drop("_k")


def min_distance(pairs: DataFrame) -> DataFrame:
    """Adds d_min and t_min, the closest approach in the common time."""
    out = _quadratic(pairs, approach_text(0.0)[:3]).withColumn("s", F.expr("CASE WHEN qa = 0 THEN CAST(0 AS DOUBLE) ELSE greatest(CAST(0 AS DOUBLE), least(b1 - b0, -qb / qa)) END"))
    out = out.withColumn("t_min", F.expr("b0 + s")).withColumn("d_min", F.expr("sqrt(greatest(qa * s * s + 2 * qb * s + qc, CAST(0 AS DOUBLE)))"))
    return out.drop("b0", "b1", "qa", "qb", "qc", "s")


@F.pandas_udf(T.StructType([T.StructField("lo", T.DoubleType()), T.StructField("hi", T.DoubleType())]))
def within_arrow(a: pd.Series, b: pd.Series, c: pd.Series, start: pd.Series, length: pd.Series) -> pd.DataFrame:
    """The interval from a, b, c of the squared distance, in Arrow batches: a cross-check of ``within``."""
    import numpy as np

    disc = b * b - a * c
    root = np.sqrt(disc.clip(lower=0))
    still = a == 0
    safe = a.where(~still, 1.0)
    s0 = ((-b - root) / safe).clip(lower=0).where(~still, 0.0)
    s1 = np.minimum(length, (-b + root) / safe).where(~still, length)
    good = (s0 <= s1) & (still & (c <= 0) | ~still & (disc >= 0))
    return pd.DataFrame({"lo": (start + s0).where(good), "hi": (start + s1).where(good)})


def hausdorff(points: str = "p", others: str = "o") -> Column:
    """Hausdorff distance of two arrays of struct<x,y,z>."""

    def gap(p: Column, o: Column) -> Column:
        return F.sqrt(F.pow(p["x"] - o["x"], 2) + F.pow(p["y"] - o["y"], 2) + F.pow(p["z"] - o["z"], 2))

    def one_way(a: str, b: str) -> Column:
        return F.array_max(F.transform(a, lambda p: F.array_min(F.transform(b, lambda o: gap(p, o)))))

    return F.greatest(one_way(points, others), one_way(others, points))
