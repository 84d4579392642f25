"""DuckDB SQL of the scenarios and of search by all pairs, from which the oracles are put together."""

from __future__ import annotations

from ..functions.geometry import approach_text
from .scenarios import DENSE_STEPS, DENSITY, EVENT_EPOCH, EVENT_Z, ORDER, QUERIES, WALK_STEPS

_ORD = ", ".join(ORDER)
_SEG = "traj_id, step AS seg_id, " + ", ".join(f"{c} AS {c}0" for c in "txyz") + ", " + ", ".join(f"lead({c}) OVER (PARTITION BY traj_id ORDER BY step) AS {c}1" for c in "txyz")
_COLS = "traj_id, seg_id, t0, x0, y0, z0, t1, x1, y1, z1"


def _steps(key: str, sums: dict[str, str], most: int) -> str:
    cols = ", ".join(f"CAST(sum({e}) OVER (PARTITION BY {key} ORDER BY {_ORD} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS {n}" for n, e in sums.items())
    return f"SELECT * FROM (SELECT {key} AS k, row_number() OVER (PARTITION BY {key} ORDER BY {_ORD}) - 1 AS step, {cols} FROM lineitem) WHERE step < {most}"


def points(name: str) -> str:
    if name == "walk":
        sums = {"sx": "CAST(l_quantity AS BIGINT) - 25", "sy": "CAST(round(100 * l_discount) AS BIGINT) - 5", "sz": "CAST(round(100 * l_tax) AS BIGINT) - 4"}
        place = ", ".join(f"CAST(s{c} + (k * {m}) % 101 AS DOUBLE) AS {c}" for c, m in zip("xyz", (37, 53, 71)))
        return f"SELECT k AS traj_id, step, CAST(step + (k * 7919) % 101 AS DOUBLE) AS t, {place} FROM ({_steps('l_suppkey', sums, WALK_STEPS)})"
    if name == "event":
        code = " ".join(f"WHEN '{k}' THEN {v}" for k, v in EVENT_Z.items())
        return f"""SELECT user_id AS traj_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS step,
            CAST(epoch_us(ts) - {EVENT_EPOCH} AS DOUBLE) / CAST(3600000000.0 AS DOUBLE) AS t, value AS x, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS y,
            CAST(25 * CASE event_type {code} END AS DOUBLE) AS z FROM events"""
    sign = lambda e: f"CASE WHEN {e} % 2 = 0 THEN 1000 ELSE -1000 END"
    sums = {
        "sx": f"(1 + CAST(l_quantity AS BIGINT) % 5) * {sign('l_orderkey')}", "sy": f"(1 + l_suppkey % 5) * {sign('l_linenumber')}",
        "sz": f"(1 + l_orderkey % 5) * {sign('CAST(round(100 * l_tax) AS BIGINT)')}",
    }
    side = f"(SELECT CAST(round(1000 * pow(count(DISTINCT l_partkey) / CAST({DENSITY} AS DOUBLE), 1 / CAST(3 AS DOUBLE))) AS BIGINT) FROM lineitem)"

    def place(c: str, a: int, b: int) -> str:
        u = f"(k * {a}) % {b} * side // {b} + s{c} + side // 5"
        p = "(7 * side // 5)"
        return f"CAST({p} - abs((({u}) % (2 * {p}) + 2 * {p}) % (2 * {p}) - {p}) - side // 5 AS DOUBLE) / CAST(1000 AS DOUBLE) AS {c}"

    cols = ", ".join(place(c, a, b) for c, (a, b) in {"x": (7919, 1009), "y": (6271, 1013), "z": (3571, 1019)}.items())
    return f"SELECT k AS traj_id, step, CAST(step AS DOUBLE) AS t, {cols} FROM ({_steps('l_partkey', sums, DENSE_STEPS)}), (SELECT {side} AS side)"


def ctes(name: str) -> str:
    """d (all segments) and q (the query slice)."""
    return f"p AS ({points(name)}), d AS MATERIALIZED (SELECT {_COLS} FROM (SELECT {_SEG} FROM p) WHERE t1 > t0), q AS MATERIALIZED (SELECT * FROM d WHERE traj_id % {QUERIES[name]} = 0)"


def pairs(q: str = "q", d: str = "d", condition: str = "qs.traj_id <> es.traj_id") -> str:
    """Pairs whose times overlap, the query's columns with q_ before them."""
    mine = ", ".join(f"qs.{c} AS q_{c}" for c in _COLS.split(", ") + (["dist"] if q == "qx" else []))
    return f"SELECT {mine}, es.* FROM {q} qs JOIN {d} es ON qs.t0 < es.t1 AND es.t0 < qs.t1 AND {condition}"


def approached(source: str, d: float | str, layers: int = 5) -> str:
    out = f"({source})"
    for layer in approach_text(d)[:layers]:
        out = f"(SELECT *, {', '.join(f'{v} AS {k}' for k, v in layer.items())} FROM {out})"
    return out


def rounded(e: str) -> str:
    return f"floor(({e}) * CAST(1000000 AS DOUBLE) + CAST(0.5 AS DOUBLE)) / CAST(1000000 AS DOUBLE)"


def match(d: float | str, source: str | None = None) -> str:
    """SELECT of all matches, not rounded; at every distance of qx where ``d`` names its column."""
    more = "q_dist AS dist, " if isinstance(d, str) else ""
    return f"SELECT {more}q_traj_id AS q_traj, q_seg_id AS q_seg, traj_id, seg_id, b0 + s0 AS lo, b0 + s1 AS hi FROM {approached(source or pairs('qx' if more else 'q'), d)} WHERE s0 <= s1"


def search(name: str, d: float) -> str:
    return f"WITH {ctes(name)} SELECT q_traj, q_seg, traj_id, seg_id, {rounded('lo')} AS lo, {rounded('hi')} AS hi FROM ({match(d)})"
