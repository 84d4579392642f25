"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line.

Searches: response time of a whole query set, mean of three runs (one where it is long) into the noop sink, after one that warms up, with the index built and
materialized before (its building is not counted).  Operators of the training-data subpackage: one run each.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
TRIALS = 3
#: Seconds beyond which a run is not repeated.
LONG = 10.0


def timed(make, trials: int = TRIALS, warm: bool = True) -> tuple[float, float]:
    took = []
    if warm and trials > 1:
        make().write.format("noop").mode("overwrite").save()
    for _ in range(trials):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
        if took[-1] > LONG:
            break
    return statistics.mean(took), statistics.pstdev(took)


#: Settings of the comparison: share of trajectories that ask, distances (the middle one is the headline), m, v, cells, r.
#: The walk's and the dense shares are those of the experiments; cells only where segments are small, as there.
PLAN = {
    "walk": (10, (5.0, 20.0, 50.0), 10000, 4, 50, 10),
    "event": (5, (1.0, 10.0, 50.0), 1000, 16, None, 1),
    "dense": (250, (0.31, 9.4, 28.1), 1000, 2, None, 4),
}


def searches(spark: SparkSession) -> tuple[dict[str, float], list[dict]]:
    from trajdist.operators import batching, cells, packed_tree, slabs, timebins
    from trajdist.operators.index import as_queries
    from trajdist.plans.scenarios import segments
    from trajdist.session import materialize

    found, rows = {}, []
    for name, (every, dists, m, v, k, r) in PLAN.items():
        d = materialize(segments(spark, SF_DIR, name))
        q = materialize(d.where(F.col("traj_id") % every == 0))
        tbin, slab, one = timebins.store(timebins.build(d, m)), slabs.store(slabs.build(d, m, v)), slabs.store(slabs.build(d, m, 1))
        tree = packed_tree.store(packed_tree.build(d, r))
        methods = {"tbin": lambda x: timebins.search(q, tbin, x), "slab": lambda x: slabs.search(q, slab, x), "tree": lambda x: packed_tree.search(q, tree, x)}
        if k:
            cell = cells.build(d, k)
            cell = replace(cell, lookup=timebins.in_place(cell.lookup, ["h"]), entries=materialize(cell.entries))
            methods["cell"] = lambda x: cells.search(q, cell, x)
        n, entries = q.count(), d.count()
        for x in dists:
            head, side = x == dists[1], {}
            for method, make in methods.items():
                mean, sd = timed(lambda: make(x), warm=x == dists[0])
                side[method] = mean
                rows.append({"scenario": name, "method": method, "d": x, "queries": n, "entries": entries, "mean": round(mean, 3), "sd": round(sd, 3)})
                print(json.dumps(rows[-1]), file=sys.stderr, flush=True)
                if head:
                    found[f"search_{method}_{name}"] = round(mean, 3)
            extra = {
                "plan_tbin": lambda: timebins.overlaps(as_queries(q), tbin.directory, tbin.bins).groupBy("q_traj_id", "q_seg_id").agg(F.sum("n")),
                "plan_slab": lambda: slabs.schedule(q, slab, x),
                "slab_one": lambda: slabs.search(q, one, x),
                **({"rounds": lambda: batching.cell_rounds(cells.demand(q, cell, x), 538 * entries)} if k else {}),
            }
            side |= {key: timed(make, warm=x == dists[0])[0] for key, make in extra.items()}
            # Shares of planning, the indirection of slabs over bins, the cells' time with their rounds, ratios to the tree, and gains in percent.
            rows.append({
                "scenario": name, "d": x, "results": timebins.search(q, tbin, x).count(), "plan_share_tbin": round(side["plan_tbin"] / side["tbin"], 3), "plan_share_slab": round(side["plan_slab"] / side["slab"], 3),
                "indirection_percent": round(100 * (side["slab_one"] / side["tbin"] - 1), 1), "slab_over_tbin_percent": round(100 * (side["slab"] / side["tbin"] - 1), 1), "tree_over_slab_percent": round(100 * (side["tree"] / side["slab"] - 1), 1),
                **({"cell_optimistic": round(side["cell"], 3), "cell_with_rounds": round(side["cell"] + side["rounds"], 3)} if k else {}), **{f"{key}_over_tree": round(side[key] / side["tree"], 3) for key in methods if key != "tree"},
            })
            print(json.dumps(rows[-1]), file=sys.stderr, flush=True)
    return found, rows


def operators(spark: SparkSession) -> dict[str, float]:
    try:
        from trajdist.llm import registry
    except ImportError:
        return {}
    out = {}
    for name, f in registry.queries().items():
        if name != "pipeline":
            make = lambda f=f: f(spark, SF_DIR)
            out[name] = round(timed(make, 1)[0], 3)
    return out


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times, rows = searches(spark)
    times |= operators(spark)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(SF_DIR.rstrip("/")), "series": rows}))
    spark.stop()


if __name__ == "__main__":
    main()
