"""Runs the timed experiments on events with companions and prints a JSON line for each.

python experiments.py [sf_dir] [NAME...]; names: size (slow-down with data size), grid (indexed against
the tile grid), amortised (preparation against five different queries), eps_t, eps_sp (up to the whole plane),
delta_t (Join and Refine of prepart and indexed for each value), index (capacity), cores (speed-up).
The same sweeps as counts, and balance, are registered queries.
"""

from __future__ import annotations

import json
import sys
from dataclasses import replace


def session(cores: int):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(2 * cores)).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def main(sf_dir: str = "/root/testdata/sf0.1", *names: str) -> None:
    from comovement import points, registry, workloads
    from comovement.params import JoinParams
    from comovement.sources.scratch import scratch

    params = JoinParams(10.0, registry.P10.eps_t_us, 5 * registry.HOUR)
    made = {
        "size": lambda pts, d: workloads.slowdown(pts, params, d), "grid": lambda pts, d: workloads.versus_grid(pts, params, d),
        "amortised": lambda pts, d: workloads.amortised(pts, [replace(params, eps_sp=e) for e in (4.0, 6.0, 8.0, 10.0, 12.0)], d),
        "eps_t": lambda pts, d: workloads.vary_timed(pts, "eps_t_us", [m * 60_000_000 for m in workloads.EPS_T_MINUTES], d, params),
        "eps_sp": lambda pts, d: workloads.vary_timed(pts, "eps_sp", [*workloads.radii(pts), 10.0, 20.0], d, params) + workloads.vary_timed(points.portion(pts, 1, 20), "eps_sp", [None], f"{d}/plane", params),
        "delta_t": lambda pts, d: workloads.vary_timed(pts, "delta_t_us", [h * registry.HOUR for h in workloads.DELTA_T_HOURS], d, params),
        "index": lambda pts, d: workloads.index_cost(pts, params, d),
    }
    for name in names or (*made, "cores"):
        if name == "cores":
            seconds = {}
            for cores in (1, 2, 4):
                spark = session(cores)
                row = workloads.timings(points.companions(registry.raw(spark, sf_dir)), params, scratch(spark, "cores"), ("indexed",))[0]
                seconds[cores] = row["join_s"] + row["refine_s"]
                spark.stop()
            rows = workloads.speedup(seconds)
        else:
            spark = session(8)
            rows = made[name](points.companions(registry.raw(spark, sf_dir)), scratch(spark, name))
        print(json.dumps({"experiment": name, "rows": rows}), flush=True)


if __name__ == "__main__":
    main(*sys.argv[1:])
