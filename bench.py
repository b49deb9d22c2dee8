"""Headline benchmark: whole density workloads at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``, one JSON line.

Each query is a full cube of a bench workload, thrown away by the ``noop`` sink after all of it is made. The grids and
the lattice and cached before the clock; what that takes is given apart (``read``), and so is the start of session and
workers (``start``). ``BENCH_ALL=1`` takes in the long
workloads, ``BENCH_ONLY=w01,w02`` just some.
"""

from __future__ import annotations

import json
import os
import sys
import time

#: workload -> method that did best on its shape
PLAN = {f"w{k:02d}": "tile_clip" for k in range(1, 22)}
#: workloads whose cubes are mostly full: they leave as arrays by tile, as the reported ones stay in memory; others as rows
DENSE = ("w01", "w02", "w03", "w04", "w05", "w06", "w07", "w08", "w09", "w10", "w11", "w18", "w19", "w20", "w21")
#: workloads that take longest
LONG = ("w09", "w10", "w20", "w21")
#: small cubes by relational and colored methods, at the size of the check grids
MORE = {"density_product_scatter_posts": ("w06", "product_scatter"), "density_parity_sets_posts": ("w06", "parity_sets"), "density_replicated_sets_posts": ("w06", "replicated_sets"), "density_block_scan_birds": ("w12", "block_scan")}


def main() -> None:
    from pyspark.sql import SparkSession

    cpus = os.environ.get("BENCH_CPUS", "8")
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    only = [x for x in os.environ.get("BENCH_ONLY", "").split(",") if x]
    names = only or [n for n in PLAN if n not in LONG or os.environ.get("BENCH_ALL")]
    began = time.perf_counter()
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from cubedensity.operators.density import cube
    from cubedensity.operators.relational import METHODS as RELATIONAL
    from cubedensity.plans.workloads import BY_NAME
    from cubedensity.spec import PlanOptions

    read: dict[str, float] = {}

    def run(name: str, method: str, bench: bool) -> float:
        w = BY_NAME[name]
        grid, bw, options = w.grid(bench), w.bw(bench), PlanOptions(mass="double" if bench else "long")
        start = time.perf_counter()
        events = w.events(spark, sf_dir, bench).repartition(2 * int(cpus), "event_id").cache()
        events.count()
        read[name] = round(time.perf_counter() - start, 3)
        more = {"emit": "blocks"} if bench and method not in RELATIONAL and name in DENSE else {}
        start = time.perf_counter()
        cube(events, grid, bw, method, options, **more).write.format("noop").mode("overwrite").save()
        took = time.perf_counter() - start
        events.unpersist()
        return took

    run("w12", "tile_clip", False)
    started = round(time.perf_counter() - began, 3)
    took = {f"bench_{name}": round(run(name, PLAN[name], True), 3) for name in names}
    if not only:
        took |= {key: round(run(name, method, False), 3) for key, (name, method) in MORE.items()}
    spark.stop()
    print(json.dumps({"metric": "density_workloads_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "read": read, "start": started, "sf": sf_dir.rstrip("/").rsplit("/sf", 1)[-1]}))


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
