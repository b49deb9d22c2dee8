"""Speedup, overhead and best-method measurements: every parallel method on local[1], local[2], ... over tile counts.

``python scaling.py [--sf DIR] [--workers 1,2,4,8] [--workloads w02,w08,...] [--part methods|forms|overhead|all] [--out FILE]``

Each worker count runs in a session of its own. Events are read and cached before the clock, as reported times exclude
reading; cubes leave as arrays by tile and are thrown away. One JSON line a run goes to FILE, tables to the screen:

* methods: seconds and speedup over one worker running the undivided product kernel, by method, tiles and workers;
* forms: seconds of the four forms of the dense kernel on one worker, undivided, and their gain;
* overhead: seconds of clipped tiles over those of the undivided run, on one worker.
"""

from __future__ import annotations

import argparse
import json
import os
import subprocess
import sys
import time

#: a workload of each class: wide disks, crowded, crowded with wide cylinders, sparse, large
WORKLOADS = ("w02", "w06", "w08", "w13", "w18")
METHODS = ("replica_sum", "tile_clip", "parity_sets", "loadaware_sets", "replicated_sets")
TILES = (2, 4, 8, 16)
FORMS = ("plain", "bar", "disk", "product")
FORM_WORKLOADS = ("w03", "w06", "w07", "w02")
OVERHEAD_TILES = (1, 2, 4, 8, 16, 32, 64)


def session(workers: int):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{workers}]")
        .config("spark.sql.shuffle.partitions", str(2 * workers))
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def one(workers: int, part: str, sf: str, names: list[str], limit: float, counts: list[int]) -> None:
    """All runs of a part on a number of workers, one JSON line each."""
    spark = session(workers)
    from cubedensity.operators.density import cube
    from cubedensity.plans.workloads import BY_NAME
    from cubedensity.spec import PlanOptions, TileSpec

    def seconds(w, events, method, tiles, **more):
        began = time.perf_counter()
        cube(events, w.grid(True), w.bw(True), method, PlanOptions(mass="double"), tiles=tiles, workers=workers, emit="blocks", **more).write.format("noop").mode("overwrite").save()
        return time.perf_counter() - began

    for name in names:
        w = BY_NAME[name]
        events = w.events(spark, sf, True).repartition(2 * workers, "event_id").cache()
        events.count()
        tell = lambda **x: print("RUN " + json.dumps({"part": part, "workers": workers, "workload": name} | x), flush=True)  # noqa: B023,E731
        whole = TileSpec(1, 1, 1)
        seconds(w, events.limit(10), "tile_clip", whole)  # workers start before the clock
        if part == "forms":
            for form in FORMS:
                tell(form=form, seconds=seconds(w, events, "tile_clip", whole, kernel_form=form))
        elif part == "overhead":
            for k in (x for x in OVERHEAD_TILES if x <= max(counts) or len(counts) >= len(TILES)):
                tell(tiles=k, seconds=seconds(w, events, "tile_clip", TileSpec(k, k, k).clamp(w.grid(True))))
        else:
            if workers == 1:
                tell(method="undivided", tiles=1, seconds=seconds(w, events, "tile_clip", whole))
            for method in METHODS:
                for k in (0,) if method == "replica_sum" else counts:
                    try:
                        took = seconds(w, events, method, TileSpec(k, k, k).clamp(w.grid(True)) if k else None)
                    except MemoryError:
                        tell(method=method, tiles=k, seconds=None)
                        continue
                    tell(method=method, tiles=k, seconds=took)
                    if took > limit:
                        break
        events.unpersist()
    spark.stop()


def table(head: list[str], rows: list[list]) -> None:
    print("\n| " + " | ".join(head) + " |\n|" + "---|" * len(head))
    for r in rows:
        print("| " + " | ".join("-" if v is None else f"{v:.2f}" if isinstance(v, float) else str(v) for v in r) + " |")


def report(runs: list[dict]) -> None:
    of = lambda **x: next((r["seconds"] for r in runs if all(r.get(k) == v for k, v in x.items())), None)
    counts = sorted({r["workers"] for r in runs if r["part"] == "methods"})
    if counts:
        rows = []
        for w in dict.fromkeys(r["workload"] for r in runs if r["part"] == "methods"):
            base = of(part="methods", workload=w, method="undivided")
            for m in METHODS:
                for k in sorted({r["tiles"] for r in runs if r.get("method") == m}):
                    took = [of(part="methods", workload=w, method=m, tiles=k, workers=p) for p in counts]
                    if any(t is not None for t in took):
                        rows.append([w, m, k or "-", *took, *(base / t if base and t else None for t in took)])
        table(["workload", "method", "tiles", *(f"s, {p}" for p in counts), *(f"speedup, {p}" for p in counts)], rows)
    forms = list(dict.fromkeys(r["workload"] for r in runs if r["part"] == "forms"))
    if forms:
        table(["workload", *FORMS, "gain of product"], [[w, *(s := [of(part="forms", workload=w, form=f) for f in FORMS]), s[0] / s[-1] if s[0] and s[-1] else None] for w in forms])
    cuts = list(dict.fromkeys(r["workload"] for r in runs if r["part"] == "overhead"))
    if cuts:
        table(["workload", *(f"{k}^3" for k in OVERHEAD_TILES)], [[w, *((t / of(part="overhead", workload=w, tiles=1) if (t := of(part="overhead", workload=w, tiles=k)) else None) for k in OVERHEAD_TILES)] for w in cuts])


def main() -> None:
    ask = argparse.ArgumentParser(description=__doc__.split("\n")[0])
    ask.add_argument("--sf", default=os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"))
    ask.add_argument("--workers", default="1,2,4,8")
    ask.add_argument("--workloads", default="")
    ask.add_argument("--tiles", default=",".join(map(str, TILES)), help="tiles an axis")
    ask.add_argument("--part", default="all", choices=("all", "methods", "forms", "overhead"))
    ask.add_argument("--limit", type=float, default=60, help="seconds of a run beyond which finer tiles are left out")
    ask.add_argument("--out", default="")
    ask.add_argument("--one", type=int, default=0, help=argparse.SUPPRESS)
    a = ask.parse_args()
    names = [x for x in a.workloads.split(",") if x]
    if a.one:
        return one(a.one, a.part, a.sf, names, a.limit, [int(k) for k in a.tiles.split(",")])
    jobs = [("methods", p, names or WORKLOADS) for p in map(int, a.workers.split(","))] + [("forms", 1, names or FORM_WORKLOADS), ("overhead", 1, names or WORKLOADS)]
    runs = []
    for part, p, which in jobs:
        if a.part not in ("all", part):
            continue
        call = [sys.executable, os.path.abspath(__file__), "--one", str(p), "--part", part, "--sf", a.sf, "--workloads", ",".join(which), "--tiles", a.tiles, "--limit", str(a.limit)]
        got = subprocess.run(call, capture_output=True, text=True)
        runs += [json.loads(x[4:]) for x in got.stdout.splitlines() if x.startswith("RUN ")]
        if got.returncode:
            print(got.stderr[-2000:], file=sys.stderr)
    if a.out:
        with open(a.out, "w") as f:
            f.writelines(json.dumps(r) + "\n" for r in runs)
    report(runs)


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
