"""The experiments as queries: tables of what each one reports, over all workloads or one of each family.

Times are of whole runs without output on the check grids, with the workers of the session, so these have no SQL of the
same meaning; what is counted rather than timed has, and is taken on the reported grids where that is cheap. Runs over
several worker counts need a session each: ``scaling.py`` makes them.
"""

from __future__ import annotations

from functools import reduce

from cubedensity.operators import dag, relational
from cubedensity.operators.pointsets import loads_of
from cubedensity.operators.replicas import replica_bytes
from cubedensity.operators.tiles import safe_tiles
from cubedensity.plans import measures, oracles, workloads
from cubedensity.plans.workloads import BY_NAME, CLASSES, FAMILIES
from cubedensity.sources.sets import events, events_sql
from cubedensity.spec import Bandwidth, GridSpec, TileSpec
from pyspark.sql import functions as F

QUERIES: dict = {}
ORACLES: dict = {}
#: tiles along each axis
CUTS = (1, 2, 4, 8, 16, 32, 64)
FOCUS = GridSpec(37, 48, 52)
WIDE_AND_NARROW = [Bandwidth(5, 1), Bandwidth(1, 0.5)]


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql



for _f, _names in FAMILIES.items():
    add(f"x01_sequential_{_f}", lambda spark, sf, n=_names: spark.createDataFrame(workloads.compare_sequential(spark, sf, n), "workload string, method string, seconds double"))
    add(f"x02_zero_and_compute_{_f}", lambda spark, sf, n=_names: spark.createDataFrame(workloads.zero_and_compute(spark, sf, n), "workload string, zero double, whole double, share double"))
    add(f"x10_best_methods_{_f}", lambda spark, sf, n=_names: spark.createDataFrame(workloads.best_methods(spark, sf, n), "workload string, best string, tiles int, seconds double, chosen string"))


def _copies(spark, sf):
    rows = []
    for n in CLASSES:
        w = BY_NAME[n]
        rows += [(n, p, replica_bytes(w.grid(), p), measures.seconds(w.cube(spark, sf, "replica_sum", workers=p))) for p in (1, 2, 4, 8)]
    return spark.createDataFrame(rows, "workload string, copies int, bytes bigint, seconds double")


add("x03_private_cubes", _copies)
add("x04_over_decomposition", lambda spark, sf: spark.createDataFrame(workloads.over_decomposition(spark, sf), "workload string, tiles int, seconds double"))


def _cut_events(spark, sf):
    """Events that tiles repeat, on the reported grids: what grows when tiles get finer."""
    found = []
    for n in CLASSES:
        w, g = BY_NAME[n], BY_NAME[n].grid(True)
        for k in CUTS:
            t = TileSpec(k, k, k).clamp(g)
            made = measures.replication(events(spark, sf, w.set, g), g, w.bw(True), t)
            found.append(made.select(F.lit(n).alias("workload"), F.lit(k).alias("tiles"), "events", "copies", "extra_disks", "extra_bars"))
    return reduce(lambda a, b: a.union(b), found)


def _cut_events_sql():
    out = []
    for n in CLASSES:
        w, g = BY_NAME[n], BY_NAME[n].grid(True)
        hs, ht = w.bw(True).whole
        for k in CUTS:
            parts = [f"(({m}*least({c}//{g.sub}+{h},{s - 1}))//{s} - ({m}*greatest({c}//{g.sub}-{h},0))//{s} + 1)" for c, h, s, m in zip("xyt", (hs, hs, ht), g.shape, TileSpec(k, k, k).clamp(g).counts)]
            out.append(f"select '{n}' as workload, {k}::int as tiles, count(*)::bigint as events, sum({parts[0]}*{parts[1]}*{parts[2]})::bigint as copies, sum({parts[2]}-1)::bigint as extra_disks, sum({parts[0]}*{parts[1]}-1)::bigint as extra_bars from ({events_sql(w.set, g)})")
    return " union all ".join(out)


add("x04_cut_events", _cut_events, _cut_events_sql())


def _work(spark, sf):
    """Overhead of tiles by counts alone: table entries of clipped tiles over those of the undivided run."""
    rows = []
    for n in CLASSES:
        w = BY_NAME[n]
        ev = w.events(spark, sf).cache()
        alone = measures.table_entries(ev, w.grid(), w.bw()).first()
        for k in (1, 2, 4, 8, 13):
            tiled = measures.tiled_entries(ev, w.grid(), w.bw(), TileSpec(k, k, k).clamp(w.grid())).first()[0]
            rows.append((n, k, (tiled + alone["products"]) / (alone["entries"] + alone["products"])))
        ev.unpersist()
    return spark.createDataFrame(rows, "workload string, tiles int, work double")


add("x05_tile_overhead", _work)


def _parity(spark, sf):
    rows = []
    for n in CLASSES:
        w = BY_NAME[n]
        ev = w.events(spark, sf, True)
        for k in CUTS:
            t = safe_tiles(TileSpec(k, k, k), w.grid(True), w.bw(True))
            loads = loads_of(ev, w.grid(True), t)
            path = dag.critical_path(dag.parity_colors(t), dag.weights_of(loads, t), t).length
            rows.append((n, k, *t.counts, path / max(1, sum(loads.values())), dag.graham_speedup(path / max(1, sum(loads.values())), 16)))
    return spark.createDataFrame(rows, "workload string, asked int, a int, b int, c int, share double, speedup double")


add("x06_parity_sets", _parity)
_FOUR = TileSpec(4, 4, 4)


def _parity_paths(spark, sf):
    """The heaviest chain of parity sets at four tiles an axis, on the check grids."""
    rows = []
    for n in CLASSES:
        w = BY_NAME[n]
        t = safe_tiles(_FOUR, w.grid(), w.bw())
        loads = loads_of(w.events(spark, sf), w.grid(), t)
        rows.append((n, sum(loads.values()), int(dag.critical_path(dag.parity_colors(t), dag.weights_of(loads, t), t).length)))
    return spark.createDataFrame(rows, "workload string, events bigint, path bigint")


def _parity_paths_sql():
    out = []
    for n in CLASSES:
        w = BY_NAME[n]
        t = safe_tiles(_FOUR, w.grid(), w.bw())
        out.append(f"select '{n}' as workload, events, path from (select sum(weight)::bigint as events, max(finish)::bigint as path from ({oracles.longest(t, oracles.loads(events_sql(w.set, w.grid()), w.grid(), t))}))")
    return " union all ".join(out)


add("x06_parity_paths", _parity_paths, _parity_paths_sql())


def _paths(spark, sf):
    """Both critical paths on the reported grids, up to 64 tiles an axis, whatever the bandwidth."""
    rows = []
    for n in CLASSES:
        w, g = BY_NAME[n], BY_NAME[n].grid(True)
        for k in (16, 64):
            t = TileSpec(k, k, k).clamp(g)
            loads = loads_of(events(spark, sf, w.set, g), g, t)
            share = measures.critical_share(loads, t)
            rows.append((n, k, share["parity"], share["load"], dag.graham_speedup(share["parity"], 16), dag.graham_speedup(share["load"], 16)))
    return spark.createDataFrame(rows, "workload string, tiles int, parity double, load double, parity_speedup double, load_speedup double")


add("x07_critical_paths", _paths)


def _scheduled(spark, sf):
    rows = []
    for n in CLASSES:
        w = BY_NAME[n]
        t = safe_tiles(TileSpec(8, 8, 8), w.grid(), w.bw())
        loads = loads_of(w.events(spark, sf), w.grid(), t)
        work = dag.weights_of(loads, t)
        for order, colors in (("parity", dag.parity_colors(t)), ("load", dag.greedy_colors(loads, t))):
            for p in (1, 2, 4, 8, 16):
                for barrier in (False, True):
                    span = max(end for *_, end in dag.list_schedule(colors, work, t, p, barrier=barrier))
                    rows.append((n, order, p, barrier, sum(work.values()) / span))
    return spark.createDataFrame(rows, "workload string, colors string, workers int, barrier boolean, speedup double")


add("x08_scheduled_sets", _scheduled)


def _replicated(spark, sf):
    """What copies on the critical path do to it, and what they cost, for 16 workers on the reported grids."""
    rows = []
    for n in CLASSES:
        w, g = BY_NAME[n], BY_NAME[n].grid(True)
        for k in (2, 4, 8, 16, 64):
            t = TileSpec(k, k, k).clamp(g)
            loads = loads_of(events(spark, sf, w.set, g), g, t)
            colors = dag.greedy_colors(loads, t)
            before = dag.critical_path(colors, dag.weights_of(loads, t), t).length
            plan = dag.replication_plan(loads, colors, t, 16)
            used = [x for x, v in loads.items() if v]
            rows.append((n, k, plan.rounds, sum(r - 1 for r in plan.copies.values()), sum(1 for x in used if plan.copies[x] > 1) / max(1, len(used)), float(before), float(plan.path.length), plan.limit))
    return spark.createDataFrame(rows, "workload string, tiles int, rounds int, copies int, copied_share double, path_before double, path double, half_share double")


add("x09_replicated_sets", _replicated)


def _ran(method):
    def query(spark, sf):
        rows = []
        for n in CLASSES:
            w = BY_NAME[n]
            rows += [(n, k, measures.seconds(w.cube(spark, sf, method, tiles=TileSpec(k, k, k)))) for k in (2, 4, 8)]
        return spark.createDataFrame(rows, "workload string, tiles int, seconds double")

    return query


for _k, _m in (("x06", "parity_sets"), ("x08", "loadaware_sets"), ("x09", "replicated_sets")):
    add(f"{_k}_{_m}_run", _ran(_m))
add(
    "x11_bandwidth_focus",
    lambda spark, sf: relational.bandwidth_sweep(events(spark, sf, "CITY", FOCUS), FOCUS, WIDE_AND_NARROW).groupBy("bw").agg(F.count("*").alias("voxels"), F.sum("hits").alias("hits"), F.max("hits").alias("most")),
    " union all ".join(f"select {i}::int as bw, count(*) as voxels, sum(hits)::bigint as hits, max(hits) as most from ({oracles.cube(events_sql('CITY', FOCUS), FOCUS, b)})" for i, b in enumerate(WIDE_AND_NARROW)),
)
