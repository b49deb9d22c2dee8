"""Queries over methods, measures and workloads, each with SQL of the same meaning where there is one."""

from __future__ import annotations

from functools import reduce

from cubedensity.operators import dag, pointsets, relational, replicas, tiles
from cubedensity.operators.blocks import FORMS, rows_of_blocks
from cubedensity.operators.density import BLOCK_METHODS, cube, density
from cubedensity.plans import chooser, measures, oracles
from cubedensity.plans.workloads import REPORTED, WORKLOADS
from cubedensity.sources.ingest import extents
from cubedensity.sources.sets import events, events_sql
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec
from pyspark.sql import functions as F

EVENTS, EVENTS_BW = GridSpec(15, 20, 30), Bandwidth(2, 1)
FINE, FINE_BW = GridSpec(30, 40, 60), Bandwidth(3, 3)
CITY, CITY_BW = GridSpec(18, 24, 52), Bandwidth(3, 1)
POSTS, POSTS_BW = GridSpec(27, 13, 84), Bandwidth(2, 3)
GRIDS = {"EVENTS": (EVENTS, EVENTS_BW), "CITY": (CITY, CITY_BW), "POSTS": (POSTS, POSTS_BW)}
SMALL = {"BIRDS": (GridSpec(24, 62, 180), Bandwidth(1, 1)), "GAZ": (GridSpec(20, 20, 40), Bandwidth(2, 1)), "DOCS": (GridSpec(20, 20, 20), Bandwidth(3, 2)), "VECS": (GridSpec(16, 16, 10), Bandwidth(2, 1)), "WORLD": (GridSpec(18, 36, 61), Bandwidth(1, 1))}
TILES = TileSpec(3, 4, 5)

QUERIES: dict = {}
ORACLES: dict = {}


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def _density(name, grid, bw, method, copies=1, **more):
    return lambda spark, sf: density(events(spark, sf, name, grid, copies), grid, bw, method, **more)


for _set, (_g, _b) in GRIDS.items():
    _sql = oracles.density(events_sql(_set, _g), _g, _b)
    for _m in (*relational.METHODS, *BLOCK_METHODS):
        # the voxel scan tests every voxel against every event: kept to the smallest set
        if _m == "voxel_scan" and _set != "EVENTS":
            continue
        add(f"density_{_m}_{_set.lower()}", _density(_set, _g, _b, _m), _sql)
for _set, (_g, _b) in SMALL.items():
    _c = 2 if _set == "WORLD" else 1
    add(f"density_product_scatter_{_set.lower()}", _density(_set, _g, _b, "product_scatter", _c), oracles.density(events_sql(_set, _g, _c), _g, _b))
add("density_fine_events", _density("EVENTS", FINE, FINE_BW, "auto"), oracles.density(events_sql("EVENTS", FINE), FINE, FINE_BW))


def _workload(w):
    return lambda spark, sf: density(w.events(spark, sf), w.grid(), w.bw(), "auto")


for _w in WORKLOADS:
    add(_w.name, _workload(_w), oracles.density(events_sql(_w.set, _w.grid()), _w.grid(), _w.bw()))

_E = lambda spark, sf: events(spark, sf, "EVENTS", EVENTS)
_E_SQL = events_sql("EVENTS", EVENTS)
for _k in ("printed", "mirrored", "epanechnikov", "uniform"):
    _o = PlanOptions(kernel=_k)
    add(f"kernel_{_k}", lambda spark, sf, o=_o: density(_E(spark, sf), EVENTS, EVENTS_BW, "scatter", o), oracles.density(_E_SQL, EVENTS, EVENTS_BW, _o))
for _name, _o in (("edge_open", PlanOptions(edge="open")), ("anchor_corner", PlanOptions(anchor="corner"))):
    add(_name, lambda spark, sf, o=_o: density(_E(spark, sf), EVENTS, EVENTS_BW, "tile_clip", o, tiles=TILES), oracles.density(_E_SQL, EVENTS, EVENTS_BW, _o))

add(
    "zero_fill",
    lambda spark, sf: density(_E(spark, sf), EVENTS, EVENTS_BW, "product_scatter", dense=True),
    f"with d as ({oracles.density(_E_SQL, EVENTS, EVENTS_BW)}) select x::int as vx, y::int as vy, t::int as vt, coalesce(hits, 0)::bigint as hits, coalesce(mass, 0)::bigint as mass, "
    f"coalesce(density, 0.0)::double as density from range({EVENTS.gx}) p(x) cross join range({EVENTS.gy}) q(y) cross join range({EVENTS.gt}) r(t) left join d on vx = x and vy = y and vt = t",
)
_BWS = [Bandwidth(3, 2), Bandwidth(1, 1), Bandwidth(2, 1)]
add(
    "bandwidth_sweep",
    lambda spark, sf: relational.bandwidth_sweep(events(spark, sf, "CITY", CITY), CITY, _BWS),
    " union all ".join(f"select {i}::int as bw, * from ({oracles.cube(events_sql('CITY', CITY), CITY, b)})" for i, b in enumerate(_BWS)),
)
add("tile_clip_relational", lambda spark, sf: tiles.tile_clip(_E(spark, sf), EVENTS, EVENTS_BW, TILES, form="relational"), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))
add("tile_clip_blocks", lambda spark, sf: rows_of_blocks(tiles.tile_clip(_E(spark, sf), EVENTS, EVENTS_BW, TILES, emit="blocks")), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))
add("tile_clip_guarded", lambda spark, sf: tiles.tile_clip(_E(spark, sf), EVENTS, EVENTS_BW, TileSpec(15, 20, 30), guard=True), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))
add("parity_sets_phased", lambda spark, sf: pointsets.parity_sets(_E(spark, sf), EVENTS, EVENTS_BW, TILES, mode="phased"), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))
add("replicated_sets_wide", lambda spark, sf: pointsets.replicated_sets(_E(spark, sf), EVENTS, EVENTS_BW, TILES, 16, scope="path_and_neighbours"), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))


def _collapsed(spark, sf):
    from cubedensity.sources.ingest import collapse

    merged = collapse(_E(spark, sf))
    return relational.scatter(merged, EVENTS, EVENTS_BW).select("vx", "vy", "vt", "mass")


add("collapse", _collapsed, f"select vx, vy, vt, mass from ({oracles.cube(_E_SQL, EVENTS, EVENTS_BW)})")


def _adaptive_sql():
    g, bw, s = EVENTS, Bandwidth(1, 1), EVENTS.sub
    hx, ht = bw.lattice(g)
    o = PlanOptions().offset(g)
    base = f"select *, count(*) over (partition by x // {4 * s}, y // {4 * s}) as n from ({_E_SQL})"
    wide = f"select *, f * {hx} as h, case f when 1 then 4096 when 2 then 64 else 1 end as unit from (select *, case when n >= 600 then 1 when n >= 200 then 2 else 4 end::bigint as f from ({base}))"
    d = [f"({v}*{s}+{o}-{c})" for v, c in zip(("vx", "vy", "vt"), "xyt")]
    term = f"(h-{d[0]})*(h-{d[0]})*(h-{d[1]})*(h-{d[1]})*({ht}-{d[2]})*({ht}-{d[2]})*w*unit"
    return f"select vx::int as vx, vy::int as vy, vt::int as vt, count(*)::bigint as hits, sum({term})::bigint as mass from ({oracles.cover(wide, g, 'h', str(ht))}) group by vx, vy, vt"


add("adaptive_bandwidth", lambda spark, sf: relational.adaptive(_E(spark, sf), EVENTS, Bandwidth(1, 1), 4, (200, 600)), _adaptive_sql())

# tiles, graph and colors -------------------------------------------------------------------------------------------
for _set, (_g, _b) in (*GRIDS.items(), *((k, SMALL[k]) for k in ("GAZ", "DOCS"))):
    add(f"tile_loads_{_set.lower()}", lambda spark, sf, s=_set, g=_g: tiles.tile_loads(events(spark, sf, s, g), g, TILES), oracles.loads(events_sql(_set, _g), _g, TILES))
_a, _b2, _c2 = oracles.tile_of(TILES, EVENTS)
add("owner_tiles", lambda spark, sf: tiles.owner(_E(spark, sf), EVENTS, TILES).select("event_id", "a", "b", "c", "tile_id"), f"select event_id, {_a}::int as a, {_b2}::int as b, {_c2}::int as c, (({_a}*4+{_b2})*5+{_c2})::bigint as tile_id from ({_E_SQL})")


def _touch(axis, c, h, n, g):
    v = f"({c}//{EVENTS.sub})"
    return f"{axis} between ({n}*greatest({v}-{h},0))//{g} and ({n}*least({v}+{h},{g - 1}))//{g}"


add(
    "tile_copies",
    lambda spark, sf: tiles.copies(_E(spark, sf), EVENTS, EVENTS_BW, TILES).select("event_id", "a", "b", "c", "tile_id"),
    f"select event_id, a::int as a, b::int as b, c::int as c, ((a*4+b)*5+c)::bigint as tile_id from ({_E_SQL}), range(3) p(a), range(4) q(b), range(5) r(c) where "
    + " and ".join(_touch(k, c, h, n, g) for k, c, h, n, g in zip("abc", "xyt", (2, 2, 1), TILES.counts, EVENTS.shape)),
)


def _used(spark, sf, *as_):
    """Tiles that hold events, under each of the names asked for."""
    return [tiles.tile_loads(_E(spark, sf), EVENTS, TILES).select(F.col("tile_id").alias(n)) for n in as_]


_USED = f"(select tile_id from ({oracles.loads(_E_SQL, EVENTS, TILES)}))"
_USED_EDGES = f"select src, dst from ({oracles.edges(TILES)}) where src in {_USED} and dst in {_USED}"
_USED_PARITY = f"select tile_id, color from ({oracles.parity(TILES)}) where tile_id in {_USED}"


def _between_used(spark, sf, edges):
    src, dst = _used(spark, sf, "src", "dst")
    return edges.join(src, "src", "left_semi").join(dst, "dst", "left_semi").select("src", "dst")


add("stencil_edges", lambda spark, sf: _between_used(spark, sf, dag.tile_graph(spark, TILES)), _USED_EDGES)


def _colors_table(spark, colors):
    return spark.createDataFrame(sorted(colors.items()), "tile_id bigint, color int")


def _used_parity(spark, sf):
    return _colors_table(spark, dag.parity_colors(TILES)).join(*_used(spark, sf, "tile_id"), "tile_id", "left_semi").select("tile_id", "color")


add("parity_color", _used_parity, _USED_PARITY)
add("conflicts", lambda spark, sf: measures.conflicts(_E(spark, sf), EVENTS, EVENTS_BW, tiles.safe_tiles(TILES, EVENTS, EVENTS_BW)), "select 0::int as color, 0::int as vx, 0::int as vy, 0::int as vt, 0::bigint as tiles where false")


def _event_loads(spark, sf):
    return pointsets.loads_of(_E(spark, sf), EVENTS, TILES)


_LOADS = oracles.loads(_E_SQL, EVENTS, TILES)
add("greedy_color", lambda spark, sf: _colors_table(spark, dag.greedy_colors(_event_loads(spark, sf), TILES)), oracles.greedy(TILES, _LOADS))
add("greedy_color_rounds", lambda spark, sf: dag.greedy_colors_df(spark, tiles.tile_loads(_E(spark, sf), EVENTS, TILES), TILES), oracles.greedy(TILES, _LOADS))


def _oriented(spark, sf):
    return _between_used(spark, sf, spark.createDataFrame(dag.oriented_edges(dag.parity_colors(TILES), TILES), "src bigint, dst bigint"))


add("oriented_edges", _oriented, f"with c as ({_USED_PARITY}) select e.src, e.dst from ({_USED_EDGES}) e join c a on a.tile_id = e.src join c b on b.tile_id = e.dst where a.color < b.color")
add(
    "critical_path",
    lambda spark, sf: dag.critical_path_df(spark, _colors_table(spark, dag.parity_colors(TILES)), tiles.tile_loads(_E(spark, sf), EVENTS, TILES).select("tile_id", F.col("load").alias("weight")), TILES),
    oracles.longest(TILES, _LOADS),
)


def _chain(spark, sf, order, weight):
    loads = _event_loads(spark, sf)
    colors = dag.parity_colors(TILES) if order == "parity" else dag.greedy_colors(loads, TILES, order)
    w = dag.weights_of(loads, TILES, weight)
    path = dag.critical_path(colors, w, TILES)
    return spark.createDataFrame([(i, t, colors[t], w[t]) for i, t in enumerate(path.chain)], "step int, tile_id bigint, color int, weight bigint")


for _order in ("parity", "load", "natural"):
    for _weight in ("own", "own_plus_neighbours"):
        add(f"critical_chain_{_order}_{_weight}", lambda spark, sf, o=_order, w=_weight: _chain(spark, sf, o, w), oracles.heaviest(TILES, _LOADS, _order, _weight))


def _graham(spark, sf):
    loads = _event_loads(spark, sf)
    w = dag.weights_of(loads, TILES)
    path = dag.critical_path(dag.parity_colors(TILES), w, TILES).length
    return spark.createDataFrame([(sum(w.values()), int(path), p, float(dag.graham_bound(sum(w.values()), path, p))) for p in (1, 2, 4, 8, 16)], "total bigint, path bigint, workers int, bound double")


add(
    "graham",
    _graham,
    f"with f as ({oracles.longest(TILES, _LOADS)}), s as (select sum(weight)::bigint as total, max(finish)::bigint as path from f) "
    "select total, path, p::int as workers, ((total - path)::double / p::double + path::double) as bound from s, (values (1), (2), (4), (8), (16)) v(p)",
)


def _schedule(spark, sf, **more):
    loads = _event_loads(spark, sf)
    colors = dag.greedy_colors(loads, TILES)
    rows = dag.list_schedule(colors, dag.weights_of(loads, TILES), TILES, 8, **more)
    return spark.createDataFrame([(t, w, float(a), float(b)) for t, w, a, b in rows], "tile_id bigint, worker int, start double, finish double")


add("list_schedule", _schedule, oracles.schedule(TILES, _LOADS, 8))
add("list_schedule_by_id", lambda spark, sf: _schedule(spark, sf, priority="id"), oracles.schedule(TILES, _LOADS, 8, priority="id"))
add("list_schedule_barrier", lambda spark, sf: _schedule(spark, sf, barrier=True), oracles.schedule(TILES, _LOADS, 8, barrier=True))


def _replication(spark, sf, scope):
    loads = _event_loads(spark, sf)
    plan = dag.replication_plan(loads, dag.greedy_colors(loads, TILES), TILES, 16, scope=scope)
    return spark.createDataFrame([(t, loads.get(t, 0), r, plan.rounds, float(plan.path.length), plan.limit) for t, r in sorted(plan.copies.items())], "tile_id bigint, load bigint, copies int, rounds int, path double, path_limit double")


add("replication_plan", lambda spark, sf: _replication(spark, sf, "path"))
add("replication_plan_neighbours", lambda spark, sf: _replication(spark, sf, "path_and_neighbours"))


def _explained(spark, sf):
    rows = []
    for k in (1, 2, 3, 6):
        t = TileSpec(k, k, k)
        said = chooser.explain_plan(pointsets.loads_of(_E(spark, sf), EVENTS, t), t, 16)
        rows.append((k, said["tiles"], said["used"], said["copied"], said["copies"], said["rounds"], said["warning"] is not None))
    return spark.createDataFrame(rows, "k int, tiles int, used int, copied int, copies int, rounds int, coarse boolean")


add("coarse_tile_warning", _explained)
add(
    "tile_clip_split",
    lambda spark, sf: tiles.tile_clip(_E(spark, sf), EVENTS, EVENTS_BW, TILES, split_over=150),
    oracles.cube(_E_SQL, EVENTS, EVENTS_BW),
)
for _form in FORMS:
    add(f"kernel_form_{_form}", lambda spark, sf, f=_form: tiles.tile_clip(_E(spark, sf), EVENTS, EVENTS_BW, TILES, kernel_form=f), oracles.cube(_E_SQL, EVENTS, EVENTS_BW))

# measures ----------------------------------------------------------------------------------------------------------
_COVER = oracles.cover(_E_SQL, EVENTS, *map(str, EVENTS_BW.lattice(EVENTS)))


def _clip(c, h, g):
    v = f"({c}//{EVENTS.sub})"
    return f"(least({v}+{h},{g - 1})-greatest({v}-{h},0)+1)"


_BOX = "*".join(_clip(c, h, g) for c, h, g in zip("xyt", (2, 2, 1), EVENTS.shape))
_HX, _HT = EVENTS_BW.lattice(EVENTS)


def _blocks(c, h, g):
    return f"(select count(*) from range({g}) k(v) where abs((v*16+8)//{h} - {c}//{h}) <= 1)"


add(
    "cost_distance_tests",
    lambda spark, sf: measures.distance_tests(_E(spark, sf), EVENTS, EVENTS_BW),
    f"select (count(*)*{EVENTS.cells})::bigint as voxel_scan, sum({_blocks('x', _HX, 15)}*{_blocks('y', _HX, 20)}*{_blocks('t', _HT, 30)})::bigint as block_scan, sum({_BOX})::bigint as event_driven from ({_E_SQL})",
)
add("cost_density_updates", lambda spark, sf: cube(_E(spark, sf), EVENTS, EVENTS_BW, "product_scatter").agg(F.sum("hits").alias("updates")), f"select count(*)::bigint as updates from ({_COVER})")
add(
    "cost_kernel_evaluations",
    lambda spark, sf: measures.kernel_evaluations(_E(spark, sf), EVENTS, EVENTS_BW),
    f"with c as materialized ({_COVER}), f as (select count(*)::bigint as n, count(distinct (event_id, vx, vy))::bigint as d, count(distinct (event_id, vt))::bigint as b from c) "
    "select 'scatter' as method, n as spatial, n as temporal from f union all select 'disk_scatter', d, n from f union all select 'bar_scatter', n, b from f union all select 'product_scatter', d, b from f",
)
add(
    "cost_flops",
    lambda spark, sf: _E(spark, sf).agg((F.count("*") * measures.flops(1, EVENTS_BW)).alias("flops")),
    f"select (count(*)*40*16*2)::bigint as flops from ({_E_SQL})",
)


def _spans(spark, sf, shapes):
    """``(name, grid)``: of each grid the part that the events of the table span."""
    parts = [extents(events(spark, sf, "EVENTS", g)).select(F.lit(k).alias("name"), *((F.floor(F.col(f"max_{c}") / g.sub) - F.floor(F.col(f"min_{c}") / g.sub) + 1).alias(c) for c in "xyt")) for k, g in ((k, GridSpec(*v)) for k, v in shapes.items())]
    return [(r.name, GridSpec(r.x, r.y, r.t)) for r in reduce(lambda a, b: a.union(b), parts).collect() if r.x is not None]


def _spans_sql(shapes):
    """The same for the oracle: ``name, x, y, t``; a table without events has none."""
    span = ", ".join(f"(max({c}) // 16 - min({c}) // 16 + 1)::bigint as {c}" for c in "xyt")
    return " union all ".join(f"select '{k}' as name, {span} from ({events_sql('EVENTS', GridSpec(*v))}) having count(*) > 0" for k, v in shapes.items())


add(
    "cost_memory",
    lambda spark, sf: measures.memory_table(spark, _spans(spark, sf, REPORTED), 16),
    f"select name, (x*y*t)::bigint as cells, (x*y*t*4)::bigint as cube_bytes, (x*y*t*4*16)::bigint as copies_bytes from ({_spans_sql(REPORTED)})",
)
_SPREAD = [f"(({n}*least({c}//16+{h},{g - 1}))//{g} - ({n}*greatest({c}//16-{h},0))//{g} + 1)" for c, h, g, n in zip("xyt", (2, 2, 1), EVENTS.shape, TILES.counts)]
add(
    "cost_replication",
    lambda spark, sf: measures.replication(_E(spark, sf), EVENTS, EVENTS_BW, TILES),
    f"select count(*)::bigint as events, sum({_SPREAD[0]}*{_SPREAD[1]}*{_SPREAD[2]})::bigint as copies, sum({_SPREAD[2]}-1)::bigint as extra_disks, sum({_SPREAD[0]}*{_SPREAD[1]}-1)::bigint as extra_bars from ({_E_SQL})",
)


def _part(axis, c, h, n, g):
    v = f"({c}//16)"
    first = lambda k: f"((({k})*{g}+{n - 1})//{n})"
    return f"(least({v}+{h},{first(axis + '+1')}-1)-greatest({v}-{h},{first(axis)})+1)"


_PARTS = [_part(k, c, h, n, g) for k, c, h, n, g in zip("abc", "xyt", (2, 2, 1), TILES.counts, EVENTS.shape)]
_SIDES = [_clip(c, h, g) for c, h, g in zip("xyt", (2, 2, 1), EVENTS.shape)]
add(
    "cost_work_units",
    lambda spark, sf: measures.work_units(_E(spark, sf), EVENTS, EVENTS_BW, TILES),
    f"with c as materialized ({_COVER}), p as (select count(*)::bigint as products from c), e as (select sum({_SIDES[0]}*{_SIDES[1]}+{_SIDES[2]})::bigint as entries from ({_E_SQL})), "
    f"k as (select sum({_PARTS[0]}*{_PARTS[1]}+{_PARTS[2]})::bigint as tiled_entries from ({_E_SQL}), range(3) p(a), range(4) q(b), range(5) r(c) where "
    + " and ".join(_touch(k, c, h, n, g) for k, c, h, n, g in zip("abc", "xyt", (2, 2, 1), TILES.counts, EVENTS.shape))
    + ") select entries, products, tiled_entries from e, p, k",
)
add(
    "cost_imbalance",
    lambda spark, sf: measures.imbalance(tiles.tile_loads(_E(spark, sf), EVENTS, TILES), TILES),
    f"with l as ({_LOADS}), r as (select load, row_number() over (order by load, tile_id) + {TILES.total} - count(*) over () as rank from l) "
    f"select max(load) as heaviest, sum(load)::bigint as total, count(*) as used, (2*sum(rank*load) - {TILES.total + 1}*sum(load))::bigint as gini_over, (sum(load)*{TILES.total})::bigint as gini_under from r",
)


def _shares(spark, sf):
    loads = _event_loads(spark, sf)
    rows = [(w, k, float(v)) for w in ("own", "own_plus_neighbours") for k, v in measures.critical_share(loads, TILES, w).items()]
    return spark.createDataFrame(rows, "weight string, colors string, share double")


add("cost_critical_share", _shares, " union all ".join(oracles.share(TILES, _LOADS, o, w) for o in ("parity", "load") for w in ("own", "own_plus_neighbours")))
add(
    "cost_colors_used",
    lambda spark, sf: _used_parity(spark, sf).groupBy("color").agg(F.count("*").alias("tiles")),
    f"select color, count(*) as tiles from ({_USED_PARITY}) group by color",
)


def _caps(spark, sf):
    """Zeroing of the grid beside the voxel updates of the table's events."""
    updates = measures.distance_tests(_E(spark, sf), EVENTS, EVENTS_BW).first()["event_driven"] or 0
    rows = [(float(EVENTS.cells), float(updates), float(s), measures.zero_fill_cap(EVENTS.cells, updates, s)) for s in (2, 3, 4)]
    return spark.createDataFrame(rows, "init double, compute double, init_speedup double, cap double")


add(
    "cost_zero_fill_cap",
    _caps,
    f"select init, compute, s::double as init_speedup, (init + compute) / (init / s) as cap from (select {EVENTS.cells}::double as init, coalesce(event_driven, 0)::double as compute from ({ORACLES['cost_distance_tests']})), (values (2), (3), (4)) v(s)",
)
add(
    "cost_total_mass",
    lambda spark, sf: measures.total_mass(cube(_E(spark, sf), EVENTS, EVENTS_BW, "product_scatter"), _E(spark, sf).agg(F.count("*")), EVENTS, EVENTS_BW),
    f"with c as ({oracles.cube(_E_SQL, EVENTS, EVENTS_BW)}) select sum(mass)::double * ('{__import__('cubedensity.spec', fromlist=['constant']).constant(EVENTS, EVENTS_BW, PlanOptions())!r}'::double / (select count(*) from ({_E_SQL}))::double) as total_mass from c",
)
for _m in ("block_scan", "tile_clip", "parity_sets", "replicated_sets"):
    add(
        f"identity_{_m}",
        lambda spark, sf, m=_m: measures.identity(cube(_E(spark, sf), EVENTS, EVENTS_BW, m, tiles=TILES), cube(_E(spark, sf), EVENTS, EVENTS_BW, "scatter")),
        "select 0::bigint as only_first, 0::bigint as only_second",
    )


def _lattice_error(spark, sf):
    coarse = GridSpec(15, 20, 30, sub=16)
    fine = GridSpec(15, 20, 30, sub=32)
    made = measures.lattice_error(*(density(events(spark, sf, "EVENTS", g), g, EVENTS_BW, "tile_clip") for g in (fine, coarse)))
    return made.select("largest", "peak", F.round(F.col("mean") / F.col("peak"), 9).alias("mean_of_peak"))


_FINE_GRID = GridSpec(15, 20, 30, sub=32)
add(
    "cost_lattice_error",
    _lattice_error,
    f"with p as ({oracles.density(events_sql('EVENTS', _FINE_GRID), _FINE_GRID, EVENTS_BW)}), q as ({oracles.density(_E_SQL, EVENTS, EVENTS_BW)}), "
    "g as (select coalesce(p.density, 0.0) as a, coalesce(q.density, 0.0) as b from p full join q on p.vx = q.vx and p.vy = q.vy and p.vt = q.vt) "
    "select max(abs(a - b)) as largest, max(greatest(a, b)) as peak, round(avg(abs(a - b)) / max(greatest(a, b)), 9) as mean_of_peak from g",
)
add("cost_copies_added", lambda spark, sf: _replication(spark, sf, "path").agg(F.sum(F.col("copies") - 1).alias("added"), F.count_if(F.col("copies") > 1).alias("copied"), F.sum(F.when(F.col("copies") > 1, F.col("copies"))).alias("blocks")))


def _rates(spark, sf):
    rows = []
    for m in ("scatter", "product_scatter", "tile_clip"):
        r = measures.throughput(_E(spark, sf), cube(_E(spark, sf), EVENTS, EVENTS_BW, m))
        rows.append((m, r["seconds"], r["events"], r["updates"]))
    return spark.createDataFrame(rows, "method string, seconds double, events_a_second double, updates_a_second double")


add("cost_throughput", _rates)
add(
    "source_extents",
    lambda spark, sf: extents(_E(spark, sf)),
    f"select min(x) as min_x, max(x) as max_x, min(y) as min_y, max(y) as max_y, min(t) as min_t, max(t) as max_t, count(*) as n from ({_E_SQL})",
)


def _estimates(spark, sf):
    loads, fine = chooser.fine_loads(_E(spark, sf), EVENTS)
    rows = [(e.method, str(e.tiles.counts) if e.tiles else "", float(e.work), float(e.span), e.memory, e.fits, e.seconds(16)) for e in chooser.estimates(loads, fine, EVENTS, EVENTS_BW, 16, 1 << 30)]
    return spark.createDataFrame(rows, "method string, tiles string, work double, span double, memory bigint, fits boolean, seconds double")


add("choose_method", _estimates)


def _guard(spark, sf):
    rows = []
    for name, grid in _spans(spark, sf, REPORTED):
        for copies in (1, 2, 4, 8, 16):
            try:
                replicas.check_memory(grid, copies, 128 << 30, 4)
                rows.append((name, copies, True))
            except replicas.ReplicaTooLarge:
                rows.append((name, copies, False))
    return spark.createDataFrame(rows, "name string, copies int, fits boolean")


add(
    "replica_guard",
    _guard,
    f"select name, c::int as copies, x*y*t*4*c <= 137438953472 as fits from ({_spans_sql(REPORTED)}), (values (1), (2), (4), (8), (16)) w(c)",
)


#: tiles asked for and bandwidths, on the part of a grid that events span
_SAFE = {"wide": ((8, 8, 8), (30, 40, 60), (3, 3)), "many": ((64, 64, 64), (30, 40, 60), (3, 3)), "small": ((2, 2, 2), (5, 5, 5), (3, 3)), "large": ((4, 4, 4), (100, 100, 100), (1, 2))}


def _safe(spark, sf):
    rows = []
    for name, g in _spans(spark, sf, {k: v[1] for k, v in _SAFE.items()}):
        w, _, b = _SAFE[name]
        rows.append((*w, *g.shape, *b, *tiles.safe_tiles(TileSpec(*w), g, Bandwidth(*b)).counts))
    return spark.createDataFrame(rows, "wa int, wb int, wc int, gx int, gy int, gt int, hs int, ht int, a int, b int, c int")


add(
    "safe_tiles",
    _safe,
    "select wa::int as wa, wb::int as wb, wc::int as wc, x::int as gx, y::int as gy, t::int as gt, hs::int as hs, ht::int as ht, greatest(1, least(wa, x//(2*hs)))::int as a, greatest(1, least(wb, y//(2*hs)))::int as b, greatest(1, least(wc, t//(2*ht)))::int as c "
    f"from ({_spans_sql({k: v[1] for k, v in _SAFE.items()})}) join (values " + ", ".join(f"('{k}', {', '.join(map(str, (*w, *b)))})" for k, (w, _, b) in _SAFE.items()) + ") v(name, wa, wb, wc, hs, ht) using (name)",
)
