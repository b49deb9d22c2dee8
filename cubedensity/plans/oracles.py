"""SQL of the same meaning for the oracle engine, written from the definition.

A voxel is joined with every event whose cylinder holds its sampling point; there are no boxes, tiles or blocks here.
"""

from __future__ import annotations

from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec, constant


def _factors(options: PlanOptions, hx: str, ht: str, dx: str, dy: str, dt: str) -> str:
    if options.kernel == "printed":
        return f"({hx}-{dx})*({hx}-{dx})*({hx}-{dy})*({hx}-{dy})*({ht}-{dt})*({ht}-{dt})"
    if options.kernel == "mirrored":
        return f"({hx}-abs({dx}))*({hx}-abs({dx}))*({hx}-abs({dy}))*({hx}-abs({dy}))*({ht}-abs({dt}))*({ht}-abs({dt}))"
    if options.kernel == "epanechnikov":
        return f"({hx}*{hx}-{dx}*{dx}-{dy}*{dy})*({ht}*{ht}-{dt}*{dt})"
    return "1"


def cover(events: str, grid: GridSpec, hx: str, ht: str, options: PlanOptions = PlanOptions()) -> str:
    """Rows (event columns, vx, vy, vt) of every event and every voxel that it covers. ``hx`` and ``ht`` may be columns."""
    s, o = grid.sub, options.offset(grid)
    at = lambda v, c: f"({v}*{s}+{o}-{c})"
    less = "<=" if options.edge == "closed_time" else "<"
    ex = f"select e.*, vx from ({events}) e join range({grid.gx}) r(vx) on vx*{s}+{o} > x-{hx} and vx*{s}+{o} < x+{hx}"
    ey = f"select f.*, vy from ({ex}) f join range({grid.gy}) r(vy) on vy*{s}+{o} > y-{hx} and vy*{s}+{o} < y+{hx} where {at('vx', 'x')}*{at('vx', 'x')}+{at('vy', 'y')}*{at('vy', 'y')} < {hx}*{hx}"
    return f"select g.*, vt from ({ey}) g join range({grid.gt}) r(vt) on t-{ht} {less} vt*{s}+{o} and vt*{s}+{o} {less} t+{ht}"


def cube(events: str, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions(), carry: str = "", factor: str = "w") -> str:
    """``select vx, vy, vt, hits, mass``."""
    hx, ht = bw.lattice(grid)
    s, o = grid.sub, options.offset(grid)
    d = [f"({v}*{s}+{o}-{c})" for v, c in zip(("vx", "vy", "vt"), "xyt")]
    keys = f"{carry}, vx, vy, vt" if carry else "vx, vy, vt"
    head = f"{carry}, " if carry else ""
    return (
        f"select {head}vx::int as vx, vy::int as vy, vt::int as vt, count(*)::bigint as hits, "
        f"sum({_factors(options, str(hx), str(ht), *d)}*{factor})::bigint as mass from ({cover(events, grid, str(hx), str(ht), options)}) group by {keys}"
    )


def density(events: str, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> str:
    found = cube(events, grid, bw, options)
    return f"select *, mass::double * ('{constant(grid, bw, options)!r}'::double / (select count(*) from ({events}))::double) as density from ({found})"


def tile_of(tiles: TileSpec, grid: GridSpec) -> tuple[str, str, str]:
    return tuple(f"(({n}*({c}//{grid.sub}))//{g})" for n, c, g in zip(tiles.counts, "xyt", grid.shape))


def loads(events: str, grid: GridSpec, tiles: TileSpec) -> str:
    a, b, c = tile_of(tiles, grid)
    return f"select (({a}*{tiles.b}+{b})*{tiles.c}+{c})::bigint as tile_id, {a}::int as a, {b}::int as b, {c}::int as c, count(*)::bigint as load from ({events}) group by all"


def edges(tiles: TileSpec) -> str:
    t = f"select a::bigint as a, b::bigint as b, c::bigint as c, ((a*{tiles.b}+b)*{tiles.c}+c)::bigint as id from range({tiles.a}) p(a), range({tiles.b}) q(b), range({tiles.c}) r(c)"
    return f"select u.id as src, v.id as dst from ({t}) u, ({t}) v where u.id <> v.id and abs(u.a-v.a) <= 1 and abs(u.b-v.b) <= 1 and abs(u.c-v.c) <= 1"


def parity(tiles: TileSpec) -> str:
    return f"select ((a*{tiles.b}+b)*{tiles.c}+c)::bigint as tile_id, ((a%2)*4+(b%2)*2+c%2)::int as color from range({tiles.a}) p(a), range({tiles.b}) q(b), range({tiles.c}) r(c)"


def longest(tiles: TileSpec, load_sql: str) -> str:
    """Finish of each tile under parity colors: the heaviest chain that ends there, color after color."""
    out = [f"with node as (select p.tile_id, p.color, coalesce(l.load, 0)::bigint as weight from ({parity(tiles)}) p left join ({load_sql}) l using (tile_id)), edge as ({edges(tiles)})"]
    out.append(", f0 as (select tile_id, color, weight, weight as finish from node where color = 0)")
    for k in range(1, 8):
        before = " union all ".join(f"select tile_id, finish from f{j}" for j in range(k))
        out.append(
            f", f{k} as (select n.tile_id, n.color, n.weight, (n.weight + coalesce(max(d.finish), 0))::bigint as finish from node n left join edge e on e.src = n.tile_id "
            f"left join ({before}) d on d.tile_id = e.dst where n.color = {k} group by n.tile_id, n.color, n.weight)"
        )
    return "".join(out) + " " + " union all ".join(f"select * from f{k}" for k in range(8))


# plans on tiles, as recursions whose state is a list with an entry for each tile -------------------------------------
def _nodes(tiles: TileSpec, load_sql: str) -> str:
    """CTEs ``node(tile_id, load, near)`` and ``edge``: every tile, empty ones included, with its neighbours."""
    return (
        f"edge as materialized ({edges(tiles)}), node as materialized (select p.tile_id, coalesce(any_value(l.load), 0)::bigint as load, list(e.dst order by e.dst) as near "
        f"from ({parity(tiles)}) p left join ({load_sql}) l using (tile_id) join edge e on e.src = p.tile_id group by p.tile_id)"
    )


def _set(items: str, at: str, value: str, total: int) -> str:
    return f"list_transform(range({total}), lambda i: case when i = {at} then {value} else {items}[i + 1] end)"


def _greedy(tiles: TileSpec, order: str) -> str:
    """CTE ``paint(color)``: a list of the color of each tile, given in turn."""
    n = tiles.total
    by = {"load": "load desc, tile_id", "natural": "tile_id"}[order]
    free = "list_min(list_filter(range(27), lambda c: not list_contains(list_transform(o.near, lambda m: r.color[m + 1]), c)))"
    return (
        f"turn as materialized (select tile_id, near, row_number() over (order by {by}) as k from node), "
        f"run(k, color) as (select 0::bigint, list_transform(range({n}), lambda i: (-1)::bigint) union all "
        f"select o.k, {_set('r.color', 'o.tile_id', free, n)} from run r join turn o on o.k = r.k + 1), paint as materialized (select color from run where k = {n})"
    )


def _paint(tiles: TileSpec, order: str) -> str:
    if order != "parity":
        return _greedy(tiles, order)
    return f"paint as materialized (select list(color::bigint order by tile_id) as color from ({parity(tiles)}))"


def greedy(tiles: TileSpec, load_sql: str, order: str = "load") -> str:
    return f"with recursive {_nodes(tiles, load_sql)}, {_greedy(tiles, order)} select (unnest(range({tiles.total})))::bigint as tile_id, unnest(color)::int as color from paint"


def _task(weight: str) -> str:
    """CTE ``task(tile_id, near, color, weight)``."""
    more = " + coalesce((select sum(m.load) from node m where list_contains(n.near, m.tile_id)), 0)" if weight == "own_plus_neighbours" else ""
    return f"task as materialized (select n.tile_id, n.near, p.color[n.tile_id + 1] as color, (n.load{more})::bigint as weight from node n, paint p)"


def _finish(tiles: TileSpec) -> str:
    """CTE ``chain(fin, came)``: when each tile ends on its heaviest chain, and the neighbour that it waits for."""
    n = tiles.total
    cand = "list_filter(o.near, lambda m: p.color[m + 1] < o.color and f.fin[m + 1] > 0)"
    best = f"coalesce(list_max(list_transform({cand}, lambda m: f.fin[m + 1])), 0)"
    return (
        f"line as materialized (select *, row_number() over (order by color, tile_id) as k from task), "
        f"flow(k, fin, came) as (select 0::bigint, list_transform(range({n}), lambda i: 0::bigint), list_transform(range({n}), lambda i: (-1)::bigint) union all "
        f"select o.k, {_set('f.fin', 'o.tile_id', 'b.best + o.weight', n)}, {_set('f.came', 'o.tile_id', 'coalesce(list_min(list_filter(b.cand, lambda m: f.fin[m + 1] = b.best)), -1)', n)} "
        f"from flow f join line o on o.k = f.k + 1, paint p, lateral (select {best} as best, {cand} as cand) b), "
        f"chain as materialized (select fin, came from flow where k = {n})"
    )


def heaviest(tiles: TileSpec, load_sql: str, order: str, weight: str) -> str:
    """The heaviest chain: ``step, tile_id, color, weight``."""
    return (
        f"with recursive {_nodes(tiles, load_sql)}, {_paint(tiles, order)}, {_task(weight)}, {_finish(tiles)}, "
        "walk(d, t) as (select 0::bigint, (list_position(fin, list_max(fin)) - 1)::bigint from chain union all select d + 1, c.came[t + 1] from walk, chain c where c.came[t + 1] >= 0) "
        "select ((select max(d) from walk) - d)::int as step, t as tile_id, color::int as color, weight from walk join task on tile_id = t"
    )


def share(tiles: TileSpec, load_sql: str, order: str, weight: str) -> str:
    """One row: the share of the heaviest chain in all work."""
    return (
        f"select '{weight}' as weight, '{order}' as colors, share from (with recursive {_nodes(tiles, load_sql)}, {_paint(tiles, order)}, {_task(weight)}, {_finish(tiles)} "
        "select list_max(fin)::double / (select sum(weight) from task)::double as share from chain)"
    )


def schedule(tiles: TileSpec, load_sql: str, workers: int, priority: str = "load", barrier: bool = False) -> str:
    """``tile_id, worker, start, finish`` of a greedy run of the tasks under load-aware colors."""
    n = tiles.total
    rank = "weight desc, tile_id" if priority == "load" else "tile_id"
    head = f"with recursive {_nodes(tiles, load_sql)}, {_greedy(tiles, 'load')}, {_task('own')}, "
    idle = f"list_transform(range({workers}), lambda i: 0::bigint)"
    if barrier:
        return (
            head + f"line as materialized (select *, row_number() over (order by color, {rank}) as k, lag(color) over (order by color, {rank}) as last from task), "
            f"go(k, free, tile_id, worker, start, finish) as (select 0::bigint, {idle}, (-1)::bigint, 0::bigint, 0::bigint, 0::bigint union all "
            f"select o.k, {_set('w.free', 'w.who', 'w.begin + o.weight', workers)}, o.tile_id, w.who, w.begin, w.begin + o.weight from go g join line o on o.k = g.k + 1, "
            f"lateral (select free, list_min(free) as begin, (list_position(free, list_min(free)) - 1)::bigint as who from (select case when o.last <> o.color then list_transform(g.free, lambda x: list_max(g.free)) else g.free end as free)) w) "
            "select tile_id, worker::int as worker, start::double as start, finish::double as finish from go where k > 0"
        )
    # a step either starts the first ready task on the worker that has been free for longest, or moves the clock on
    waits = "list_filter(range({n}), lambda i: s.beg[i + 1] < 0 and len(list_filter(a.near[i + 1], lambda m: a.color[m + 1] < a.color[i + 1] and not (s.beg[m + 1] >= 0 and s.done[m + 1] <= s.clock))) = 0)".format(n=n)
    first = "list_min(list_transform({ready}, lambda i: a.rank[i + 1]))".format(ready=waits)
    return (
        head + f"line as (select *, row_number() over (order by {rank}) as rank from task), "
        "a as materialized (select list(near order by tile_id) as near, list(color order by tile_id) as color, list(weight order by tile_id) as weight, list(rank order by tile_id) as rank, list(tile_id order by rank) as at from line), "
        f"s(k, clock, beg, done, who, free) as (select 0::bigint, 0::bigint, list_transform(range({n}), lambda i: (-1)::bigint), list_transform(range({n}), lambda i: (-1)::bigint), list_transform(range({n}), lambda i: (-1)::bigint), {idle} union all "
        f"select s.k + 1, case when c.go then s.clock else (select min(x) from (select unnest(s.done) as x) where x > s.clock) end, "
        f"case when c.go then {_set('s.beg', 'c.tile', 's.clock', n)} else s.beg end, case when c.go then {_set('s.done', 'c.tile', 's.clock + a.weight[c.tile + 1]', n)} else s.done end, "
        f"case when c.go then {_set('s.who', 'c.tile', 'c.worker', n)} else s.who end, case when c.go then {_set('s.free', 'c.worker', 's.clock + a.weight[c.tile + 1]', workers)} else s.free end "
        f"from s, a, lateral (select r.rank is not null and list_min(s.free) <= s.clock as go, a.at[r.rank] as tile, (list_position(s.free, list_min(s.free)) - 1)::bigint as worker from (select {first} as rank) r) c "
        f"where list_min(s.beg) < 0) "
        f"select (unnest(range({n})))::bigint as tile_id, unnest(who)::int as worker, unnest(beg)::double as start, unnest(done)::double as finish from s where list_min(beg) >= 0"
    )
