"""All methods against brute force, on random and degenerate event sets."""

import random

import pytest
from pyspark.sql import functions as F

from cubedensity.operators import dag, output, relational, tiles
from cubedensity.operators.density import METHODS, cube, density
from cubedensity.plans import measures
from cubedensity.sources.ingest import EVENTS, collapse, event_view, extents, inside, reader, scale_up
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec, constant

GRID, BW = GridSpec(9, 7, 6, sub=8), Bandwidth(2, 1)


def random_events(n=60, seed=1, grid=GRID):
    rng = random.Random(seed)
    return [(i, *(rng.randrange(g * grid.sub) for g in grid.shape), rng.randint(1, 3)) for i in range(n)]


def factors(kernel, dx, dy, dt, hx, ht):
    if kernel == "printed":
        return (hx - dx) ** 2 * (hx - dy) ** 2 * (ht - dt) ** 2
    if kernel == "mirrored":
        return (hx - abs(dx)) ** 2 * (hx - abs(dy)) ** 2 * (ht - abs(dt)) ** 2
    if kernel == "epanechnikov":
        return (hx * hx - dx * dx - dy * dy) * (ht * ht - dt * dt)
    return 1


def brute(rows, grid=GRID, bw=BW, o=PlanOptions()):
    hx, ht = bw.lattice(grid)
    off = o.offset(grid)
    out = {}
    for _, x, y, t, w in rows:
        for vx in range(grid.gx):
            for vy in range(grid.gy):
                dx, dy = vx * grid.sub + off - x, vy * grid.sub + off - y
                if dx * dx + dy * dy >= hx * hx:
                    continue
                for vt in range(grid.gt):
                    dt = vt * grid.sub + off - t
                    if abs(dt) < ht or o.edge == "closed_time" and abs(dt) == ht:
                        h, m = out.get((vx, vy, vt), (0, 0))
                        out[vx, vy, vt] = h + 1, m + w * factors(o.kernel, dx, dy, dt, hx, ht)
    return {(*v, *hm) for v, hm in out.items()}


def rows_of(df):
    return {(r.vx, r.vy, r.vt, r.hits, int(r.mass)) for r in df.collect()}


def frame(spark, rows):
    return spark.createDataFrame(rows, EVENTS)


@pytest.mark.parametrize("method", METHODS)
def test_methods(spark, method):
    rows = random_events()
    more = {} if method in relational.METHODS else {"tiles": TileSpec(3, 2, 2), "workers": 3}
    assert rows_of(cube(frame(spark, rows), GRID, BW, method, **more)) == brute(rows)


@pytest.mark.parametrize("kernel", ["printed", "mirrored", "epanechnikov", "uniform"])
@pytest.mark.parametrize("edge", ["closed_time", "open"])
def test_kernels_and_edges(spark, kernel, edge):
    rows = random_events(20, 5)
    o = PlanOptions(kernel=kernel, edge=edge, anchor="corner")
    for method in ("product_scatter", "tile_clip", "block_scan"):
        assert rows_of(cube(frame(spark, rows), GRID, BW, method, o)) == brute(rows, o=o)


@pytest.mark.parametrize("method", ["scatter", "product_scatter", "replica_sum", "tile_clip", "parity_sets", "replicated_sets"])
def test_degenerate_sets(spark, method):
    s = GRID.sub
    cases = [
        [],
        [(1, 0, 0, 0, 1)],
        [(1, GRID.gx * s - 1, GRID.gy * s - 1, GRID.gt * s - 1, 1)] * 3,
        [(i, 4 * s, 3 * s, 2 * s, 1) for i in range(12)],
        [(1, 8, 8, 8, 1), (2, 8 + 4 * s, 8, 8, 1), (3, 8 + 5 * s, 8, 8, 2)],
    ]
    for rows in cases:
        assert rows_of(cube(frame(spark, rows), GRID, BW, method, tiles=TileSpec(9, 7, 6), workers=20) if method not in relational.METHODS else cube(frame(spark, rows), GRID, BW, method)) == brute(rows)


def test_bandwidth_beyond_the_grid(spark):
    grid, bw = GridSpec(3, 2, 2, sub=4), Bandwidth(5, 4)
    rows = random_events(10, 2, grid)
    for method in ("scatter", "block_scan", "tile_clip", "parity_sets", "replica_sum"):
        assert rows_of(cube(frame(spark, rows), grid, bw, method)) == brute(rows, grid, bw)
    assert tiles.safe_tiles(TileSpec(3, 2, 2), grid, bw).total == 1


def test_fractional_bandwidth(spark):
    bw = Bandwidth(1.5, 0.75)
    rows = random_events(25, 8)
    for method in ("scatter", "block_scan", "tile_clip", "two_pass"):
        assert rows_of(cube(frame(spark, rows), GRID, bw, method)) == brute(rows, bw=bw)


def test_outside_rules(spark):
    far = [(1, -4, 20, 20, 1), (2, 20, 20, 10_000, 1), (3, None, 1, 1, 1), (4, 20, 20, 20, 1)]
    df = frame(spark, far)
    assert rows_of(cube(df, GRID, BW, "scatter")) == brute(far[3:])
    halo = PlanOptions(outside="halo")
    assert rows_of(cube(df, GRID, BW, "scatter", halo)) == brute([far[0], far[3]])
    assert rows_of(cube(df, GRID, BW, "tile_clip", halo, tiles=TileSpec(2, 2, 2))) == brute([far[0], far[3]])
    with pytest.raises(Exception, match="outside the grid"):
        inside(df, GRID, PlanOptions(outside="error")).count()
    with pytest.raises(ValueError):
        cube(df, GRID, BW, "parity_sets", halo)


def test_wide_masses(spark):
    grid, bw = GridSpec(6, 6, 4, sub=512), Bandwidth(5, 3)
    rows = random_events(12, 3, grid)
    for method in ("scatter", "product_scatter", "disk_scatter", "bar_scatter", "two_pass"):
        assert rows_of(cube(frame(spark, rows), grid, bw, method, PlanOptions(mass="decimal"))) == brute(rows, grid, bw)
    with pytest.raises(Exception, match="64 bits"):
        cube(frame(spark, rows * 100), GridSpec(6, 6, 4, sub=2048), Bandwidth(5, 3), "replica_sum").collect()


def test_float_mode_is_near(spark):
    rows = random_events()
    exact = {r[:3]: r[4] for r in brute(rows)}
    for method in ("scatter", "tile_clip"):
        for r in cube(frame(spark, rows), GRID, BW, method, PlanOptions(mass="double")).collect():
            assert r.mass == pytest.approx(exact[r.vx, r.vy, r.vt], rel=1e-9)


def test_density_and_zeros(spark):
    rows = random_events(15)
    full = density(frame(spark, rows), GRID, BW, "product_scatter", dense=True)
    assert full.count() == GRID.cells
    c = constant(GRID, BW, PlanOptions()) / 15
    want = {r[:3]: r[4] * c for r in brute(rows)}
    for r in full.collect():
        assert r.density == pytest.approx(want.get((r.vx, r.vy, r.vt), 0.0), rel=1e-12)


def test_additivity_collapse_and_scale(spark):
    rows = random_events(40)
    df = frame(spark, rows)
    parts = [cube(df.filter(F.col("event_id") % 2 == k), GRID, BW, "scatter") for k in (0, 1)]
    assert rows_of(relational.merge_cubes(*parts)) == brute(rows)
    twice = rows + [(100 + r[0], *r[1:]) for r in rows]
    merged = relational.scatter(collapse(frame(spark, twice)), GRID, BW)
    assert {(r.vx, r.vy, r.vt, r.mass) for r in merged.collect()} == {(*r[:3], r[4]) for r in brute(twice)}
    assert scale_up(df, 3, GRID).count() == 120
    assert extents(df).first()["n"] == 40


def test_adaptive_bandwidth_one_class(spark):
    rows = random_events(30)
    wide = relational.adaptive(frame(spark, rows), GRID, Bandwidth(0.5, 1), 3, (10**6, 10**7))
    assert rows_of(wide) == brute(rows, bw=Bandwidth(2, 1))


def test_sweep(spark):
    rows = random_events(30)
    bws = [Bandwidth(1, 1), Bandwidth(2, 2)]
    got = relational.bandwidth_sweep(frame(spark, rows), GRID, bws)
    for i, b in enumerate(bws):
        assert rows_of(got.filter(F.col("bw") == i)) == brute(rows, bw=b)


def test_sets_never_conflict_and_copies_are_bounded(spark):
    df = frame(spark, random_events(200, 4))
    safe = tiles.safe_tiles(TileSpec(9, 7, 6), GRID, BW)
    assert measures.conflicts(df, GRID, BW, safe).isEmpty()
    assert not measures.conflicts(df, GRID, BW, TileSpec(9, 7, 6)).isEmpty()
    per = tiles.copies(df, GRID, BW, safe).groupBy("event_id").count().agg(F.max("count")).first()[0]
    assert per <= 8
    r = measures.replication(df, GRID, BW, safe).first()
    assert r.copies == tiles.copies(df, GRID, BW, safe).count() and r.events == 200


def test_scan_is_refused_when_too_large(spark):
    with pytest.raises(ValueError):
        relational.voxel_scan(frame(spark, random_events(10)), GRID, BW, limit=9)


def test_rounds_of_colors_and_paths_equal_the_driver(spark):
    t = TileSpec(3, 2, 3)
    rng = random.Random(5)
    loads = {k: rng.randint(0, 5) for k in range(t.total) if rng.random() < 0.7}
    df = spark.createDataFrame([*loads.items()], "tile_id bigint, load bigint")
    colors = dag.greedy_colors(loads, t)
    assert {r.tile_id: r.color for r in dag.greedy_colors_df(spark, df, t).collect()} == colors
    table = spark.createDataFrame([*colors.items()], "tile_id bigint, color int")
    path = dag.critical_path(colors, dag.weights_of(loads, t), t)
    got = dag.critical_path_df(spark, table, df.withColumnRenamed("load", "weight"), t)
    assert {r.tile_id: r.finish for r in got.collect()} == path.finish


def test_hot_spots_against_union_find(spark):
    rows = random_events(25, 11)
    c = cube(frame(spark, rows), GRID, Bandwidth(1, 1), "scatter")
    level = sorted(r.mass for r in c.collect())[-25]
    hot = {(r.vx, r.vy, r.vt) for r in c.collect() if r.mass >= level}
    parent = {v: v for v in hot}

    def find(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for a in hot:
        for b in hot:
            if a < b and all(abs(p - q) <= 1 for p, q in zip(a, b)):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    got = {(r.vx, r.vy, r.vt): r.label for r in output.hot_spots(c, level).collect()}
    assert set(got) == hot
    for v in hot:
        x, y, t = find(v)
        assert got[v] == (x << 42) + (y << 21) + t


def test_sinks_and_readers(spark, tmp_path):
    rows = random_events(20)
    c = cube(frame(spark, rows), GRID, BW, "scatter")
    output.write_cube(c, str(tmp_path / "cube"), slab=2)
    back = spark.read.parquet(str(tmp_path / "cube"))
    assert rows_of(back) == brute(rows)
    plan = back.filter("slab = 1")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(slab" in plan
    output.write_slices(c, str(tmp_path / "slices"))
    for kind in ("csv", "json", "orc"):
        frame(spark, rows).write.format(kind).save(str(tmp_path / kind))
        assert rows_of(cube(reader(spark, kind, str(tmp_path / kind), EVENTS), GRID, BW, "scatter")) == brute(rows)
    (tmp_path / "bad.json").write_text('{"event_id":1,"x":2,"y":2,"t":2,"w":1}\nnot json\n')
    bad = reader(spark, "json", str(tmp_path / "bad.json"), EVENTS + ", _bad string")
    assert cube(event_view(bad, "event_id", "x", "y", "t", "w"), GRID, BW, "scatter").agg(F.max("hits")).first()[0] == 1
