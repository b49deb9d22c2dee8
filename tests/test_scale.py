"""Crowded tiles and blocks, memory limits, planning by arrays, and state that expires: equal to the plain forms."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from cubedensity.operators import dag, output, relational, replicas
from cubedensity.operators.blocks import FORMS, Kernel, rows_of_blocks, task_memory
from cubedensity.operators.density import cube
from cubedensity.operators.tiles import finer, fitting, tile_clip, zero_blocks
from cubedensity.plans import chooser, measures
from cubedensity.plans.durable import shared_folder
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec
from cubedensity.streaming import stream

GRID, BW = GridSpec(12, 10, 14), Bandwidth(2, 1.5)


def crowd(spark, seed=1, n=400):
    rng = random.Random(seed)
    s = GRID.sub
    rows = [(i, rng.randrange(GRID.gx * s), rng.randrange(GRID.gy * s), rng.randrange(GRID.gt * s), rng.choice([1, 1, 2])) for i in range(n)]
    rows += [(1000 + i, 5 * s + rng.randrange(s), 5 * s + rng.randrange(s), 6 * s + rng.randrange(s), 1) for i in range(n)]  # half of them in one voxel
    return spark.createDataFrame(rows, "event_id bigint, x bigint, y bigint, t bigint, w bigint")


def rows_of(df):
    return sorted(map(tuple, df.select("vx", "vy", "vt", "hits", "mass").collect()))


def test_crowded_blocks_and_tiles(spark):
    ev = crowd(spark).cache()
    want = rows_of(relational.scatter(ev, GRID, BW))
    assert rows_of(relational.block_scan(ev, GRID, BW, crowded=7)) == want
    for tiles in (TileSpec(1, 1, 1), TileSpec(2, 3, 2), TileSpec(5, 5, 5)):
        for over in (1, 50, 300, 10_000):
            assert rows_of(tile_clip(ev, GRID, BW, tiles, split_over=over)) == want
        assert rows_of(rows_of_blocks(tile_clip(ev, GRID, BW, tiles, split_over=50, emit="blocks"))) == want
    for method in ("parity_sets", "loadaware_sets", "replicated_sets"):
        assert rows_of(cube(ev, GRID, BW, method, tiles=TileSpec(3, 2, 4))) == want
        assert rows_of(rows_of_blocks(cube(ev, GRID, BW, method, tiles=TileSpec(3, 2, 4), emit="blocks"))) == want
    assert rows_of(cube(ev, GRID, BW, "replica_sum", workers=3)) == want
    assert rows_of(cube(ev, GRID, BW, "replica_sum", PlanOptions(mass="double"), workers=3)) == want


@pytest.mark.parametrize("kernel", ["printed", "mirrored", "epanechnikov", "uniform"])
@pytest.mark.parametrize("edge", ["closed_time", "open"])
def test_forms_of_the_dense_kernel(kernel, edge):
    rng = np.random.default_rng(3)
    x, y, t = (rng.integers(0, g * GRID.sub, 300) for g in GRID.shape)
    w = rng.integers(1, 4, 300)
    box, found = [(2, 9), (0, 10), (3, 14)], {}
    for form in FORMS:
        for mass in ("long", "double"):
            k = Kernel(GRID, BW, PlanOptions(kernel=kernel, edge=edge, mass=mass), form)
            arrays = k.empty(box)
            k.fill(*arrays, box, x, y, t, w)
            found[form, mass] = arrays
    first = found["product", "long"]
    for mass, hits in found.values():
        assert (mass == first[0]).all() and (hits == first[1]).all()
    with pytest.raises(ValueError):
        Kernel(GRID, BW, form="other")


def test_tiles_nest_and_fit():
    tiles = TileSpec(2, 3, 5)
    fine = finer(tiles, 4, GRID)
    assert fine == TileSpec(8, 9, 10)
    for a in range(2):
        inner = [fine.bounds((k, 0, 0), GRID)[0] for k in range(4 * a, 4 * a + 4)]
        assert (inner[0][0], inner[-1][1]) == tiles.bounds((a, 0, 0), GRID)[0]
    small = fitting(TileSpec(1, 1, 1), GridSpec(100, 100, 100), 1 << 16)
    assert math.prod(-(-100 // n) for n in small.counts) * 16 <= 1 << 16
    with pytest.raises(MemoryError):
        fitting(TileSpec(1, 1, 1), GridSpec(4, 4, 4), 8)


def test_private_cubes_that_do_not_fit(spark):
    ev = crowd(spark, n=20)
    wide = GridSpec(4000, 4000, 400)
    with pytest.raises(replicas.ReplicaTooLarge):
        cube(ev, wide, BW, "replica_sum")
    assert rows_of(cube(ev, wide, BW, "replica_sum", fall_back=True, tiles=TileSpec(40, 40, 40))) == rows_of(relational.scatter(ev, wide, BW))
    with pytest.raises(replicas.ReplicaTooLarge):
        cube(ev, GRID, BW, "replica_sum", workers=8, memory_limit=1000)
    assert task_memory(spark) >= 64 << 20


def test_zero_blocks(spark):
    made = zero_blocks(spark, GRID, TileSpec(2, 2, 3)).collect()
    assert len(made) == 12 and sum(len(r.hits) for r in made) == GRID.cells and not any(any(r.hits) for r in made)


def test_choice_keeps_to_the_options(spark):
    ev = crowd(spark, n=50)
    for options in (PlanOptions(outside="halo"), PlanOptions(mass="decimal"), PlanOptions(mass="double")):
        made = cube(ev, GRID, BW, "auto", options)
        assert [tuple(map(int, r)) for r in rows_of(made)] == [tuple(map(int, r)) for r in rows_of(relational.scatter(ev, GRID, BW, options))]
    assert not chooser.possible(chooser.Estimate("parity_sets", None, 1, 1, 1, True), 5, GRID, BW, PlanOptions(outside="halo"))


# plans on tiles ----------------------------------------------------------------------------------------------------
def plain_colors(loads, tiles, order):
    colors = {}
    for t in dag.visiting_order(loads, tiles, order):
        used = {colors[n] for n in dag.neighbours(t, tiles) if n in colors}
        colors[t] = next(c for c in range(27) if c not in used)
    return colors


def plain_path(colors, weights, tiles):
    finish, came = {}, {}
    for t in sorted(colors, key=lambda t: (colors[t], t)):
        before = [n for n in dag.neighbours(t, tiles) if n in colors and colors[n] < colors[t] and finish[n] > 0]
        by = min(before, key=lambda n: (-finish[n], n), default=None)
        finish[t], came[t] = (finish[by] if before else 0) + weights[t], by
    at = min(finish, key=lambda t: (-finish[t], t))
    length, chain = finish[at], []
    while at is not None:
        chain.append(at)
        at = came[at]
    return length, chain[::-1]


def test_plans_by_arrays_equal_plain_ones():
    rng = random.Random(6)
    for tiles in (TileSpec(1, 1, 1), TileSpec(4, 3, 5), TileSpec(2, 7, 2)):
        for _ in range(6):
            loads = {t: rng.choice([0, 1, 5, int(rng.paretovariate(1) * 9)]) for t in range(tiles.total) if rng.random() < 0.8}
            for order in ("load", "natural", "parity"):
                colors = dag.greedy_colors(loads, tiles, order)
                assert colors == plain_colors(loads, tiles, order)
                for weight in ("own", "own_plus_neighbours"):
                    w = dag.weights_of(loads, tiles, weight)
                    path = dag.critical_path(colors, w, tiles)
                    assert (path.length, path.chain) == plain_path(colors, w, tiles)
                for scope in ("path", "path_and_neighbours"):
                    plan = dag.replication_plan(loads, colors, tiles, 4, scope=scope)
                    now = {t: math.ceil(loads.get(t, 0) / plan.copies[t]) for t in colors}
                    assert (plan.path.length, plan.path.chain) == plain_path(colors, now, tiles)
            wide = dag.weights_of(loads, tiles, "own_plus_neighbours")
            assert all(wide[t] == loads.get(t, 0) + sum(loads.get(n, 0) for n in dag.neighbours(t, tiles)) for t in range(tiles.total))


def test_many_tiles_are_planned_in_seconds():
    import time

    tiles, rng = TileSpec(48, 48, 48), random.Random(2)
    loads = {t: int(rng.paretovariate(1.1)) for t in range(tiles.total)}
    began = time.process_time()
    plan = dag.replication_plan(loads, dag.greedy_colors(loads, tiles), tiles, 16)
    assert plan.rounds > 0 and time.process_time() - began < 30


def test_coarse_tiles_are_told():
    one = chooser.explain_plan({0: 900}, TileSpec(1, 1, 1), 16)
    assert one["copied"] == 1 and one["copies"] == 15 and "coarse" in one["warning"]
    even = chooser.explain_plan({t: 10 for t in range(1000)}, TileSpec(10, 10, 10), 4)
    assert even["warning"] is None


def test_running_share_of_equal_masses(spark):
    rows = [(i % 7, i % 5, i, 1, 10 if i % 3 else 10_000 + i) for i in range(300)]
    got = output.running_share(spark.createDataFrame(rows, "vx int, vy int, vt int, hits bigint, mass bigint").repartition(5)).collect()
    total, want = 0, {}
    for vx, vy, vt, _, mass in sorted(rows, key=lambda r: (-r[4], r[:3])):
        total += mass
        want[vx, vy, vt] = total
    assert {(r.vx, r.vy, r.vt): r.running for r in got} == want


# streams -----------------------------------------------------------------------------------------------------------
def test_state_expires(spark, tmp_path):
    for k, day in enumerate((1, 28, 1)):
        spark.createDataFrame([(k, f"2024-01-{day:02d} 05:00:00", 1, "view", 1.0)], "event_id bigint, at string, user_id bigint, event_type string, value double").select(
            "event_id", F.col("at").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value"
        ).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    grid, bw = GridSpec(6, 6, 30), Bandwidth(1, 1)
    read = lambda: stream.read_events(spark, str(tmp_path), files_per_trigger=1)
    whole = stream.run_merged(read(), grid, bw, 5, slab=4)
    kept = stream.run_merged(read(), grid, bw, 5, slab=4, keep_back=2)
    first = lambda df: df.filter("vt < 4").agg(F.max("hits")).first()[0]
    assert first(whole) == 2 and first(kept) == 1  # the second event of day 1 came after its slab had closed
    assert rows_of(whole.filter("vt > 20")) == rows_of(kept.filter("vt > 20"))


def test_a_cluster_needs_a_shared_folder():
    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:
            get = staticmethod(lambda key, default=None: default)

    with pytest.raises(RuntimeError):
        shared_folder(Session())
    Session.conf.get = staticmethod(lambda key, default=None: "hdfs://x/y/")
    assert shared_folder(Session()) == "hdfs://x/y"


def test_runtime_filter_prunes_slabs(spark):
    import __spark_entry__ as entry

    plan = entry.queries()["op_skip_empty_tiles"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "dynamicpruning" in plan


def test_voxel_scan_takes_any_number_of_events(spark):
    ev = spark.range(1_000_001).select(F.col("id").alias("event_id"), *(F.lit(8).cast("long").alias(c) for c in "xyt"), F.lit(1).cast("long").alias("w"))
    got = relational.voxel_scan(ev, GridSpec(2, 1, 1), Bandwidth(1, 1)).collect()
    assert [(r.vx, r.hits) for r in got] == [(0, 1_000_001)]


def test_block_scan_moves_every_event_once(spark):
    ev = crowd(spark, 3)
    made = relational.block_scan(ev, GRID, BW)
    # shares and three axes of voxels are the only rows that are made
    assert made._jdf.queryExecution().optimizedPlan().toString().count("Generate explode") == 4
    assert rows_of(made) == rows_of(relational.scatter(ev, GRID, BW))


def test_running_share_beyond_a_long(spark):
    rows = [(i, 0, 0, 1, 4 * 10**18) for i in range(5)]
    got = output.running_share(spark.createDataFrame(rows, "vx int, vy int, vt int, hits bigint, mass bigint")).collect()
    assert sorted(int(r.running) for r in got) == [4 * 10**18 * k for k in range(1, 6)]


def test_entries_once_a_place_are_those_of_every_event(spark):
    ev = crowd(spark, 4, 80)
    ev = ev.union(ev)
    each = measures.box_sizes(ev, GRID, BW).agg(F.sum(F.col("n_place") + F.col("n_time")), F.sum(F.col("n_disk") * F.col("n_bar"))).first()
    assert tuple(measures.table_entries(ev, GRID, BW).first()) == tuple(each)


def test_tiled_entries_need_no_copies(spark):
    ev, cut = crowd(spark, 5, 60), TileSpec(5, 3, 4)
    made = measures.tiled_entries(ev, GRID, BW, cut)
    assert "Generate" not in made._jdf.queryExecution().optimizedPlan().toString()
    want = 0
    for r in ev.collect():
        ends = [(max(0, c // GRID.sub - h), min(g - 1, c // GRID.sub + h)) for c, g, h in zip((r.x, r.y, r.t), GRID.shape, (2, 2, BW.whole[1]))]
        parts = [[sum(v * n // g == k for v in range(lo, hi + 1)) for k in range(n)] for (lo, hi), n, g in zip(ends, cut.counts, GRID.shape)]
        want += sum(p * q + t for p in parts[0] for q in parts[1] for t in parts[2] if p and q and t)
    assert made.first()[0] == want


def test_event_driven_methods_use_all_workers(spark):
    from cubedensity.operators import relational
    from cubedensity.spec import Bandwidth, GridSpec

    few = spark.range(50).coalesce(1).selectExpr("id as event_id", "id % 40 as x", "id % 30 as y", "id % 20 as t", "1L as w")
    grid, bw, deals = GridSpec(4, 4, 4), Bandwidth(1, 1), []
    for name in ("scatter", "disk_scatter", "bar_scatter", "product_scatter"):
        plan = getattr(relational, name)(few, grid, bw)._jdf.queryExecution().optimizedPlan().toString()
        deals.append("RepartitionByExpression" in plan)
    assert all(deals)
    rows = [sorted(map(tuple, getattr(relational, name)(few, grid, bw).collect())) for name in ("scatter", "product_scatter")]
    assert rows[0] == rows[1] and rows[0]


@pytest.mark.parametrize("kernel", ["printed", "mirrored", "epanechnikov", "uniform"])
def test_events_by_place_equal_those_by_cell(kernel):
    rng = np.random.default_rng(8)
    n = 3000  # more than voxels, so that places share their disks; some events lie beyond the box and the grid
    x, y, t = (rng.integers(-3 * GRID.sub, (g + 3) * GRID.sub, n) for g in GRID.shape)
    for w in (np.ones(n, np.int64), rng.integers(-3, 4, n)):
        for bw in (BW, Bandwidth(1, 1), Bandwidth(3.3, 5)):
            for edge, anchor, mass in (("open", "corner", "long"), ("closed_time", "centre", "double")):
                k, box = Kernel(GRID, bw, PlanOptions(kernel=kernel, edge=edge, anchor=anchor, mass=mass)), [(2, 9), (0, 10), (3, 14)]
                placed, celled = k.empty(box), k.empty(box)
                k._by_place(*placed, box, x, y, t, w)
                k._by_cell(*celled, box, x, y, t, w, 3)
                assert (placed[0] == celled[0]).all() and (placed[1] == celled[1]).all()


def test_many_events_cost_little_each():
    import time

    grid, bw, rng = GridSpec(33, 15, 42), Bandwidth(5, 7), np.random.default_rng(9)
    x, y, t = (rng.integers(0, g * grid.sub, 400_000) for g in grid.shape)
    k, box = Kernel(grid, bw), [(0, g) for g in grid.shape]
    arrays = k.empty(box)
    began = time.process_time()
    for at in range(0, len(x), 1 << 18):
        part = slice(at, at + (1 << 18))
        k.fill(*arrays, box, x[part], y[part], t[part], np.ones(len(x[part]), np.int64))
    assert time.process_time() - began < 3


def test_masses_beyond_a_long_are_refused():
    k, box = Kernel(GRID, BW), [(0, g) for g in GRID.shape]
    arrays, at = k.empty(box), np.full(2000, 100)
    with pytest.raises(OverflowError):
        for _ in range(100):
            k.fill(*arrays, box, at, at, at, np.full(2000, 10**6))
    double = Kernel(GRID, BW, PlanOptions(mass="double"))
    more = double.empty(box)
    for _ in range(100):
        double.fill(*more, box, at, at, at, np.full(2000, 10**6))
    assert more[0].max() > 2**63


def test_events_travel_as_parcels(spark):
    ev = crowd(spark, 6, 300)
    for method in ("replica_sum", "tile_clip", "parity_sets", "loadaware_sets", "replicated_sets"):
        plan = cube(ev, GRID, BW, method, tiles=TileSpec(2, 2, 2))._jdf.queryExecution().optimizedPlan().toString()
        assert "places" in plan and "Generate" not in plan


def test_groups_of_arrays_equal_those_of_columns(spark):
    from cubedensity.operators.pointsets import _owners
    from cubedensity.operators.tiles import copies, meeting, owner

    for tiles in (TileSpec(1, 1, 1), TileSpec(5, 3, 4), TileSpec(12, 10, 14)):
        rows = crowd(spark, 7, 200).collect()
        event = [np.array([r[c] for r in rows]) for c in "xyt"]
        at, keys = meeting(GRID, BW, tiles)(*event)
        got = sorted(zip((rows[k].event_id for k in at), *(k.tolist() for k in keys)))
        assert got == sorted(map(tuple, copies(crowd(spark, 7, 200), GRID, BW, tiles).select("event_id", "a", "b", "c").collect()))
        assert sorted(zip((r.event_id for r in rows), *(k.tolist() for k in _owners(GRID, tiles, *event)))) == sorted(
            map(tuple, owner(crowd(spark, 7, 200), GRID, tiles).select("event_id", "a", "b", "c").collect())
        )


@pytest.mark.parametrize("kernel", ["printed", "mirrored", "epanechnikov", "uniform"])
def test_sequential_methods_over_arrays_equal_the_dense_kernel(kernel):
    from cubedensity.operators.sequential import Private

    rng = np.random.default_rng(11)
    box = [(0, g) for g in GRID.shape]
    x, y, t = (rng.integers(-2 * GRID.sub, (g + 2) * GRID.sub, 500) for g in GRID.shape)
    x[:300], y[:300], t[:300] = 100, 90, 110 + np.arange(300) % 9  # a crowded voxel
    for w in (np.ones(500, np.int64), rng.integers(-3, 4, 500)):
        for bw in (BW, Bandwidth(1, 1), Bandwidth(2.3, 3)):
            reach = [h * GRID.sub for h in (bw.whole[0], bw.whole[0], bw.whole[1])]
            keep = np.all([(c > -h) & (c < g * GRID.sub + h) for c, h, g in zip((x, y, t), reach, GRID.shape)], axis=0)
            event = [c[keep] for c in (x, y, t, w)]
            for edge, anchor, mass in (("open", "corner", "long"), ("closed_time", "centre", "double")):
                options = PlanOptions(kernel=kernel, edge=edge, anchor=anchor, mass=mass)
                want = Kernel(GRID, bw, options).empty(box)
                Kernel(GRID, bw, options).fill(*want, box, *event)
                for method in ("voxel_scan", "block_scan", "scatter", "disk_scatter", "bar_scatter", "product_scatter"):
                    made = Private(method, GRID, bw, options)
                    made.add(*event)
                    assert (made.cube()[0] == want[0]).all() and (made.cube()[1] == want[1]).all(), (method, bw, edge)


def test_sequential_methods_take_arrays_for_many_events(spark, monkeypatch):
    from cubedensity.operators import sequential

    ev = crowd(spark, 12, 300)
    want = rows_of(relational.scatter(ev, GRID, BW))
    monkeypatch.setattr(sequential, "MANY_PAIRS", 1000)
    monkeypatch.setattr(sequential, "HELD", 1 << 10)
    for method in ("voxel_scan", "block_scan", "scatter", "disk_scatter", "bar_scatter", "product_scatter"):
        made = cube(ev, GRID, BW, method)
        plan = made._jdf.queryExecution().optimizedPlan().toString()
        assert "places" in plan and "Generate" not in plan
        assert rows_of(made) == want
    for options in (PlanOptions(outside="halo"), PlanOptions(mass="decimal"), PlanOptions(kernel="mirrored", mass="double")):
        plain = [tuple(map(int, r)) for r in rows_of(relational.two_pass(ev, GRID, BW, options))]
        assert all([tuple(map(int, r)) for r in rows_of(cube(ev, GRID, BW, m, options))] == plain for m in ("voxel_scan", "block_scan", "scatter"))


def test_masses_beyond_a_long_are_refused_by_sequential_methods():
    from cubedensity.operators.sequential import Private

    at, heavy = np.full(2000, 100), np.full(2000, 10**6)
    for method in ("voxel_scan", "block_scan", "scatter"):
        one = Private(method, GRID, BW, PlanOptions())
        with pytest.raises(OverflowError):
            for _ in range(100):
                one.add(at, at, at, heavy)


def test_shares_of_events_have_a_partition_each(spark):
    from cubedensity.operators.blocks import parcels

    deal = lambda x, y, t, whole: (np.arange(len(x)), [np.mod(whole, 8)])
    made = parcels(crowd(spark, 13), 8, "replica", place=deal, hashed=True, own_partition=True)
    found = made.select("replica", F.spark_partition_id().alias("p")).distinct().collect()
    assert sorted((r.replica, r.p) for r in found) == [(k, k) for k in range(8)]
