"""Hand-made fixtures: kernels on one event, tiles, graph, paths, bounds."""

import math
import random
from itertools import product

import numpy as np
import pytest

from cubedensity.operators import dag, replicas
from cubedensity.operators.blocks import Kernel
from cubedensity.operators.tiles import safe_tiles
from cubedensity.plans import chooser, measures
from cubedensity.spec import MASS_OF_ONE, Bandwidth, GridSpec, PlanOptions, TileSpec, constant, largest_term, mass_type


def one_event(**options):
    grid, bw = GridSpec(5, 5, 3, sub=2), Bandwidth(2, 1)
    k = Kernel(grid, bw, PlanOptions(**options))
    box = [(0, g) for g in grid.shape]
    mass, hits = k.empty(box)
    at = np.array([5]), np.array([5]), np.array([3])
    k.fill(mass, hits, box, *at, np.array([1]))
    return mass, hits


def test_one_event_printed():
    mass, hits = one_event()
    assert (hits > 0).sum() == 27 and mass.sum() == 62_720
    assert [mass[v] for v in ((2, 2, 1), (3, 2, 1), (1, 2, 1), (2, 2, 0), (2, 2, 2))] == [1024, 256, 2304, 4096, 0]
    assert hits[2, 2, 2] == 1 and hits[4, 2, 1] == 0


def test_one_event_other_kernels_and_edges():
    mass, hits = one_event(edge="open")
    assert (hits > 0).sum() == 9 and mass.sum() == 12_544
    assert one_event(kernel="mirrored")[0].sum() == 2_304
    assert one_event(kernel="epanechnikov")[0].sum() == 384
    assert one_event(kernel="uniform")[0].sum() == 27


def test_printed_is_not_mirrored():
    grid, bw = GridSpec(5, 5, 3, sub=16), Bandwidth(2, 1)
    cubes = []
    for k in ("printed", "mirrored"):
        kernel = Kernel(grid, bw, PlanOptions(kernel=k))
        box = [(0, g) for g in grid.shape]
        mass, hits = kernel.empty(box)
        kernel.fill(mass, hits, box, np.array([37]), np.array([44]), np.array([20]), np.array([1]))
        cubes.append(mass)
    assert not np.array_equal(*cubes)


def test_mass_of_an_interior_event_nears_the_kernel_constant():
    grid, bw = GridSpec(64, 64, 64, sub=4), Bandwidth(24, 24)
    for name, want in MASS_OF_ONE.items():
        if want is None:
            continue
        o = PlanOptions(kernel=name, mass="double", edge="open")
        k = Kernel(grid, bw, o)
        box = [(0, g) for g in grid.shape]
        mass, hits = k.empty(box)
        k.fill(mass, hits, box, np.array([130]), np.array([130]), np.array([130]), np.array([1]))
        assert mass.sum() * constant(grid, bw, o) == pytest.approx(want, rel=0.06)


def test_translation_moves_the_cube():
    grid, bw = GridSpec(12, 12, 12, sub=4), Bandwidth(2, 2)
    k = Kernel(grid, bw)
    box = [(0, g) for g in grid.shape]
    cubes = []
    for shift in (0, 3):
        mass, hits = k.empty(box)
        k.fill(mass, hits, box, np.array([17 + 4 * shift]), np.array([18]), np.array([19]), np.array([2]))
        cubes.append(mass)
    assert np.array_equal(np.roll(cubes[0], 3, axis=0), cubes[1])


def test_large_batches_stay_exact():
    grid, bw = GridSpec(6, 6, 4, sub=64), Bandwidth(3, 2)
    rng = np.random.default_rng(1)
    ev = [rng.integers(0, g * 64, 9000) for g in grid.shape]
    k = Kernel(grid, bw)
    box = [(0, g) for g in grid.shape]
    assert largest_term(grid, bw, PlanOptions()) * 4096 > 1 << 53  # the path of whole numbers
    mass, hits = k.empty(box)
    k.fill(mass, hits, box, *ev, np.ones(9000, np.int64))
    want = np.zeros(grid.shape, object)
    hx, ht = bw.lattice(grid)
    for vx, vy, vt in product(*(range(g) for g in grid.shape)):
        d = [v * 64 + 32 - e for v, e in zip((vx, vy, vt), ev)]
        ok = (d[0] ** 2 + d[1] ** 2 < hx * hx) & (abs(d[2]) <= ht)
        want[vx, vy, vt] = sum(int(x) for x in ((hx - d[0]) ** 2 * (hx - d[1]) ** 2 * (ht - d[2]) ** 2)[ok])
    assert (mass == want).all()


def test_tiles():
    assert [TileSpec(2, 1, 1).bounds((k, 0, 0), GridSpec(7, 1, 1))[0] for k in (0, 1)] == [(0, 4), (4, 7)]
    safe = lambda g, h, n: safe_tiles(TileSpec(n, 1, 1), GridSpec(g, 1, 1), Bandwidth(h, 1)).a
    assert (safe(8, 1, 8), safe(7, 1, 8), safe(5, 3, 4)) == (4, 3, 1)
    for n, g in ((3, 7), (5, 5), (4, 30), (7, 23)):
        bounds = [TileSpec(n, 1, 1).bounds((k, 0, 0), GridSpec(g, 1, 1))[0] for k in range(n)]
        assert [v for a, b in bounds for v in range(a, b)] == list(range(g))
        for k, (a, b) in enumerate(bounds):
            assert all(n * v // g == k for v in range(a, b))


def test_default_tiles():
    from cubedensity.operators.density import default_tiles

    assert default_tiles(GridSpec(326, 151, 84), Bandwidth(12, 7)).counts == (3, 1, 1)
    for grid, bw in ((GridSpec(326, 151, 84), Bandwidth(12, 7)), (GridSpec(5, 5, 3), Bandwidth(2, 1)), (GridSpec(131, 61, 84), Bandwidth(2, 3)), (GridSpec(1, 1, 900), Bandwidth(4, 4))):
        few, many = default_tiles(grid, bw), default_tiles(grid, bw, 8)
        assert many.total >= few.total
        assert all(n == 1 or w >= 2 * h for n, w, h in zip(many.counts, many.widths(grid), (*bw.whole[:1] * 2, bw.whole[1])))


def test_sizes_and_types():
    assert GridSpec(148, 194, 728).bytes(4) == 83_609_344
    assert GridSpec.of_extent((10.0, 9.9, 5.0), 2.0, 2.5).shape == (5, 5, 2)
    assert Bandwidth.of_domain(2500, 14, 500, 7).whole == (5, 2)
    assert mass_type(GridSpec(9, 9, 9), Bandwidth(50, 14), PlanOptions(), 10**6).mass == "decimal"
    assert mass_type(GridSpec(9, 9, 9), Bandwidth(2, 1), PlanOptions(), 10**6).mass == "long"
    for bad in (lambda: GridSpec(0, 1, 1), lambda: Bandwidth(0, 1), lambda: TileSpec(0, 1, 1), lambda: PlanOptions(kernel="no")):
        with pytest.raises(ValueError):
            bad()


ROW = TileSpec(4, 1, 1)
LOADS = {0: 1, 1: 5, 2: 4, 3: 2}


def test_row_of_four_tiles():
    colors = dag.greedy_colors(LOADS, ROW)
    assert [colors[t] for t in range(4)] == [1, 0, 1, 0]
    parity = dag.parity_colors(ROW)
    assert [parity[t] // 4 for t in range(4)] == [0, 1, 0, 1]
    assert sorted(dag.oriented_edges(colors, ROW)) == [(1, 0), (1, 2), (3, 2)]
    own = dag.weights_of(LOADS, ROW)
    both = dag.weights_of(LOADS, ROW, "own_plus_neighbours")
    assert both == {0: 6, 1: 10, 2: 11, 3: 6}
    for c in (colors, parity):
        assert dag.critical_path(c, own, ROW).length == 9
        assert dag.critical_path(c, both, ROW).length == 21
    assert dag.critical_path(colors, own, ROW).chain == [1, 2]
    assert dag.graham_bound(12, 9, 2) == 10.5
    assert max(end for *_, end in dag.list_schedule(colors, own, ROW, 2)) == 9
    plan = dag.replication_plan(LOADS, colors, ROW, 2)
    assert (plan.limit, plan.rounds, plan.copies, plan.path.length) == (3, 1, {0: 1, 1: 2, 2: 2, 3: 1}, 5)


def test_bounds():
    assert dag.graham_speedup(0.10, 16) == pytest.approx(6.40)
    assert dag.graham_speedup(0.55, 16) == pytest.approx(1.7297, abs=1e-4)
    assert measures.zero_fill_cap(6, 4, 3) == 5
    assert measures.flops(10, Bandwidth(2, 1)) == 10 * 40 * 16 * 2


def longest_by_search(colors, weights, tiles):
    best = 0

    def go(t, total):
        nonlocal best
        best = max(best, total)
        for n in dag.neighbours(t, tiles):
            if colors[n] > colors[t]:
                go(n, total + weights[n])

    for t in colors:
        go(t, weights[t])
    return best


@pytest.mark.parametrize("seed", range(6))
def test_random_graphs(seed):
    rng = random.Random(seed)
    tiles = TileSpec(rng.randint(1, 3), rng.randint(1, 3), rng.randint(1, 3))
    loads = {t: rng.randint(0, 20) for t in range(tiles.total) if rng.random() < 0.8}
    w = dag.weights_of(loads, tiles)
    for order in ("load", "natural", "parity"):
        colors = dag.greedy_colors(loads, tiles, order)
        assert max(colors.values()) < 27
        assert all(colors[t] != colors[n] for t in colors for n in dag.neighbours(t, tiles))
        path = dag.critical_path(colors, w, tiles)
        if tiles.total <= 12:
            assert path.length == longest_by_search(colors, w, tiles)
        assert max(w.values(), default=0) <= path.length <= sum(w.values())
        assert sum(w[t] for t in path.chain) == path.length
        for workers in (1, 3):
            for barrier in (False, True):
                plan = dag.list_schedule(colors, w, tiles, workers, barrier=barrier)
                assert sorted(t for t, *_ in plan) == sorted(colors)
                end = {t: b for t, _, _, b in plan}
                start = {t: a for t, _, a, _ in plan}
                assert all(start[b] >= end[a] for a, b in dag.oriented_edges(colors, tiles))
                span = max(end.values())
                assert max(path.length, sum(w.values()) / workers) <= span + 1e-9
                if not barrier:
                    assert span <= dag.graham_bound(sum(w.values()), path.length, workers) + 1e-9
        for scope in ("path", "path_and_neighbours"):
            rep = dag.replication_plan(loads, colors, tiles, 4, scope=scope)
            assert rep.path.length <= path.length
            assert all(1 <= r <= max(1, min(4, loads.get(t, 0))) for t, r in rep.copies.items())
    assert len(set(dag.parity_colors(tiles).values())) <= 8


def test_memory_guard():
    replicas.check_memory(GridSpec(10, 10, 10), 4, 64_000)
    with pytest.raises(replicas.ReplicaTooLarge):
        replicas.check_memory(GridSpec(10, 10, 10), 4, 63_999)
    with pytest.raises(ValueError):
        dag.check_tiles(TileSpec(100, 100, 100))


def test_model_refuses_what_does_not_fit():
    loads = {(0, 0, 0): 1000, (3, 3, 3): 10}
    fine = TileSpec(4, 4, 4)
    found = chooser.estimates(loads, fine, GridSpec(400, 400, 400), Bandwidth(2, 2), 16, 1 << 20)
    assert not next(e for e in found if e.method == "replica_sum").fits
    assert all(math.isfinite(e.seconds(16)) and e.seconds(16) >= e.span for e in found)
    assert chooser.coarser({(0, 0, 0): 1, (1, 0, 0): 2, (2, 0, 0): 4}, (2, 2, 2)) == {(0, 0, 0): 3, (1, 0, 0): 4}
