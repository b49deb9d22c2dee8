"""A parametric cost model for the parallel methods, and the choice by it.

Costs are in seconds of one worker: zeroing a voxel, making a table entry, adding a product, moving a byte. Work is
spread over the workers but never below the span of the method (one task for the sequential kernel, the heaviest tile
for clipped tiles, the critical path for colored sets); methods whose tasks do not fit the memory of a worker are out.
The loads come from one aggregate at the finest tiles; coarser tiles are sums of those, as counts halve.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from cubedensity.operators import dag, relational
from cubedensity.operators.blocks import task_memory
from cubedensity.operators.tiles import safe_tiles, tile_loads
from cubedensity.sources.ingest import inside
from cubedensity.spec import LONG_LIMIT, Bandwidth, GridSpec, PlanOptions, TileSpec, largest_term

#: seconds for: zeroing a voxel, a table entry, a product added, a byte shuffled, a row out, a task started
CONSTANTS = {"zero": 1e-9, "entry": 4e-9, "product": 1.5e-9, "byte": 4e-9, "row": 2.5e-7, "task": 0.02}
EVENT_BYTES, ROW_BYTES, CUBE_BYTES = 40, 28, 16


@dataclass(frozen=True)
class Estimate:
    method: str
    tiles: TileSpec | None
    work: float
    span: float
    memory: int
    fits: bool

    def seconds(self, workers: int) -> float:
        return max(self.work / workers, self.span)


def finest(grid: GridSpec, most: int = 32) -> TileSpec:
    """Powers of two, so that coarser counts nest."""
    return TileSpec(*(1 << (min(most, g).bit_length() - 1) for g in grid.shape))


def coarser(loads: dict[tuple[int, int, int], int], step: tuple[int, int, int]) -> dict[tuple[int, int, int], int]:
    out: dict[tuple[int, int, int], int] = {}
    for t, n in loads.items():
        k = tuple(v // s for v, s in zip(t, step))
        out[k] = out.get(k, 0) + n
    return out


def shape_of(bw: Bandwidth) -> tuple[int, int]:
    """Places of the box around a disk, and of a bar."""
    hs, ht = bw.whole
    return (2 * hs + 1) ** 2, 2 * ht + 1


def replication(grid: GridSpec, bw: Bandwidth, tiles: TileSpec) -> float:
    """Copies of an event, for events spread evenly."""
    hs, ht = bw.whole
    rho = 1.0
    for g, n, h in zip(grid.shape, tiles.counts, (hs, hs, ht)):
        rho *= min(n, 1 + 2 * h * n / g)
    return rho


def estimates(loads: dict[tuple[int, int, int], int], fine: TileSpec, grid: GridSpec, bw: Bandwidth, workers: int, memory: int) -> list[Estimate]:
    c = CONSTANTS
    n = sum(loads.values())
    disk, bar = shape_of(bw)
    each = c["entry"] * (disk + bar) + c["product"] * disk * bar
    touched = min(grid.cells, n * disk * bar)
    out_rows = touched * c["row"]
    found = [
        Estimate("product_scatter", None, n * disk * bar * (c["row"] + ROW_BYTES * c["byte"]), 0, 0, True),
        Estimate("replica_sum", None, workers * (grid.cells * c["zero"] + min(touched, n * disk * bar / workers) * (c["row"] + ROW_BYTES * c["byte"])) + n * each, n * each / workers + grid.cells * c["zero"], grid.cells * CUBE_BYTES, grid.cells * CUBE_BYTES <= memory),
    ]
    hs, ht = bw.whole
    step = 1
    while step <= max(fine.counts):
        tiles = TileSpec(*(max(1, k // step) for k in fine.counts))
        own = coarser(loads, tuple(min(step, k) for k in fine.counts))
        volume = grid.cells / tiles.total
        halo = 1
        for g, k, h in zip(grid.shape, tiles.counts, (hs, hs, ht)):
            halo *= min(g, g / k + 2 * h)
        rho = replication(grid, bw, tiles)
        heavy = max(own.values(), default=0)
        clip = n * rho * (EVENT_BYTES * c["byte"] + c["entry"] * (disk + bar)) + n * c["product"] * disk * bar + len(own) * (c["task"] + volume * c["zero"]) + out_rows
        found.append(Estimate("tile_clip", tiles, clip, heavy * rho * each, int(volume * CUBE_BYTES), volume * CUBE_BYTES <= memory))
        if safe_tiles(tiles, grid, bw) == tiles:
            # a voxel near a border gets a partial value from each tile around it
            partial = min(len(own) * halo, touched * rho)
            base = n * (EVENT_BYTES * c["byte"] + each) + len(own) * c["task"] + len(own) * halo * c["zero"] + partial * (c["row"] + ROW_BYTES * c["byte"])
            ids = {dag.number(t, tiles): v for t, v in own.items()}
            scale = each
            if tiles.total <= 4096:
                parity = dag.critical_path({t: dag.parity(t, tiles) for t in ids}, ids, tiles).length
                colors = dag.greedy_colors(ids, tiles)
                aware = dag.critical_path({t: colors[t] for t in ids}, ids, tiles).length
                plan = dag.replication_plan(ids, {t: colors[t] for t in ids}, tiles, workers)
                extra = sum(r - 1 for r in plan.copies.values())
                found += [
                    Estimate("parity_sets", tiles, base, parity * scale, int(halo * CUBE_BYTES), halo * CUBE_BYTES <= memory),
                    Estimate("loadaware_sets", tiles, base, aware * scale, int(halo * CUBE_BYTES), halo * CUBE_BYTES <= memory),
                    Estimate("replicated_sets", tiles, base + extra * (c["task"] + halo * (c["zero"] + c["row"])), plan.path.length * scale, int(halo * CUBE_BYTES), halo * CUBE_BYTES <= memory),
                ]
        step *= 2
    return found


def fine_loads(events: DataFrame, grid: GridSpec, options: PlanOptions = PlanOptions()) -> tuple[dict, TileSpec]:
    fine = finest(grid)
    rows = tile_loads(inside(events, grid, options), grid, fine).select("a", "b", "c", "load").collect()  # 32^3 at most
    return {(r["a"], r["b"], r["c"]): r["load"] for r in rows}, fine


def possible(estimate: Estimate, events: int, grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> bool:
    """Whether a method can run under the options: events beyond the grid belong to no tile of a colored set, and block
    kernels keep whole numbers in 64 bits, or doubles."""
    if options.outside == "halo" and estimate.method in ("parity_sets", "loadaware_sets", "replicated_sets"):
        return False
    if estimate.method in relational.METHODS or options.mass == "double":
        return True
    return options.mass == "long" and largest_term(grid, bw, options) * max(1, events) <= LONG_LIMIT


def choose(events: DataFrame, grid: GridSpec, bw: Bandwidth, workers: int, memory: int | None = None, options: PlanOptions = PlanOptions()) -> Estimate:
    """The method of the least estimated time among those that fit the memory of a task and can run under the options."""
    memory = task_memory(events.sparkSession) if memory is None else memory
    loads, fine = fine_loads(events, grid, options)
    n = sum(loads.values())
    fitting = [e for e in estimates(loads, fine, grid, bw, workers, memory) if e.fits and possible(e, n, grid, bw, options)]
    return min(fitting, key=lambda e: (e.seconds(workers), e.method, str(e.tiles)))


#: share of tiles that a replication plan may copy before tiles count as too coarse
COARSE = 0.5


def explain_plan(loads: dict[int, int], tiles: TileSpec, workers: int) -> dict:
    """What a replication plan would do, and a warning where tiles are too coarse for it.

    With few tiles nearly every one is on a critical path in some round and gets copied, up to a copy for each worker, which
    is no better than private cubes of the whole domain.
    """
    plan = dag.replication_plan(loads, dag.greedy_colors(loads, tiles), tiles, workers)
    used = [t for t, n in loads.items() if n]
    copied = [t for t in used if plan.copies[t] > 1]
    share = len(copied) / max(1, len(used))
    return {
        "tiles": tiles.total,
        "used": len(used),
        "copied": len(copied),
        "copies": sum(r - 1 for r in plan.copies.values()),
        "rounds": plan.rounds,
        "warning": "tiles are coarse: most of them are copied, as private cubes would be" if share > COARSE and workers > 1 else None,
    }
