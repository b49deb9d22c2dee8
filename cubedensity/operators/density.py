"""One call for every method."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.operators import pointsets, relational, replicas
from cubedensity.operators.tiles import tile_clip
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec

BLOCK_METHODS = ("replica_sum", "tile_clip", "parity_sets", "loadaware_sets", "replicated_sets")
METHODS = (*relational.METHODS, *BLOCK_METHODS)


def cube(events: DataFrame, grid: GridSpec, bw: Bandwidth, method: str = "auto", options: PlanOptions = PlanOptions(), tiles: TileSpec | None = None, workers: int | None = None, partitions: int | None = None, fall_back: bool = False, **more) -> DataFrame:
    """``(vx, vy, vt, hits, mass)`` by any method; ``auto`` takes the cheapest by the cost model.

    ``partitions`` deals the events out first: for tables of few files, whose splits would leave workers idle. With
    ``fall_back``, clipped tiles take the place of private cubes that do not fit memory.
    """
    if partitions:
        events = events.repartition(partitions, "event_id")
    workers = workers or events.sparkSession.sparkContext.defaultParallelism
    if method == "auto":
        from cubedensity.plans.chooser import choose

        best = choose(events, grid, bw, workers, options=options)
        method, tiles = best.method, best.tiles or tiles
    if method in relational.METHODS:
        return relational.METHODS[method](events, grid, bw, options, **more)
    if method == "replica_sum":
        try:
            return replicas.replica_sum(events, grid, bw, workers, options, **more)
        except replicas.ReplicaTooLarge:
            if not fall_back:
                raise
            method = "tile_clip"
            more.pop("memory_limit", None)
    tiles = (tiles or default_tiles(grid, bw, workers)).clamp(grid)
    if method == "tile_clip":
        return tile_clip(events, grid, bw, tiles, options, **more)
    if method == "parity_sets":
        return pointsets.parity_sets(events, grid, bw, tiles, options, **more)
    if method == "loadaware_sets":
        return pointsets.loadaware_sets(events, grid, bw, tiles, options, **more)
    if method == "replicated_sets":
        return pointsets.replicated_sets(events, grid, bw, tiles, workers, options, **more)
    raise ValueError(f"no method {method!r}; there are {METHODS}")


def default_tiles(grid: GridSpec, bw: Bandwidth, workers: int = 1) -> TileSpec:
    """Tiles about eight bandwidths wide, so that an event has about two copies, and of 32 voxels at least; narrower ones,
    down to two bandwidths, where there would be fewer than two for each worker."""
    hs, ht = bw.whole
    reach = (hs, hs, ht)
    width = [max(32, 8 * h) for h in reach]
    count = lambda: [max(1, g // v) for g, v in zip(grid.shape, width)]
    while math.prod(count()) < 2 * workers:
        wide = [k for k in range(3) if min(width[k], grid.shape[k]) // 2 >= max(4, 2 * reach[k])]
        if not wide:
            break
        k = max(wide, key=lambda k: (min(width[k], grid.shape[k]) / reach[k], -k))
        width[k] = min(width[k], grid.shape[k]) // 2
    return TileSpec(*count())


def density(events: DataFrame, grid: GridSpec, bw: Bandwidth, method: str = "auto", options: PlanOptions = PlanOptions(), dense: bool = False, **more) -> DataFrame:
    """``(vx, vy, vt, hits, mass, density)``: the cube, normalised by the number of events that took part."""
    found = cube(events, grid, bw, method, options, **more)
    if dense:
        found = relational.with_zeros(found, grid)
    return relational.normalise(found, inside(events, grid, options, bw.lattice(grid)).agg(F.count("*")), grid, bw, options)
