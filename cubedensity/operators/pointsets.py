"""Conflict-free sets of tiles: each event belongs to one tile, tiles of one color never write the same voxel.

Colors are not needed for right sums here, since partial cubes meet in a shuffle; they bound how many partial values a
voxel gets, order the work, and drive the phased form, which runs color after color as the method is described.
"""

from __future__ import annotations

from typing import Iterator, Tuple  # noqa: UP035  the engine reads these hints

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.operators import dag
from cubedensity.operators.blocks import PIECE, Kernel, parcels, pieces, row_schema, sum_pieces, unpacked
from cubedensity.operators.relational import merge_cubes
from cubedensity.operators.tiles import AXES, owner, safe_tiles, tile_loads
from cubedensity.plans.durable import durable
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec


def _halo(owned: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions, as_rows: bool = False, **dealt) -> DataFrame:
    """Partial cubes of groups ``(color, tile, replica)``: the tile with the halo that its events reach, cut along the tiles
    that own its parts, or as voxel rows."""
    kernel = Kernel(grid, bw, options)

    def fill(key: Tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # noqa: UP006
        tile = tuple(k.as_py() for k in key[1:4])
        bounds = tiles.bounds(tile, grid)
        hs, ht = bw.whole
        box = [(max(0, a - h), min(g, b + h)) for (a, b), h, g in zip(bounds, (hs, hs, ht), grid.shape)]
        mass, hits = kernel.empty(box)
        for x, y, t, w in unpacked(batches):
            kernel.fill(mass, hits, box, x, y, t, w)
        yield from kernel.rows(mass, hits, box) if as_rows else pieces(mass, hits, box, tiles, grid)

    keys = ("color", *AXES, "replica")
    return parcels(owned, tiles.total, *keys, narrow=kernel.narrow, **dealt).groupBy(*keys).applyInArrow(fill, row_schema(options) if as_rows else PIECE)


def _summed(ready: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions, emit: str, **dealt) -> DataFrame:
    return sum_pieces(_halo(ready, grid, bw, tiles, options, **dealt), grid, bw, tiles, options, emit)


def _ready(events, grid, options) -> DataFrame:
    if options.outside == "halo":
        raise ValueError("events outside the grid belong to no tile: use another method for outside='halo'")
    return inside(events, grid, options)


def _owners(grid: GridSpec, tiles: TileSpec, *event: np.ndarray) -> list[np.ndarray]:
    """As ``owner``, over arrays of events inside the grid."""
    return [np.floor_divide(c, grid.sub) * n // g for c, n, g in zip(event, tiles.counts, grid.shape)]


def parity_sets(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions(), mode: str = "single", emit: str = "rows") -> DataFrame:
    """Eight sets by the parity of the tiles; tiles too small for the bandwidth are enlarged first."""
    tiles = safe_tiles(tiles, grid, bw)
    ready = _ready(events, grid, options)
    if mode == "single":

        def place(*event):
            a, b, c = _owners(grid, tiles, *event)
            return np.arange(len(a)), [a % 2 * 4 + b % 2 * 2 + c % 2, a, b, c, np.zeros(len(a), np.int64)]

        return _summed(ready, grid, bw, tiles, options, emit, place=place)
    color = F.pmod("a", F.lit(2)) * 4 + F.pmod("b", F.lit(2)) * 2 + F.pmod("c", F.lit(2))
    owned = owner(ready, grid, tiles).withColumns({"color": color, "replica": F.lit(0)})
    total = None
    for set_number in range(8):  # one set after the other, over a growing sum
        part = _halo(owned.filter(F.col("color") == set_number), grid, bw, tiles, options, as_rows=True)
        total = durable(part if total is None else merge_cubes(total, part))
    return total


def loads_of(events: DataFrame, grid: GridSpec, tiles: TileSpec) -> dict[int, int]:
    """Tile loads on the driver: as many numbers as there are tiles, refused beyond a bound."""
    dag.check_tiles(tiles)
    return {r["tile_id"]: r["load"] for r in tile_loads(events, grid, tiles).select("tile_id", "load").collect()}


def _painted(grid: GridSpec, tiles: TileSpec, colors: dict[int, int], copies: dict[int, int] | None = None) -> dict:
    """How events are dealt: by the color of their tile, and by hash to a replica where a tile has several copies."""
    # as many numbers as tiles, at most dag.DRIVER_TILES
    color, many = np.zeros(tiles.total, np.int64), np.ones(tiles.total, np.int64)
    for t, c in colors.items():
        color[t], many[t] = c, (copies or {}).get(t, 1)

    def place(x, y, t, whole):
        a, b, c = _owners(grid, tiles, x, y, t)
        tile = (a * tiles.b + b) * tiles.c + c
        return np.arange(len(a)), [color[tile], a, b, c, np.mod(whole, many[tile])]

    return {"place": place, "hashed": True}


def loadaware_sets(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions(), emit: str = "rows") -> DataFrame:
    """Colors by falling load instead of parity."""
    tiles = safe_tiles(tiles, grid, bw)
    ready = _ready(events, grid, options)
    loads = loads_of(events, grid, tiles)
    colors = dag.greedy_colors(loads, tiles, "load")
    return _summed(ready, grid, bw, tiles, options, emit, **_painted(grid, tiles, {t: colors[t] for t in loads}))


def replicated_sets(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, workers: int, options: PlanOptions = PlanOptions(), scope: str = "path", emit: str = "rows") -> DataFrame:
    """Load-aware sets with the tiles of the critical path copied: a copy takes a share of the tile's events, copies are summed."""
    tiles = safe_tiles(tiles, grid, bw)
    ready = _ready(events, grid, options)
    loads = loads_of(events, grid, tiles)
    colors = dag.greedy_colors(loads, tiles, "load")
    plan = dag.replication_plan(loads, colors, tiles, workers, scope=scope)
    return _summed(ready, grid, bw, tiles, options, emit, **_painted(grid, tiles, {t: colors[t] for t in loads}, plan.copies))
