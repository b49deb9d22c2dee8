"""Tiles of the domain: assignment, loads, safe sizes, and the method that clips cylinders to tiles."""

from __future__ import annotations

import math
from typing import Iterator, Tuple  # noqa: UP035  the engine reads these hints

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.operators.blocks import CUBE_WIDTH, Kernel, block_schema, parcels, row_schema, task_memory, unpacked
from cubedensity.operators.relational import VOXEL, _exact, _long, accumulate, centre, span
from cubedensity.functions.kernels import in_bar, in_disk, spatial, temporal
from cubedensity.plans.durable import durable
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec

AXES = ("a", "b", "c")


def safe_tiles(wanted: TileSpec, grid: GridSpec, bw: Bandwidth) -> TileSpec:
    """Tiles at least twice as wide as the bandwidth: fewer than wanted where they would be too small."""
    hs, ht = bw.whole
    return TileSpec(*(max(1, min(n, g // (2 * h))) for n, g, h in zip(wanted.counts, grid.shape, (hs, hs, ht))))


def voxel_of(coordinate: Column, sub: int) -> Column:
    return F.floor(coordinate / sub).cast("int")


def tile_index(voxel: Column, count: int, cells: int) -> Column:
    return F.floor(voxel.cast("long") * count / cells).cast("int")


def pack(a: Column, b: Column, c: Column, tiles: TileSpec) -> Column:
    return (a.cast("long") * tiles.b + b) * tiles.c + c


def owner(events: DataFrame, grid: GridSpec, tiles: TileSpec) -> DataFrame:
    """Events with the tile that holds them: ``a, b, c`` and ``tile_id``."""
    at = [tile_index(voxel_of(F.greatest(F.lit(0).cast("long"), F.least(F.col(x), F.lit(g * grid.sub - 1).cast("long"))), grid.sub), n, g) for x, n, g in zip("xyt", tiles.counts, grid.shape)]
    return events.select("*", *(c.alias(n) for c, n in zip(at, AXES))).withColumn("tile_id", pack(*map(F.col, AXES), tiles))


def tile_loads(events: DataFrame, grid: GridSpec, tiles: TileSpec) -> DataFrame:
    """Events of each tile that has any: ``(tile_id, a, b, c, load)``."""
    return owner(events, grid, tiles).groupBy("tile_id", *AXES).agg(F.count("*").alias("load"))


def copies(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec) -> DataFrame:
    """Each event once for every tile that its box meets, by interval arithmetic."""
    hs, ht = bw.whole
    out = events
    for axis, x, n, g, h in zip(AXES, "xyt", tiles.counts, grid.shape, (hs, hs, ht)):
        v = voxel_of(F.col(x), grid.sub)
        low, high = F.greatest(v - h, F.lit(0)), F.least(v + h, F.lit(g - 1))
        out = out.select("*", F.explode(F.when(low <= high, F.sequence(tile_index(low, n, g), tile_index(high, n, g))).otherwise(F.array().cast("array<int>"))).alias(axis))
    return out.withColumn("tile_id", pack(*map(F.col, AXES), tiles))


def checked(tiles: TileSpec, grid: GridSpec, bw: Bandwidth, guard: bool) -> TileSpec:
    """Tiles as asked, or with ``guard`` no smaller than twice the bandwidth, so that an event has eight copies at most."""
    return safe_tiles(tiles, grid, bw) if guard else tiles.clamp(grid)


def finer(tiles: TileSpec, factor: int, grid: GridSpec) -> TileSpec:
    """Tiles that nest in ``tiles``, ``factor`` along each axis as far as voxels allow."""
    return TileSpec(*(n * max(1, min(factor, g // n)) for n, g in zip(tiles.counts, grid.shape)))


def fitting(tiles: TileSpec, grid: GridSpec, limit: int) -> TileSpec:
    """``tiles``, or the finer ones that nest in them and whose arrays take at most ``limit`` bytes."""
    while math.prod(-(-g // n) for g, n in zip(grid.shape, tiles.counts)) * CUBE_WIDTH > limit:
        more = finer(tiles, 2, grid)
        if more == tiles:
            raise MemoryError(f"tiles of one voxel exceed {limit} bytes")
        tiles = more
    return tiles


def tile_clip(
    events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions(), guard: bool = False, form: str = "block", emit: str = "rows", kernel_form: str = "product", split_over: int | None = None
) -> DataFrame:
    """Each tile takes the events whose cylinders meet it and writes only its own voxels; tiles are disjoint, so no sum follows.

    ``emit="blocks"`` gives one row of arrays for each tile that has events, for cubes that are mostly full. Tiles whose arrays
    would not fit a task's memory are cut into finer ones. With ``split_over``, so are tiles that more events meet, down to
    parts an eighth as wide, so that a crowded tile is no single task; this takes a pass that counts events by tile.
    ``kernel_form`` names a form of the dense kernel.
    """
    tiles = checked(tiles, grid, bw, guard)
    ready = inside(events, grid, options, bw.lattice(grid))
    if form == "relational":
        return _clip_rows(copies(ready, grid, bw, tiles), grid, bw, tiles, options)
    tiles = fitting(tiles, grid, task_memory(events.sparkSession))
    clip = lambda rows, t: _clip_blocks(parcels(rows, t.total, *AXES), grid, bw, t, options, emit, kernel_form)
    if split_over is None:
        return _clip_blocks(parcels(ready, tiles.total, *AXES, place=meeting(grid, bw, tiles), narrow=Kernel(grid, bw, options).narrow), grid, bw, tiles, options, emit, kernel_form)
    whole = copies(ready, grid, bw, tiles)
    crowded = durable(whole.groupBy(*AXES).agg(F.count("*").alias("n")).filter(F.col("n") > split_over))
    most = crowded.agg(F.max("n")).first()[0]
    fine = finer(tiles, min(8, math.ceil((most or 1) / split_over)), grid)
    if most is None or fine == tiles:
        return clip(whole, tiles)
    hot = F.broadcast(crowded.select(*AXES))  # fewer rows than events over split_over
    parent = [F.floor(F.col(a) * n / m).cast("int").alias(f"p{a}") for a, n, m in zip(AXES, tiles.counts, fine.counts)]
    named = F.broadcast(crowded.select(*(F.col(a).alias(f"p{a}") for a in AXES)))
    parts = copies(ready, grid, bw, fine).select("*", *parent).join(named, [f"p{a}" for a in AXES], "left_semi")
    return clip(whole.join(hot, list(AXES), "left_anti"), tiles).union(clip(parts, fine))


def meeting(grid: GridSpec, bw: Bandwidth, tiles: TileSpec):
    """As ``copies``, over arrays: the numbers of the events, once for every tile that their boxes meet, and the tiles."""
    hs, ht = bw.whole

    def place(*event: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        at, found = np.arange(len(event[0])), []
        for c, n, g, h in zip(event, tiles.counts, grid.shape, (hs, hs, ht)):
            v = np.floor_divide(c, grid.sub)[at]
            low, high = np.maximum(v - h, 0), np.minimum(v + h, g - 1)
            first = low * n // g
            times = np.where(low <= high, high * n // g - first + 1, 0)
            again = np.repeat(np.arange(len(at)), times)
            nth = np.arange(len(again)) - np.repeat(np.cumsum(times) - times, times)
            at, found = at[again], [*(f[again] for f in found), first[again] + nth]
        return at, found

    return place


def _clip_blocks(dealt: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions, emit: str, kernel_form: str) -> DataFrame:
    kernel = Kernel(grid, bw, options, kernel_form)

    def clip(key: Tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # noqa: UP006
        box = tiles.bounds(tuple(k.as_py() for k in key), grid)
        mass, hits = kernel.empty(box)
        for x, y, t, w in unpacked(batches):
            kernel.fill(mass, hits, box, x, y, t, w)
        if emit == "blocks":
            yield kernel.block(mass, hits, box, [k.as_py() for k in key])
        else:
            yield from kernel.rows(mass, hits, box)

    schema = block_schema(options) if emit == "blocks" else row_schema(options)
    return dealt.groupBy(*AXES).applyInArrow(clip, schema)


def zero_blocks(spark: SparkSession, grid: GridSpec, tiles: TileSpec, options: PlanOptions = PlanOptions()) -> DataFrame:
    """The whole domain as arrays of zeros, one row a tile: what a dense cube costs before any event."""
    tiles = fitting(tiles.clamp(grid), grid, task_memory(spark))
    kernel = Kernel(grid, Bandwidth(1, 1), options)

    def fill(batches):
        for batch in batches:
            for k in batch.column("id").to_pylist():
                tile = (k // (tiles.b * tiles.c), k // tiles.c % tiles.b, k % tiles.c)
                box = tiles.bounds(tile, grid)
                yield kernel.block(*kernel.empty(box), box, tile)

    return spark.range(tiles.total).mapInArrow(fill, block_schema(options))


def _clip_rows(ready: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions) -> DataFrame:
    """The relational twin: boxes clipped to the tile, then sums by tile and voxel."""
    hs, half = bw.whole
    hx, ht = map(_long, bw.lattice(grid))
    rows = ready
    for v, x, axis, n, g, h in zip(VOXEL, "xyt", AXES, tiles.counts, grid.shape, (hs, hs, half)):
        own = voxel_of(F.col(x), grid.sub)
        first = lambda k: F.floor((k * g + n - 1) / n).cast("int")  # noqa: B023,E731
        low, high = F.greatest(own - h, first(F.col(axis))), F.least(own + h, first(F.col(axis) + 1) - 1)
        rows = rows.select("*", F.explode(span(low, high)).alias(v))
    dx, dy, dt = (centre(v, grid, options) - F.col(c) for v, c in zip(VOXEL, "xyt"))
    near = rows.filter(in_disk(dx, dy, hx) & in_bar(options.edge, dt, ht))
    term = _exact(spatial(options.kernel, dx, dy, hx), options) * _exact(temporal(options.kernel, dt, ht), options) * _exact(F.col("w"), options)
    return accumulate(near.select("tile_id", *VOXEL, term.alias("term")), options, "tile_id").drop("tile_id")
