"""Private cubes that are summed: events are dealt evenly, each share fills a cube of its own."""

from __future__ import annotations

from typing import Iterator, Tuple  # noqa: UP035  the engine reads these hints

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from cubedensity.operators.blocks import CUBE_WIDTH, PIECE, Kernel, parcels, pieces, sum_pieces, task_memory, unpacked
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec

WIDTH = CUBE_WIDTH
#: parts of the domain in which private cubes are summed, along its longest axis
SHARES = 32


class ReplicaTooLarge(MemoryError):
    """The private cubes do not fit the memory they may take."""


def replica_bytes(grid: GridSpec, copies: int, width: int = WIDTH) -> int:
    return grid.cells * copies * width


def check_memory(grid: GridSpec, copies: int, limit: int | None, width: int = WIDTH) -> None:
    need = replica_bytes(grid, copies, width)
    if limit is not None and need > limit:
        raise ReplicaTooLarge(f"{copies} cubes of {grid.cells} voxels take {need} bytes, {limit} are allowed")


def replica_sum(events: DataFrame, grid: GridSpec, bw: Bandwidth, copies: int, options: PlanOptions = PlanOptions(), memory_limit: int | None = None, emit: str = "rows") -> DataFrame:
    """``copies`` private cubes, then their sum. Refused where one cube exceeds the memory of a task, or where all exceed
    ``memory_limit`` bytes, if that is given."""
    check_memory(grid, 1, task_memory(events.sparkSession))
    check_memory(grid, copies, memory_limit)
    kernel = Kernel(grid, bw, options)
    box = [(0, g) for g in grid.shape]
    # the cubes are summed in shares that lie along the longest axes, a few for each worker
    shares = TileSpec(*(min(g, SHARES if g == max(grid.shape) else 1) for g in grid.shape))

    def fill(key: Tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # noqa: UP006
        mass, hits = kernel.empty(box)
        for x, y, t, w in unpacked(batches):
            kernel.fill(mass, hits, box, x, y, t, w)
        yield from pieces(mass, hits, box, shares, grid)

    ready = inside(events, grid, options, bw.lattice(grid))
    # dealt by a hash of the whole event, so a task that runs again gets the same share
    deal = lambda x, y, t, whole: (np.arange(len(x)), [np.mod(whole, copies)])
    parts = parcels(ready, copies, "replica", place=deal, hashed=True, narrow=kernel.narrow).groupBy("replica").applyInArrow(fill, PIECE)
    return sum_pieces(parts, grid, bw, shares, options, emit)
