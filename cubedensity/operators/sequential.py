"""The sequential methods over arrays: the form for large event sets.

Each method does what its relational form in ``relational`` does, to arrays of events instead of rows, and adds to a
private cube; the cubes of the workers are summed. What a method tests and evaluates, and how often, stays its own:

* ``voxel_scan``: every column of the grid tests every event, every time of it each event of its disk;
* ``block_scan``: every voxel of 27 blocks tests and evaluates every event of the middle one;
* ``scatter``: every voxel of an event's box is tested and both factors are evaluated there;
* ``disk_scatter``: the spatial factor once for each place of the disk, the temporal one at every voxel;
* ``bar_scatter``: the temporal factor once for each time of the bar, the spatial one at every voxel;
* ``product_scatter``: both factors once, their product at every voxel.
"""

from __future__ import annotations

import math
from typing import Iterator  # noqa: UP035

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from cubedensity.functions.kernels import in_bar, in_disk, spatial, temporal
from cubedensity.operators.blocks import CUBE_WIDTH, PIECE, TOO_LARGE, Kernel, parcels, pieces, plus, sum_pieces, task_memory, unpacked
from cubedensity.operators.replicas import SHARES
from cubedensity.sources.ingest import inside
from cubedensity.spec import DOUBLE_LIMIT, LONG_LIMIT, Bandwidth, GridSpec, PlanOptions, TileSpec, largest_term

#: pairs of an event and a voxel from which arrays pay for the start of their workers
MANY_PAIRS = 50_000_000
#: pairs that are evaluated at a time, so that they stay in the cache of a core
EVALUATED = 1 << 13
#: events that a scan of all columns looks at at a time
SCANNED = 1 << 15
#: events whose sums by voxel are taken at a time
SUMMED = 256
#: entries of the boxes that are held before they are added to the cube
HELD = 1 << 19


def many(method: str, events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> bool:
    """Whether arrays are the form for these events: they meet many voxels, and the cube, its margin included, fits a task.

    Takes a short pass that ends once there are enough events."""
    if events.isStreaming or options.mass == "decimal":
        return False
    if math.prod(g + 2 * m for g, m in zip(grid.shape, margin(bw))) * CUBE_WIDTH > task_memory(events.sparkSession):
        return False
    hs, _, half = reach(bw)
    met = {"voxel_scan": grid.gx * grid.gy + 4 * hs * hs * grid.gt, "block_scan": 27 * hs * hs * half}.get(method, (2 * hs + 1) ** 2 * (2 * half + 1))
    few = MANY_PAIRS // met
    return events.limit(few + 1).count() > few


def reach(bw: Bandwidth) -> tuple[int, int, int]:
    return bw.whole[0], bw.whole[0], bw.whole[1]


def margin(bw: Bandwidth) -> tuple[int, int, int]:
    """Voxels beyond the grid that boxes of events in it, or in the halo around it, may take."""
    return tuple(2 * h for h in reach(bw))


def over_arrays(method: str, events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """``(vx, vy, vt, hits, mass)`` by a sequential method: a private cube a worker, then their sum."""
    kernel, copies = Kernel(grid, bw, options), events.sparkSession.sparkContext.defaultParallelism
    box = [(0, g) for g in grid.shape]
    shares = TileSpec(*(min(g, SHARES if g == max(grid.shape) else 1) for g in grid.shape))

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        private = Private(method, grid, bw, options)
        for event in unpacked(batches):
            private.add(*event)
        yield from pieces(*private.cube(), box, shares, grid)

    ready = inside(events, grid, options, bw.lattice(grid))
    # by a hash of the whole event, and each share a partition of its own: no two of them meet in one task
    deal = lambda x, y, t, whole: (np.arange(len(x)), [np.mod(whole, copies)])
    parts = parcels(ready, copies, "replica", place=deal, hashed=True, narrow=kernel.narrow, own_partition=True).mapInArrow(fill, PIECE)
    return sum_pieces(parts, grid, bw, shares, options)


class Private:
    """A cube with a margin, so that boxes need no clipping, and the methods that add events to it."""

    def __init__(self, method: str, grid: GridSpec, bw: Bandwidth, options: PlanOptions):
        self.method, self.grid, self.bw, self.options = method, grid, bw, options
        self.margin = margin(bw)
        shape = tuple(g + 2 * m for g, m in zip(grid.shape, self.margin))
        self.mass = np.zeros(shape, np.float64 if options.mass == "double" else np.int64)
        self.hits = np.zeros(shape, np.int64)

    def cube(self):
        """Mass and hits of the grid itself."""
        own = tuple(slice(m, m + g) for m, g in zip(self.margin, self.grid.shape))
        return self.mass[own], self.hits[own]

    def add(self, x, y, t, w) -> None:
        if not len(x):
            return
        self.term = largest_term(self.grid, self.bw, self.options) * max(1, int(np.abs(w).max()))
        if self.mass.dtype == np.int64 and self.term > LONG_LIMIT:
            raise OverflowError(TOO_LARGE)
        {"voxel_scan": self._columns, "block_scan": self._blocks}.get(self.method, self._boxes)(x, y, t, w)

    def _kind(self, events: int):
        """The type in which terms of so many events are summed: doubles where they are exact, or asked for."""
        if self.mass.dtype == np.float64 or self.term * events < DOUBLE_LIMIT:
            return np.float64
        if self.term * events > LONG_LIMIT:
            raise OverflowError(TOO_LARGE)
        return np.int64

    # event-driven ------------------------------------------------------------------------------------------------
    def _boxes(self, x, y, t, w) -> None:
        """Events in the order of their own voxels; those of one voxel have one box, whose sums go to the cube."""
        s, (hs, _, half) = self.grid.sub, reach(self.bw)
        shape = self.mass.shape
        own = [np.floor_divide(c, s) for c in (x, y, t)]
        voxel = np.ravel_multi_index([o + m for o, m in zip(own, self.margin)], shape)
        order = np.argsort(voxel, kind="stable")
        voxel, w = voxel[order], w[order]
        even = bool((w == 1).all())
        within = [(c - o * s)[order] for c, o in zip((x, y, t), own)]
        new = np.concatenate(([True], voxel[1:] != voxel[:-1]))
        group, starts = np.cumsum(new) - 1, voxel[new]
        size = (2 * hs + 1) ** 2 * (2 * half + 1)
        ax, at = np.arange(-hs, hs + 1), np.arange(-half, half + 1)
        offsets = ((ax[:, None, None] * shape[1] + ax[None, :, None]) * shape[2] + at).reshape(-1)
        step = max(1, min(SUMMED, EVALUATED // size))
        kind = self._kind(step)
        room = max(step, HELD // size)
        near = ax.astype(kind) * s + self.options.offset(self.grid)
        then = at.astype(kind) * s + self.options.offset(self.grid)
        dx, dy, dt = (c[:, None] - p.astype(kind) for c, p in zip((near, near, then), within))
        first, mass, hits = 0, None, None
        for k in range(0, len(voxel), step):
            part = slice(k, min(k + step, len(voxel)))
            a, b = int(group[k]), int(group[part.stop - 1]) + 1
            if mass is None or b - first > room:
                if mass is not None:
                    self._spread(starts[first : first + room], offsets, mass, hits)
                first = a
                mass, hits = np.zeros((size, room), self.mass.dtype), np.zeros((size, room), np.int64)
            value, met = self._terms(dx[:, part], dy[:, part], dt[:, part], None if even else w[part].astype(kind))
            member = group[part][:, None] == np.arange(a, b)
            mass[:, a - first : b - first] += (value @ member.astype(kind)).astype(mass.dtype)
            hits[:, a - first : b - first] += (met.astype(np.float32) @ member.astype(np.float32)).astype(np.int64)
        self._spread(starts[first : first + room], offsets, mass, hits)

    def _terms(self, dx, dy, dt, w):
        """Terms of events at all voxels of their boxes, and which voxels they cover, by the form of the method. Events lie
        along the last axis, which is the longest."""
        n, hx, ht = dx.shape[1], *self.bw.lattice(self.grid)
        whole = (len(dx), len(dy), len(dt), n)
        every = lambda d: np.ascontiguousarray(np.broadcast_to(d, whole))
        dx, dy, dt = dx[:, None, None], dy[None, :, None], dt[None, None]
        if self.method in ("scatter", "bar_scatter"):
            dx, dy = every(dx), every(dy)
        if self.method in ("scatter", "disk_scatter"):
            dt = every(dt)
        disk, bar = in_disk(dx, dy, hx), in_bar(self.options.edge, dt, ht)
        ks, kt = spatial(self.options.kernel, dx, dy, hx) * disk, temporal(self.options.kernel, dt, ht) * bar
        if w is not None:
            # with the factor that is kept, or at every voxel where none is
            if self.method == "bar_scatter":
                kt = kt * w
            else:
                ks = ks * w
        return (ks * kt).reshape(-1, n), (disk & bar).reshape(-1, n)

    def _spread(self, voxels, offsets, mass, hits) -> None:
        """Adds sums over boxes to the cube: one entry of all boxes at a time, as the boxes have different voxels."""
        flat, counts = self.mass.reshape(-1), self.hits.reshape(-1)
        for offset, m, h in zip(offsets.tolist(), mass[:, : len(voxels)], hits[:, : len(voxels)]):
            at = voxels + offset
            held = flat[at]
            plus(held, m)
            flat[at] = held
            counts[at] += h

    # voxel-driven ------------------------------------------------------------------------------------------------
    def _axes(self, kind):
        g, o = self.grid, self.options.offset(self.grid)
        return [np.arange(n, dtype=kind) * g.sub + o for n in g.shape]

    def _columns(self, x, y, t, w) -> None:
        """Every column looks at every event, and its times at those in its disk."""
        hx, ht = self.bw.lattice(self.grid)
        ax, ay, at = self._axes(np.int64)
        # places of events may lie as far beyond the grid as they reach
        widest = sum((g * self.grid.sub + hx) ** 2 for g in self.grid.shape[:2])
        small = np.int32 if widest < 1 << 31 else np.int64
        mass, hits = self.cube()
        for k in range(0, len(x), SCANNED):
            part = slice(k, k + SCANNED)
            px, py, pw = x[part].astype(small), y[part].astype(small), w[part]
            kind = self._kind(len(px))
            pt, limit = t[part].astype(kind), small(hx * hx)
            times, even = at.astype(kind), bool((pw == 1).all())
            dys = ay.astype(small)[:, None] - py
            squares = dys * dys
            for i, cx in enumerate(ax.tolist()):
                dx = small(cx) - px
                far = dx * dx
                for j in range(len(ay)):
                    seen = np.flatnonzero(far + squares[j] < limit)
                    if not len(seen):
                        continue
                    ks = spatial(self.options.kernel, dx[seen].astype(kind), dys[j][seen].astype(kind), hx)
                    if not even:
                        ks = ks * pw[seen].astype(kind)
                    for a in range(0, len(seen), step := max(1, 2 * EVALUATED // len(times))):
                        dt = times[None, :] - pt[seen[a : a + step], None]
                        bar = in_bar(self.options.edge, dt, ht)
                        made = ks[a : a + step] @ (temporal(self.options.kernel, dt, ht) * bar)
                        plus(mass[i, j], made.astype(mass.dtype))
                        hits[i, j] += (np.ones(len(bar), np.float32) @ bar.astype(np.float32)).astype(np.int64)

    def _blocks(self, x, y, t, w) -> None:
        """Every voxel of the blocks around a block, and of the block, looks at every event of it."""
        g, o = self.grid, self.options.offset(self.grid)
        hx, ht = self.bw.lattice(g)
        block = [np.floor_divide(c, h) for c, h in zip((x, y, t), (hx, hx, ht))]
        low = [int(b.min()) for b in block]
        key = np.ravel_multi_index([b - lo for b, lo in zip(block, low)], [int(b.max()) - lo + 1 for b, lo in zip(block, low)])
        order = np.argsort(key, kind="stable")
        key = key[order]
        starts = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1]))).tolist()
        x, y, t, w, *block = (c[order] for c in (x, y, t, w, *block))
        even = bool((w == 1).all())
        firsts = [b[starts].tolist() for b in block]
        axes = self._axes(np.int64)
        mass, hits = self.cube()
        for a, b, *place in zip(starts, [*starts[1:], len(x)], *firsts):
            spans = [
                (max(0, -(-((p - 1) * h - o) // g.sub)), min(n, -(-((p + 2) * h - o) // g.sub))) for p, h, n in zip(place, (hx, hx, ht), g.shape)
            ]
            shape = [q - p for p, q in spans]
            if min(shape) <= 0:
                continue
            spot = tuple(slice(p, q) for p, q in spans)
            step = max(1, EVALUATED // math.prod(shape))
            kind = self._kind(step)
            cx, cy, ct = (c[s].astype(kind) for c, s in zip(axes, spot))
            for k in range(a, b, step):
                part = slice(k, min(k + step, b))
                whole = (*shape, part.stop - k)
                dx, dy, dt = (
                    np.ascontiguousarray(np.broadcast_to(d, whole))
                    for d in (
                        (cx[:, None] - x[part].astype(kind))[:, None, None],
                        (cy[:, None] - y[part].astype(kind))[None, :, None],
                        (ct[:, None] - t[part].astype(kind))[None, None],
                    )
                )
                near = in_disk(dx, dy, hx) & in_bar(self.options.edge, dt, ht)
                value = spatial(self.options.kernel, dx, dy, hx) * temporal(self.options.kernel, dt, ht) * near
                if not even:
                    value = value * w[part].astype(kind)
                plus(mass[spot], value.sum(axis=-1).astype(mass.dtype))
                hits[spot] += (near.astype(np.float32) @ np.ones(whole[-1], np.float32)).astype(np.int64)
