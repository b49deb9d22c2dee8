"""Dense kernels over Arrow batches: the form for large event sets.

A kernel gets the events of a box of voxels in bounded batches and adds them to one dense array. For a batch, the
spatial factor of every event at every place of the box and the temporal factor at every time are tabulated once, and
the box grows by the product of the two tables. For comparison there are forms that keep one of the two factors or
neither, and evaluate the rest at every voxel. Whole numbers are kept: in doubles through the matrix library where
every partial sum stays below 2^53, in 64-bit integers otherwise. A box is cut into cells of about the bandwidth, so
that the tables stay mostly full, and only touched voxels leave as rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from itertools import product
from typing import Iterator, Tuple  # noqa: UP035  the engine reads these hints

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.functions.kernels import in_bar, in_disk, spatial, temporal
from cubedensity.spec import DOUBLE_LIMIT, LONG_LIMIT, Bandwidth, GridSpec, PlanOptions, TileSpec, largest_term

BATCH = 4096
#: events that a task gathers before it adds them, and the fewest of them for which a sum is taken again
GATHERED = 1 << 20
FEW = 10_000
#: entries of the profiles, and events, that are summed by place at a time
PROFILE = 1 << 19
PLACED = 1 << 17
#: events that a cell should hold, and products an event may cost at most for it
CELL_EVENTS = 48
CELL_PRODUCTS = 8192
ROWS_OUT = 65_536
#: bytes of a voxel in a dense array: mass and hits
CUBE_WIDTH = 16
#: which factors are tabulated once for each event: both, the spatial one, the temporal one, none
FORMS = ("product", "disk", "bar", "plain")
#: voxels of all events together that a form without both tables evaluates at a time
EVALUATED = 1 << 20


TOO_LARGE = "masses of this box may not fit 64 bits: use mass='double' or smaller groups"


def plus(total, more) -> None:
    """``total += more`` in place; whole numbers that leave 64 bits are an error."""
    before = total.copy() if total.dtype == np.int64 else None
    total += more
    if before is not None and bool((((before ^ total) & (more ^ total)) < 0).any()):
        raise OverflowError(TOO_LARGE)


@dataclass(frozen=True)
class Kernel:
    grid: GridSpec
    bw: Bandwidth
    options: PlanOptions = PlanOptions()
    form: str = "product"

    def __post_init__(self):
        if self.form not in FORMS:
            raise ValueError(f"{self.form!r} is none of {FORMS}")

    @property
    def narrow(self) -> bool:
        """Whether the coordinates of all events that may reach the grid take 16 bits."""
        return max(self.grid.shape) * self.grid.sub + max(self.bw.lattice(self.grid)) < HALF

    def box_of(self, low, high):
        """A box of voxels with the halo that its events reach, clipped to the grid."""
        hs, ht = self.bw.whole
        return [(max(0, a - h), min(g, b + h)) for a, b, h, g in zip(low, high, (hs, hs, ht), self.grid.shape)]

    def tables(self, x, y, t, box):
        """Disk and bar tables of a batch of events over a box, with the masks of what they cover."""
        g, o = self.grid, self.options.offset(self.grid)
        hx, ht = self.bw.lattice(g)
        at = [np.arange(a, b, dtype=np.int64) * g.sub + o for a, b in box]
        dx, dy, dt = at[0][None, :, None] - x[:, None, None], at[1][None, None, :] - y[:, None, None], at[2][None, :] - t[:, None]
        disk, bar = in_disk(dx, dy, hx), in_bar(self.options.edge, dt, ht)
        ks = np.where(disk, spatial(self.options.kernel, dx, dy, hx), 0)
        kt = np.where(bar, temporal(self.options.kernel, dt, ht), 0)
        n = len(x)
        return ks.reshape(n, -1), kt, disk.reshape(n, -1), bar

    def add(self, mass, hits, box, x, y, t, w, weight_bound: int) -> None:
        """Add events to dense arrays over ``box``. All parts of the arrays that the events reach must be in it."""
        if self.form != "product":
            return self._evaluate(mass, hits, box, x, y, t, w)
        term = largest_term(self.grid, self.bw, self.options) * max(1, weight_bound)
        shape = tuple(b - a for a, b in box)
        for at in range(0, len(x), BATCH):
            part = slice(at, at + BATCH)
            ks, kt, disk, bar = self.tables(x[part], y[part], t[part], box)
            ks = ks * w[part][:, None]
            if mass.dtype == np.float64 or term * ks.shape[0] < DOUBLE_LIMIT:
                made = ks.T.astype(np.float64) @ kt.astype(np.float64)
                plus(mass, made.reshape(shape).astype(mass.dtype))
            else:
                plus(mass, (ks.T @ kt).reshape(shape))
            hits += (disk.T.astype(np.float32) @ bar.astype(np.float32)).reshape(shape).astype(np.int64)

    def _evaluate(self, mass, hits, box, x, y, t, w) -> None:
        """The forms that do not keep both factors: what is not kept is evaluated at every voxel of every event's box."""
        g, o = self.grid, self.options.offset(self.grid)
        hx, ht = self.bw.lattice(g)
        at = [np.arange(a, b, dtype=np.int64) * g.sub + o for a, b in box]
        step = max(1, EVALUATED // max(1, math.prod(b - a for a, b in box)))
        for k in range(0, len(x), step):
            part = slice(k, k + step)
            n = len(x[part])
            dx = at[0][None, :, None, None] - x[part][:, None, None, None]
            dy = at[1][None, None, :, None] - y[part][:, None, None, None]
            dt = at[2][None, None, None, :] - t[part][:, None, None, None]
            whole = (n, *(b - a for a, b in box))
            every = lambda d: np.ascontiguousarray(np.broadcast_to(d, whole))  # noqa: B023,E731
            if self.form in ("plain", "bar"):
                dx, dy = every(dx), every(dy)
            if self.form in ("plain", "disk"):
                dt = every(dt)
            ks = spatial(self.options.kernel, dx, dy, hx) * in_disk(dx, dy, hx)
            kt = temporal(self.options.kernel, dt, ht) * in_bar(self.options.edge, dt, ht)
            plus(mass, (ks * kt * w[part][:, None, None, None]).sum(axis=0).astype(mass.dtype))
            hits += (in_disk(dx, dy, hx) & in_bar(self.options.edge, dt, ht)).sum(axis=0)

    def cells(self, box, events: int):
        """Edges of the cells that a box is cut into: about two bandwidths, and larger where a cell would hold few events,
        since each cell costs some calls and each event the products of its cell and halo."""
        hs, ht = self.bw.whole
        halo = (2 * hs, 2 * hs, 2 * ht)
        edge = [min(b - a, max(4, min(32, h))) for (a, b), h in zip(box, halo)]
        while True:
            count = math.prod(-(-(b - a) // e) for (a, b), e in zip(box, edge))
            grow = [k for k, (a, b) in enumerate(box) if edge[k] < b - a]
            if events >= CELL_EVENTS * count or not grow:
                return edge
            k = min(grow, key=lambda k: (edge[k] / halo[k], k))
            if math.prod((2 * e if j == k else e) + h for j, (e, h) in enumerate(zip(edge, halo))) > CELL_PRODUCTS:
                return edge
            edge[k] = min(2 * edge[k], box[k][1] - box[k][0])

    def fill(self, mass, hits, box, x, y, t, w) -> None:
        """Add events to dense arrays over a box, by place or cell by cell; what falls outside the box is clipped."""
        if not len(x):
            return
        bound = int(np.abs(w).max())
        if self.form == "product" and len(x) >= mass.size and self._bar_bound() * bound * len(x) < DOUBLE_LIMIT:
            return self._by_place(mass, hits, box, x, y, t, w)
        term = largest_term(self.grid, self.bw, self.options) * bound
        step = len(x) if mass.dtype == np.float64 or term * len(x) <= LONG_LIMIT else FEW
        if mass.dtype != np.float64 and term * min(step, len(x)) > LONG_LIMIT:
            raise OverflowError(TOO_LARGE)
        for at in range(0, len(x), step):
            part = slice(at, at + step)
            self._by_cell(mass, hits, box, x[part], y[part], t[part], w[part], bound)

    def _bar_bound(self) -> int:
        """Bound of the temporal factor."""
        return 4 * self.bw.lattice(self.grid)[1] ** 2

    def _by_place(self, mass, hits, box, x, y, t, w) -> None:
        """Events of one place share their disk: their bars are summed into a profile over the times of the box, and the
        profiles of a column of voxels meet one table of what each place within a voxel gives to the voxels around it."""
        s, o = self.grid.sub, self.options.offset(self.grid)
        hs, half = self.bw.whole
        hx, ht = self.bw.lattice(self.grid)
        within, near, then = np.arange(s, dtype=np.int64), np.arange(-hs, hs + 1) * s + o, np.arange(-half, half + 1) * s + o
        dx, dy = near[None, None, :, None] - within[:, None, None, None], near[None, None, None, :] - within[None, :, None, None]
        dt = then[None, :] - within[:, None]
        disk, bar = in_disk(dx, dy, hx), in_bar(self.options.edge, dt, ht)
        ks = np.where(disk, spatial(self.options.kernel, dx, dy, hx), 0).reshape(s * s, -1).T
        kt = np.where(bar, temporal(self.options.kernel, dt, ht), 0).astype(np.float64)
        disk, bar = np.ascontiguousarray(disk.reshape(s * s, -1).T, np.float64), bar.astype(np.float64)
        widest = int(np.abs(ks).max())

        (x0, x1), (y0, y1), (t0, t1) = box
        vx, vy, vt = (np.floor_divide(c, s) for c in (x, y, t))
        keep = (vx >= x0 - hs) & (vx < x1 + hs) & (vy >= y0 - hs) & (vy < y1 + hs) & (vt >= t0 - half) & (vt < t1 + half)
        if not keep.all():
            x, y, t, w, vx, vy, vt = (c[keep] for c in (x, y, t, w, vx, vy, vt))
        # a profile has room for every time that a kept event reaches, so that no bar is cut while it is added
        long, first, high = t1 - t0 + 4 * half, t0 - 2 * half, y1 - y0 + 2 * hs
        column = (vx - (x0 - hs)) * high + (vy - (y0 - hs))
        order = np.argsort(column.astype(np.uint16) if (x1 - x0 + 2 * hs) * high < 1 << 16 else column, kind="stable")
        column = column[order]
        at = (((x - vx * s) * s + (y - vy * s)) * long + (vt - half - first))[order]
        late, w = (t - vt * s)[order], w[order].astype(np.float64)
        even = bool((w == 1).all())
        starts = np.flatnonzero(np.concatenate(([True], column[1:] != column[:-1]))) if len(column) else np.zeros(0, np.int64)
        ends, size, bars = np.append(starts[1:], len(column)), s * s * long, np.arange(2 * half + 1)
        taken = max(1, PROFILE // size)
        for k in range(0, len(starts), taken):
            some = slice(k, k + taken)
            columns_ = column[starts[some]]
            profile, counts = np.zeros(len(columns_) * size), np.zeros(len(columns_) * size)
            for a in range(starts[k], ends[some][-1], PLACED):
                part = slice(a, min(a + PLACED, ends[some][-1]))
                nth = np.searchsorted(columns_, column[part])
                spot = ((nth * size + at[part])[:, None] + bars).reshape(-1)
                value = kt[late[part]] if even else kt[late[part]] * w[part][:, None]
                profile += np.bincount(spot, value.reshape(-1), len(profile))
                counts += np.bincount(spot, bar[late[part]].reshape(-1), len(counts))
            profile, counts = (c.reshape(len(columns_), s * s, long)[:, :, 2 * half : 2 * half + t1 - t0] for c in (profile, counts))
            made, met = self._spread(ks, profile, widest, mass.dtype), (disk @ counts).astype(np.int64)
            for c, m, h in zip(columns_.tolist(), made, met):
                cx, cy = c // high + x0 - hs, c % high + y0 - hs
                (p, q), (u, v) = (max(cx - hs, x0), min(cx + hs + 1, x1)), (max(cy - hs, y0), min(cy + hs + 1, y1))
                if p >= q or u >= v:
                    continue
                cut = slice(p - cx + hs, q - cx + hs), slice(u - cy + hs, v - cy + hs)
                spot = slice(p - x0, q - x0), slice(u - y0, v - y0)
                plus(mass[spot], m.reshape(2 * hs + 1, 2 * hs + 1, -1)[cut])
                hits[spot] += h.reshape(2 * hs + 1, 2 * hs + 1, -1)[cut]

    @staticmethod
    def _spread(ks, profile, widest: int, dtype):
        """``ks @ profile`` in whole numbers: ``ks`` goes through the matrix library in parts of so few bits that sums stay below 2^53."""
        most = int(np.abs(profile).sum(axis=1).max(initial=0))
        if dtype != np.float64 and widest * most > LONG_LIMIT:
            raise OverflowError(TOO_LARGE)
        bits = max(1, DOUBLE_LIMIT.bit_length() - 1 - most.bit_length())
        made = 0
        for low in range(0, max(1, widest.bit_length()), bits):
            # the arithmetic shift keeps the sign in the last part
            part = ks >> low if low + bits >= widest.bit_length() else (ks >> low) & ((1 << bits) - 1)
            made = made + (np.ascontiguousarray(part, np.float64) @ profile).astype(dtype) * dtype.type(1 << low)
        return made

    def _by_cell(self, mass, hits, box, x, y, t, w, bound: int) -> None:
        s = self.grid.sub
        own = [np.floor_divide(c, s) for c in (x, y, t)]
        size = self.cells(box, len(x))
        key = [(o - a) // c for o, (a, _), c in zip(own, box, size)]
        order = np.lexsort(key)
        key = [k[order] for k in key]
        new = np.flatnonzero(np.any([k[1:] != k[:-1] for k in key], axis=0)) + 1
        for a, b in zip([0, *new.tolist()], [*new.tolist(), len(order)]):
            low = [int(k[a]) * c + lo for k, c, (lo, _) in zip(key, size, box)]
            wide = self.box_of(low, [v + c for v, c in zip(low, size)])
            cut = [(max(p, lo), min(q, hi)) for (p, q), (lo, hi) in zip(wide, box)]
            if any(p >= q for p, q in cut):
                continue
            spot = tuple(slice(p - lo, q - lo) for (p, q), (lo, _) in zip(cut, box))
            at = order[a:b]
            self.add(mass[spot], hits[spot], cut, x[at], y[at], t[at], w[at], bound)

    def empty(self, box):
        shape = tuple(b - a for a, b in box)
        return np.zeros(shape, np.float64 if self.options.mass == "double" else np.int64), np.zeros(shape, np.int64)

    def rows(self, mass, hits, box) -> Iterator[pa.RecordBatch]:
        """Touched voxels as record batches."""
        at = np.nonzero(hits)
        for k in range(0, len(at[0]), ROWS_OUT):
            part = tuple(a[k : k + ROWS_OUT] for a in at)
            voxel = [(a + lo).astype(np.int32) for a, (lo, _) in zip(part, box)]
            yield pa.RecordBatch.from_arrays([*map(pa.array, voxel), pa.array(hits[part]), pa.array(mass[part])], names=["vx", "vy", "vt", "hits", "mass"])

    def block(self, mass, hits, box, key) -> pa.RecordBatch:
        """The whole array of a tile as one row, zeros included, in row-major order."""
        one = lambda values, kind: pa.array([values], pa.list_(kind))
        flat = lambda a, kind: pa.ListArray.from_arrays(pa.array([0, a.size], pa.int32()), pa.array(a.reshape(-1), kind))
        return pa.RecordBatch.from_arrays(
            [
                *(pa.array([k], pa.int32()) for k in key),
                one([a for a, _ in box], pa.int32()),
                one([b - a for a, b in box], pa.int32()),
                flat(hits.astype(np.int32), pa.int32()),
                flat(mass, pa.float64() if mass.dtype == np.float64 else pa.int64()),
            ],
            names=["a", "b", "c", "low", "shape", "hits", "mass"],
        )


_UNITS = {"k": 10, "m": 20, "g": 30, "t": 40}


def task_memory(spark: SparkSession) -> int:
    """Bytes that the arrays of one task may take: a share of an executor's memory for each of its cores."""
    conf = spark.sparkContext.getConf()
    local = spark.sparkContext.master.startswith("local[")
    said = conf.get("spark.driver.memory" if local else "spark.executor.memory", "1g").lower().rstrip("b")
    whole = int(said[:-1]) << _UNITS[said[-1]] if said[-1] in _UNITS else int(said)
    cores = spark.sparkContext.defaultParallelism if local else int(conf.get("spark.executor.cores", "1"))
    return max(64 << 20, whole // (2 * max(1, cores)))


#: a part of a partial cube that one tile owns: its box, and its arrays as bytes, whole or (with ``at``) where events are
PIECE = "a int, b int, c int, low array<int>, shape array<int>, at binary, hits binary, mass binary"
#: share of touched voxels from which a part is sent whole
MOSTLY_FULL = 0.5


def pieces(mass, hits, box, tiles: TileSpec, grid: GridSpec) -> Iterator[pa.RecordBatch]:
    """A partial cube cut along the tiles that own its voxels; parts without events are left out."""
    ranges = [range(lo * n // g, (hi - 1) * n // g + 1) for (lo, hi), n, g in zip(box, tiles.counts, grid.shape)]
    for owner in product(*ranges):
        cut = [(max(p, lo), min(q, hi)) for (p, q), (lo, hi) in zip(tiles.bounds(owner, grid), box)]
        spot = tuple(slice(p - lo, q - lo) for (p, q), (lo, _) in zip(cut, box))
        h, m = hits[spot].reshape(-1), mass[spot].reshape(-1)
        at = np.flatnonzero(h)
        if not len(at):
            continue
        whole = len(at) >= MOSTLY_FULL * len(h) or len(h) > 1 << 31
        held = [None, h, m] if whole else [at.astype(np.int32).tobytes(), h[at], m[at]]
        one = lambda v, kind=pa.list_(pa.int32()): pa.array([v], kind)
        yield pa.RecordBatch.from_arrays(
            [*(pa.array([k], pa.int32()) for k in owner), one([p for p, _ in cut]), one([q - p for p, q in cut]), one(held[0], pa.binary()), one(held[1].astype(np.int32).tobytes(), pa.binary()), one(held[2].tobytes(), pa.binary())],
            names=["a", "b", "c", "low", "shape", "at", "hits", "mass"],
        )


def sum_pieces(parts: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions, emit: str = "rows") -> DataFrame:
    """Sum of partial cubes: each tile gets its pieces as arrays and adds them, so no voxel is shuffled as a row."""
    kernel = Kernel(grid, bw, options)

    def add(key: Tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # noqa: UP006
        tile = tuple(k.as_py() for k in key)
        box = tiles.bounds(tile, grid)
        mass, hits = kernel.empty(box)
        for batch in batches:
            for low, shape, at, h, m in zip(*(batch.column(c).to_pylist() for c in ("low", "shape", "at", "hits", "mass"))):
                spot = tuple(slice(p - lo, p - lo + n) for p, n, (lo, _) in zip(low, shape, box))
                h, m = np.frombuffer(h, np.int32), np.frombuffer(m, mass.dtype)
                if at is None:
                    hits[spot] += h.reshape(shape)
                    plus(mass[spot], m.reshape(shape))
                else:  # each voxel of a piece once
                    place = np.unravel_index(np.frombuffer(at, np.int32), shape)
                    hits[spot][place] += h
                    held = mass[spot][place]
                    plus(held, m)
                    mass[spot][place] = held
        if emit == "blocks":
            yield kernel.block(mass, hits, box, tile)
        else:
            yield from kernel.rows(mass, hits, box)

    keys = ("a", "b", "c")
    return spread(parts, tiles.total, *keys).groupBy(*keys).applyInArrow(add, block_schema(options) if emit == "blocks" else row_schema(options))


EVENT = ("x", "y", "t", "w")
#: events of one group as one row: coordinates in whole numbers of ``width`` bytes, x then y then t, and weights where not all are one
PARCEL = "width int, places binary, weights binary"
#: coordinates from here on, and below its negative, take more than 16 bits
HALF = 1 << 15
#: events of a parcel at most
PARCEL_EVENTS = 1 << 16


def columns(batches, names=EVENT) -> Iterator[tuple[np.ndarray, ...]]:
    """Columns of events, many batches at a time."""
    yield from _gathered(tuple(batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in names) for batch in batches)


def unpacked(batches) -> Iterator[tuple[np.ndarray, ...]]:
    """Coordinates and weights of the parcels of a group, many parcels at a time."""

    def each():
        for batch in batches:
            for width, places, weights in zip(*(batch.column(c) for c in ("width", "places", "weights"))):
                x, y, t = np.frombuffer(places.as_buffer(), f"i{width.as_py()}").reshape(3, -1).astype(np.int64)
                yield x, y, t, np.frombuffer(weights.as_buffer(), np.int64) if weights.is_valid else np.ones(len(x), np.int64)

    yield from _gathered(each())


def _gathered(parts) -> Iterator[tuple[np.ndarray, ...]]:
    held, n = [], 0
    joined = lambda: tuple(np.concatenate(c) for c in zip(*held))
    for part in parts:
        held.append(part)
        n += len(part[0])
        if n >= GATHERED:
            yield joined()
            held, n = [], 0
    if n:
        yield joined()


def parcels(events: DataFrame, groups: int, *keys: str, place=None, hashed: bool = False, narrow: bool = False, own_partition: bool = False) -> DataFrame:
    """Events dealt by group, as parcels instead of rows: sorting and moving a row costs far more than the event it holds.

    ``place`` makes the keys by arrays instead of columns: of ``x, y, t``, and of a hash of the whole event with ``hashed``, it
    gives the numbers of the events to send, repeats included, and their keys. With ``narrow`` all coordinates are within 16
    bits, and reach the workers as one number with bits of the hash: each column of a batch is measured again for every row.
    With ``own_partition`` the only key is a number below ``groups``, and each group is the partition of its number.
    """
    narrow = narrow and place is not None
    whole = F.xxhash64("event_id", "x", "y", "t")
    given = [whole.alias("hash")] * hashed if place else list(keys)
    names = ["hash"] * hashed if place else list(keys)
    sent, reads = [*EVENT, *given], (*EVENT, *names)
    if narrow:
        number = (F.col("x") + HALF) * (1 << 32) + (F.col("y") + HALF) * (1 << 16) + F.col("t") + HALF
        sent, reads = [(number + F.pmod(whole, F.lit(HALF)) * (1 << 48) if hashed else number).alias("number"), "w"], ("number", "w")

    def opened(number, w):
        return (*(((number >> k) & 0xFFFF) - HALF for k in (32, 16, 0)), w, *[number >> 48] * hashed)


    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for found in columns(batches, reads):
            x, y, t, w, *key = opened(*found) if narrow else found
            at, key = place(x, y, t, *key) if place else (np.arange(len(x)), key)
            if not len(at):
                continue
            group = np.zeros(len(at), np.int64)
            for k in key:
                group = group * (int(k.max()) - int(k.min()) + 1) + (k - k.min())
            order = np.argsort(group.astype(np.uint16) if int(group.max()) < 1 << 16 else group, kind="stable")
            group, at, key = group[order], at[order], [k[order] for k in key]
            places, weights = np.stack([c[at] for c in (x, y, t)]), w[at]
            width = next(b for b in (2, 4, 8) if b == 8 or int(np.abs(places).max()) < 1 << (8 * b - 1))
            places, heavy = places.astype(f"i{width}"), bool((weights != 1).any())
            edges = np.concatenate(([0], np.flatnonzero(group[1:] != group[:-1]) + 1, [len(group)])).tolist()
            starts = [k for a, b in zip(edges, edges[1:]) for k in range(a, b, PARCEL_EVENTS)]
            ends = [*starts[1:], len(group)]
            yield pa.RecordBatch.from_arrays(
                [
                    *(pa.array(k[starts].astype(np.int32)) for k in key),
                    pa.array([width] * len(starts), pa.int32()),
                    pa.array([places[:, a:b].tobytes() for a, b in zip(starts, ends)], pa.binary()),
                    pa.array([weights[a:b].tobytes() if heavy else None for a, b in zip(starts, ends)], pa.binary()),
                ],
                names=[*keys, "width", "places", "weights"],
            )

    packed = events.select(*sent).mapInArrow(pack, ", ".join((*(f"{k} int" for k in keys), PARCEL)))
    return packed.repartitionById(groups, *keys) if own_partition else spread(packed, groups, *keys)


def row_schema(options: PlanOptions) -> str:
    return "vx int, vy int, vt int, hits bigint, mass " + ("double" if options.mass == "double" else "bigint")


def spread(df: DataFrame, groups: int, *keys: str) -> DataFrame:
    """Rows dealt by group into a stated number of partitions.

    Groups carry much work on few bytes, so partitions must not be merged by their bytes, as they are where their number is
    left to the engine.
    """
    spark = df.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(groups, 4 * spark.sparkContext.defaultParallelism))
    return df.repartition(parts, *keys)


def block_schema(options: PlanOptions) -> str:
    return f"a int, b int, c int, low array<int>, shape array<int>, hits array<int>, mass array<{'double' if options.mass == 'double' else 'bigint'}>"


def rows_of_blocks(blocks: DataFrame) -> DataFrame:
    """Block rows back to voxel rows; voxels without hits are left out."""
    flat = blocks.select("low", "shape", F.posexplode(F.arrays_zip("hits", "mass")).alias("at", "v")).filter("v.hits > 0")
    size = lambda k: F.element_at("shape", k)
    vx, vy, vt = F.floor(F.col("at") / (size(2) * size(3))), F.pmod(F.floor(F.col("at") / size(3)), size(2)), F.pmod("at", size(3))
    place = [(v + F.element_at("low", k)).cast("int").alias(n) for k, (v, n) in enumerate(((vx, "vx"), (vy, "vy"), (vt, "vt")), 1)]
    return flat.select(*place, F.col("v.hits").cast("bigint").alias("hits"), F.col("v.mass").alias("mass"))
