"""Grid, bandwidth, tiles and options: what a density query is made of."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

KERNELS = ("printed", "mirrored", "epanechnikov", "uniform")
EDGES = ("closed_time", "open")
ANCHORS = ("centre", "corner")
OUTSIDE = ("drop", "halo", "error")
LONG_LIMIT = (1 << 63) - 1
#: integers up to here are exact in a double
DOUBLE_LIMIT = 1 << 53


@dataclass(frozen=True)
class GridSpec:
    """A voxel grid of ``gx`` x ``gy`` x ``gt`` with ``sub`` lattice steps along each voxel."""

    gx: int
    gy: int
    gt: int
    sub: int = 16

    def __post_init__(self):
        if min(self.gx, self.gy, self.gt, self.sub) < 1:
            raise ValueError("a grid needs at least one voxel and one lattice step along each axis")

    @classmethod
    def of_extent(cls, extent: tuple[float, float, float], sres: float, tres: float, sub: int = 16) -> GridSpec:
        """Grid of a domain: as many voxels as cover it."""
        x, y, t = extent
        return cls(math.ceil(x / sres), math.ceil(y / sres), math.ceil(t / tres), sub)

    @property
    def shape(self) -> tuple[int, int, int]:
        return self.gx, self.gy, self.gt

    @property
    def cells(self) -> int:
        return self.gx * self.gy * self.gt

    def bytes(self, width: int = 8) -> int:
        """Memory of one dense cube; a width of 4 gives the sizes that the paper lists."""
        return self.cells * width


@dataclass(frozen=True)
class Bandwidth:
    """Radius in space and half height in time, in voxels; fractions are taken to whole lattice steps."""

    hs: float
    ht: float

    def __post_init__(self):
        if self.hs <= 0 or self.ht <= 0:
            raise ValueError("bandwidths are positive")

    @classmethod
    def of_domain(cls, hs: float, ht: float, sres: float, tres: float) -> Bandwidth:
        return cls(hs / sres, ht / tres)

    @property
    def whole(self) -> tuple[int, int]:
        """Bandwidths rounded up to voxels."""
        return math.ceil(self.hs), math.ceil(self.ht)

    def lattice(self, grid: GridSpec) -> tuple[int, int]:
        return max(1, round(self.hs * grid.sub)), max(1, round(self.ht * grid.sub))


@dataclass(frozen=True)
class TileSpec:
    """``a`` x ``b`` x ``c`` tiles; tile of voxel X is ``a*X div gx``."""

    a: int
    b: int
    c: int

    def __post_init__(self):
        if min(self.a, self.b, self.c) < 1:
            raise ValueError("at least one tile along each axis")

    @property
    def counts(self) -> tuple[int, int, int]:
        return self.a, self.b, self.c

    @property
    def total(self) -> int:
        return self.a * self.b * self.c

    def bounds(self, tile: tuple[int, int, int], grid: GridSpec) -> list[tuple[int, int]]:
        """First voxel and the one after the last, along each axis."""
        return [(-(-k * g // n), -(-(k + 1) * g // n)) for k, n, g in zip(tile, self.counts, grid.shape)]

    def widths(self, grid: GridSpec) -> tuple[int, int, int]:
        """Least width of a tile along each axis."""
        return tuple(g // n for n, g in zip(self.counts, grid.shape))

    def clamp(self, grid: GridSpec) -> TileSpec:
        """No more tiles than voxels along an axis."""
        return TileSpec(*(min(n, g) for n, g in zip(self.counts, grid.shape)))


@dataclass(frozen=True)
class PlanOptions:
    kernel: str = "printed"
    edge: str = "closed_time"
    anchor: str = "centre"
    outside: str = "drop"
    mass: str = "long"  # long, decimal or double

    def __post_init__(self):
        for value, known in ((self.kernel, KERNELS), (self.edge, EDGES), (self.anchor, ANCHORS), (self.outside, OUTSIDE), (self.mass, ("long", "decimal", "double"))):
            if value not in known:
                raise ValueError(f"{value!r} is none of {known}")

    def offset(self, grid: GridSpec) -> int:
        """Lattice place of a voxel's sampling point, from its first step."""
        return grid.sub // 2 if self.anchor == "centre" else 0


def largest_term(grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> int:
    """Bound of one event's integer contribution to a voxel."""
    hx, ht = bw.lattice(grid)
    # (1-u)^2 (1-v)^2 over the unit disk is below 8.49; (1-w)^2 is at most 4
    return {"printed": 34 * hx**4 * ht**2, "mirrored": hx**4 * ht**2, "epanechnikov": hx**2 * ht**2, "uniform": 1}[options.kernel]


def mass_type(grid: GridSpec, bw: Bandwidth, options: PlanOptions, events: int) -> PlanOptions:
    """Options with the narrowest exact type for the sum over ``events`` events."""
    return replace(options, mass="long" if largest_term(grid, bw, options) * max(events, 1) <= LONG_LIMIT else "decimal")


def constant(grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> float:
    """What a mass is multiplied by, but for the number of events, to give a density."""
    hx, ht = bw.lattice(grid)
    norm = bw.hs**2 * bw.ht
    return {
        "printed": (math.pi / 2) * 0.75 / (hx**4 * ht**2 * norm),
        "mirrored": (math.pi / 2) * 0.75 / (hx**4 * ht**2 * norm),
        "epanechnikov": (2 / math.pi) * 0.75 / (hx**2 * ht**2 * norm),
        "uniform": 1 / norm,
    }[options.kernel]


#: integral of each kernel pair over its cylinder, for events well inside the domain
MASS_OF_ONE = {
    "printed": (math.pi / 2) * math.pi * (1 + 1 / 2 + 1 / 24) * 2,
    "mirrored": None,
    "epanechnikov": 1.0,
    "uniform": 2 * math.pi,
}
