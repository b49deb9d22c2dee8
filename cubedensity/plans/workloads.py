"""The experiment workloads, numbered as the reported instances are, on the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from cubedensity.operators.density import cube, default_tiles
from cubedensity.operators.tiles import zero_blocks
from cubedensity.plans import measures
from cubedensity.sources.sets import events
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec


@dataclass(frozen=True)
class Workload:
    name: str
    set: str
    check: tuple[int, int, int]
    check_bw: tuple[int, int]
    bench: tuple[int, int, int]
    bench_bw: tuple[int, int]
    copies: int = 1
    long: bool = False

    def grid(self, bench: bool = False) -> GridSpec:
        # bench masses are doubles; fewer lattice steps keep them exact for longer
        return GridSpec(*(self.bench if bench else self.check), sub=4 if bench else 16)

    def bw(self, bench: bool = False) -> Bandwidth:
        return Bandwidth(*(self.bench_bw if bench else self.check_bw))

    def events(self, spark: SparkSession, sf_dir: str, bench: bool = False) -> DataFrame:
        return events(spark, sf_dir, self.set, self.grid(bench), self.copies if bench else 1)

    def cube(self, spark: SparkSession, sf_dir: str, method: str = "auto", bench: bool = False, **more) -> DataFrame:
        options = PlanOptions(mass="double" if bench else "long")
        return cube(self.events(spark, sf_dir, bench), self.grid(bench), self.bw(bench), method, options, **more)


def _w(k, name, check, check_bw, bench, bench_bw, copies=1, long=False):
    return Workload(f"w{k:02d}", name, check, check_bw, bench, bench_bw, copies, long)


WORKLOADS = [
    _w(1, "CITY", (37, 48, 104), (1, 1), (148, 194, 731), (3, 1)),
    _w(2, "CITY", (37, 48, 104), (6, 1), (148, 194, 731), (25, 1)),
    _w(3, "CITY", (49, 64, 73), (1, 1), (294, 386, 731), (2, 1)),
    _w(4, "CITY", (49, 64, 73), (8, 1), (294, 386, 731), (50, 1)),
    _w(5, "CITY", (49, 64, 73), (8, 2), (294, 386, 731), (50, 14), long=True),
    _w(6, "POSTS", (27, 13, 84), (2, 3), (131, 61, 84), (2, 3)),
    _w(7, "POSTS", (33, 15, 42), (2, 2), (326, 151, 84), (5, 3)),
    _w(8, "POSTS", (33, 15, 42), (3, 4), (326, 151, 84), (12, 7)),
    _w(9, "POSTS", (33, 15, 42), (5, 7), (326, 151, 84), (25, 14), long=True),
    _w(10, "POSTS", (65, 30, 14), (4, 1), (1300, 600, 84), (20, 3), long=True),
    _w(11, "POSTS", (65, 30, 14), (2, 1), (1300, 600, 84), (10, 3)),
    _w(12, "BIRDS", (24, 62, 180), (1, 1), (117, 308, 720), (1, 1)),
    _w(13, "BIRDS", (24, 62, 180), (2, 3), (117, 308, 720), (2, 3)),
    _w(14, "BIRDS", (30, 80, 120), (2, 3), (233, 615, 1440), (2, 3)),
    _w(15, "BIRDS", (30, 80, 120), (4, 7), (233, 615, 1440), (4, 7)),
    _w(16, "BIRDS", (36, 96, 90), (3, 3), (581, 1536, 2880), (5, 7)),
    _w(17, "BIRDS", (36, 96, 90), (4, 5), (581, 1536, 2880), (10, 21), long=True),
    _w(18, "WORLD", (18, 36, 61), (1, 1), (179, 361, 833), (2, 3), 2),
    _w(19, "WORLD", (18, 36, 61), (2, 2), (179, 361, 833), (6, 5)),
    _w(20, "WORLD", (22, 45, 40), (2, 1), (445, 900, 833), (5, 3)),
    _w(21, "WORLD", (22, 45, 40), (4, 2), (445, 900, 833), (15, 5), long=True),
]
BY_NAME = {w.name: w for w in WORKLOADS}

#: grids of the reported instances, for the memory of private cubes
REPORTED = {
    "city_low": (148, 194, 728), "city_high": (294, 386, 728), "posts_low": (131, 61, 84), "posts_high": (651, 301, 84),
    "posts_very_high": (6501, 3001, 84), "birds_low": (117, 308, 851), "birds_middle": (233, 615, 1985), "birds_high": (581, 1536, 5951),
    "world_low": (357, 721, 2435), "world_high": (1781, 3601, 2435),
}


FAMILIES = {f: [w.name for w in WORKLOADS if w.set == s] for f, s in (("city", "CITY"), ("posts", "POSTS"), ("birds", "BIRDS"), ("world", "WORLD"))}
#: one workload of each family, with wide cylinders where it has some
CLASSES = ("w02", "w08", "w13", "w19")
SEQUENTIAL = ("voxel_scan", "block_scan", "scatter", "disk_scatter", "bar_scatter", "product_scatter")


def compare_sequential(spark: SparkSession, sf_dir: str, names, methods=SEQUENTIAL) -> list[tuple[str, str, float]]:
    """Seconds of the sequential methods, each a whole run without output, on every workload."""
    return [(w, m, measures.seconds(BY_NAME[w].cube(spark, sf_dir, m))) for w in names for m in methods]


def zero_and_compute(spark: SparkSession, sf_dir: str, names) -> list[tuple[str, float, float, float]]:
    """(workload, seconds of making all arrays, seconds of the whole dense cube, share of the first)."""
    out = []
    for n in names:
        w = BY_NAME[n]
        tiles = default_tiles(w.grid(), w.bw(), spark.sparkContext.defaultParallelism)
        zero = measures.seconds(zero_blocks(spark, w.grid(), tiles))
        whole = measures.seconds(w.cube(spark, sf_dir, "tile_clip", tiles=tiles, emit="blocks"))
        out.append((n, zero, whole, zero / (zero + whole)))
    return out


def over_decomposition(spark: SparkSession, sf_dir: str, names=CLASSES, counts=(1, 2, 4, 8)) -> list[tuple[str, int, float]]:
    """(workload, tiles an axis, seconds of clipped tiles)."""
    return [(n, k, measures.seconds(BY_NAME[n].cube(spark, sf_dir, "tile_clip", tiles=TileSpec(k, k, k)))) for n in names for k in counts]


def parallel_methods(spark: SparkSession, sf_dir: str, name: str = "w06", counts=(2, 4, 8)) -> list[tuple[str, int, float]]:
    """(method, tiles an axis, seconds) of the parallel methods."""
    w = BY_NAME[name]
    out = [("replica_sum", 0, measures.seconds(w.cube(spark, sf_dir, "replica_sum")))]
    for m in ("tile_clip", "parity_sets", "loadaware_sets", "replicated_sets"):
        out += [(m, k, measures.seconds(w.cube(spark, sf_dir, m, tiles=TileSpec(k, k, k)))) for k in counts]
    return out


def best_methods(spark: SparkSession, sf_dir: str, names, counts=(4,)) -> list[tuple[str, str, int, float, str]]:
    """(workload, best method, tiles, seconds, method that the model chooses)."""
    from cubedensity.plans.chooser import choose

    out = []
    for n in names:
        w = BY_NAME[n]
        m, k, s = min(parallel_methods(spark, sf_dir, n, counts), key=lambda r: r[2])
        out.append((n, m, k, s, choose(w.events(spark, sf_dir), w.grid(), w.bw(), spark.sparkContext.defaultParallelism).method))
    return out
