"""Cost and accuracy measures: closed forms on the driver, counts as aggregates."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubedensity.functions.kernels import in_bar, in_disk
from cubedensity.operators import dag
from cubedensity.operators.relational import VOXEL, _long, box, centre
from cubedensity.operators.replicas import replica_bytes
from cubedensity.operators.tiles import owner, tile_index, voxel_of
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, TileSpec, constant

FLOPS = 40  # of one kernel evaluation, as the text puts it


def _ready(events, grid, bw, options):
    return inside(events, grid, options, bw.lattice(grid))


def box_sizes(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """Voxels of each event's clipped box, disk and bar: ``(event_id, x, y, t, n_place, n_disk, n_time, n_bar)``."""
    hs, half = bw.whole
    hx, ht = map(_long, bw.lattice(grid))
    xs, ys, ts = (box(c, h, g, grid.sub) for c, h, g in zip("xyt", (hs, hs, half), grid.shape))
    at = lambda v, c: centre(v, grid, options) - F.col(c)
    disk = F.aggregate(
        xs, F.lit(0).cast("long"), lambda n, vx: n + F.size(F.filter(ys, lambda vy: in_disk(at(vx, "x"), at(vy, "y"), hx))).cast("long")
    )
    bar = F.size(F.filter(ts, lambda vt: in_bar(options.edge, at(vt, "t"), ht))).cast("long")
    return _ready(events, grid, bw, options).select(
        "event_id", "x", "y", "t", (F.size(xs).cast("long") * F.size(ys)).alias("n_place"), disk.alias("n_disk"), F.size(ts).cast("long").alias("n_time"), bar.alias("n_bar")
    )


def distance_tests(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """One row: tests of the voxel scan, of the block scan and of event-driven methods."""
    hx, ht = bw.lattice(grid)
    o, s = options.offset(grid), grid.sub
    # the block scan tests a voxel against the events of the blocks around it: 3 blocks along each axis
    def near(c, h, g):
        b = F.floor(F.col(c) / h)
        low, high = (b - 1) * h, (b + 2) * h - 1  # lattice stretch of the three blocks
        first = F.greatest(F.lit(0), F.ceil((low - o) / s))
        last = F.least(F.lit(g - 1), F.floor((high - o) / s))
        return F.greatest(F.lit(0), last - first + 1).cast("long")

    sizes = box_sizes(events, grid, bw, options)
    return sizes.agg(
        (F.count("*") * grid.cells).alias("voxel_scan"),
        F.sum(near("x", hx, grid.gx) * near("y", hx, grid.gy) * near("t", ht, grid.gt)).alias("block_scan"),
        F.sum(F.col("n_place") * F.col("n_time")).alias("event_driven"),
    )


def kernel_evaluations(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """``(method, spatial, temporal)``: evaluations of each factor that the event-driven methods make."""
    n_disk, n_bar = F.col("n_disk"), F.col("n_bar")
    total = box_sizes(events, grid, bw, options).agg(F.sum(n_disk * n_bar).alias("full"), F.sum(n_disk).alias("disk"), F.sum(n_bar).alias("bar"))
    rows = F.array(
        *(
            F.struct(F.lit(m).alias("method"), F.col(a).alias("spatial"), F.col(b).alias("temporal"))
            for m, a, b in (("scatter", "full", "full"), ("disk_scatter", "disk", "full"), ("bar_scatter", "full", "bar"), ("product_scatter", "disk", "bar"))
        )
    )
    return total.select(F.inline(rows))


def flops(n: int, bw: Bandwidth) -> int:
    """Operations of evaluating the kernel at every voxel of every event's box."""
    hs, ht = bw.whole
    return FLOPS * n * (2 * hs) ** 2 * (2 * ht)


def memory_table(spark, cases: list[tuple[str, GridSpec]], copies_: int, width: int = 4) -> DataFrame:
    rows = [(name, g.cells, g.bytes(width), replica_bytes(g, copies_, width)) for name, g in cases]
    return spark.createDataFrame(rows, "name string, cells bigint, cube_bytes bigint, copies_bytes bigint")


def replication(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions()) -> DataFrame:
    """One row: events, copies, and the extra disks and bars that cuts make.

    A cut in time repeats the disk in each part, a cut in space repeats the bar.
    """
    hs, ht = bw.whole
    spread = [
        F.floor(F.least(voxel_of(F.col(c), grid.sub) + h, F.lit(g - 1)).cast("long") * n / g) - F.floor(F.greatest(voxel_of(F.col(c), grid.sub) - h, F.lit(0)).cast("long") * n / g) + 1
        for c, h, g, n in zip("xyt", (hs, hs, ht), grid.shape, tiles.counts)
    ]
    rows = _ready(events, grid, bw, options).select(*(s.alias(k) for s, k in zip(spread, "abc")))
    a, b, c = map(F.col, "abc")
    return rows.agg(F.count("*").alias("events"), F.sum(a * b * c).alias("copies"), F.sum(c - 1).alias("extra_disks"), F.sum(a * b - 1).alias("extra_bars"))


def work_units(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions()) -> DataFrame:
    """Overhead of clipped tiles without a clock: table entries and products, alone and with tiles."""
    return table_entries(events, grid, bw, options).join(tiled_entries(events, grid, bw, tiles, options))


def table_entries(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """One row: entries of both tables and products, without tiles. Bars are sized once a time and disks once a place."""
    ready = _ready(events, grid, bw, options)
    zero = F.lit(0).cast("long")
    one = lambda *at: box_sizes(ready.select(F.lit(0).cast("long").alias("event_id"), *(c if c in at else zero.alias(c) for c in "xyt")).distinct(), grid, bw, options)
    bars = one("t").select("t", "n_time", "n_bar")
    places = ready.join(bars, "t").groupBy("x", "y").agg(F.count("*").alias("n"), F.sum("n_time").alias("times"), F.sum("n_bar").alias("bars"))
    disks = one("x", "y").select("x", "y", "n_place", "n_disk")
    return places.join(disks, ["x", "y"]).agg(F.sum(F.col("n") * F.col("n_place") + F.col("times")).alias("entries"), F.sum(F.col("n_disk") * F.col("bars")).alias("products"))


def tiled_entries(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions()) -> DataFrame:
    """One row: entries of both tables with clipped tiles.

    The parts into which tiles cut an event's box add up to the box along each axis, so no copies are made to count them:
    its disk is tabulated once for each part in time, its bar once for each part in space.
    """
    hs, half = bw.whole
    ends = []
    for c, g, h in zip("xyt", grid.shape, (hs, hs, half)):
        v = voxel_of(F.col(c), grid.sub)
        ends.append((F.greatest(v - h, F.lit(0)), F.least(v + h, F.lit(g - 1))))
    nx, ny, nt = ((high - low + 1).cast("long") for low, high in ends)
    na, nb, nc = ((tile_index(high, n, g) - tile_index(low, n, g) + 1).cast("long") for (low, high), n, g in zip(ends, tiles.counts, grid.shape))
    met = reduce(lambda p, q: p & q, (low <= high for low, high in ends))
    return _ready(events, grid, bw, options).agg(F.sum(F.when(met, nx * ny * nc + na * nb * nt).otherwise(0)).cast("long").alias("tiled_entries"))


def imbalance(loads: DataFrame, tiles: TileSpec) -> DataFrame:
    """One row over ``loads(tile_id, load)``: heaviest load, its share, total, tiles in use, and the numerator of the Gini
    coefficient over all tiles, empty ones included: 2 * sum(rank * load) - (tiles + 1) * total, over tiles * total.

    Tiles of one load share their ranks, so only the distinct loads meet in one task, at most as many as tiles may be.
    """
    dag.check_tiles(tiles)
    each = loads.groupBy("load").agg(F.count("*").alias("n"))
    up_to = Window.partitionBy().orderBy("load").rowsBetween(Window.unboundedPreceding, 0)
    ranked = each.select("load", "n", (F.sum("n").over(up_to) - F.col("n") + tiles.total - F.sum("n").over(Window.partitionBy())).alias("before"))
    total = F.sum(F.col("load") * F.col("n"))
    ranks = F.col("n") * F.col("before") + F.call_function("div", F.col("n") * (F.col("n") + 1), F.lit(2))
    return ranked.agg(
        F.max("load").alias("heaviest"), total.alias("total"), F.sum("n").alias("used"), (2 * F.sum(F.col("load") * ranks) - (tiles.total + 1) * total).alias("gini_over"), (total * tiles.total).alias("gini_under")
    )


def conflicts(events: DataFrame, grid: GridSpec, bw: Bandwidth, tiles: TileSpec, options: PlanOptions = PlanOptions()) -> DataFrame:
    """Voxels that two tiles of one parity set both write: none, if the tiles are safe."""
    hs, half = bw.whole
    rows = owner(_ready(events, grid, bw, options), grid, tiles)
    rows = rows.select(
        "tile_id", (F.pmod("a", F.lit(2)) * 4 + F.pmod("b", F.lit(2)) * 2 + F.pmod("c", F.lit(2))).alias("color"), *(voxel_of(F.col(c), grid.sub).alias(v) for c, v in zip("xyt", VOXEL))
    ).distinct()
    for v, h, g in zip(VOXEL, (hs, hs, half), grid.shape):
        at = F.col(v)
        rows = rows.select(*(c for c in rows.columns if c != v), F.explode(F.sequence(F.greatest(at - h, F.lit(0)), F.least(at + h, F.lit(g - 1)))).alias(v)).distinct()
    return rows.groupBy("color", *VOXEL).agg(F.count_distinct("tile_id").alias("tiles")).filter("tiles > 1")


def critical_share(loads: dict[int, int], tiles: TileSpec, weight: str = "own") -> dict[str, float]:
    """Share of the critical path under parity and load-aware colors."""
    w = dag.weights_of(loads, tiles, weight)
    total = sum(w.values()) or 1
    colors = {"parity": dag.parity_colors(tiles), "load": dag.greedy_colors(loads, tiles)}
    return {k: dag.critical_path(c, w, tiles).length / total for k, c in colors.items()}


def zero_fill_cap(init: float, compute: float, init_speedup: float) -> float:
    """Best total speedup if only the compute part vanished."""
    return (init + compute) / (init / init_speedup)


def total_mass(cube: DataFrame, n: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """One row: the sum of all densities over one event's volume of a voxel, times one: the integral of the cube."""
    return cube.agg(F.sum(F.col("mass").cast("decimal(38,0)")).alias("mass")).select((F.col("mass").cast("double") * (F.lit(constant(grid, bw, options)) / n.scalar().cast("double"))).alias("total_mass"))


def identity(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: how many rows of each cube the other lacks; zero and zero if they are equal."""
    return a.exceptAll(b).agg(F.count("*").alias("only_first")).join(b.exceptAll(a).agg(F.count("*").alias("only_second")))


def lattice_error(fine: DataFrame, coarse: DataFrame) -> DataFrame:
    """Largest and mean difference of two cubes with densities, over voxels that either touches."""
    both = fine.select(*VOXEL, F.col("density").alias("p")).join(coarse.select(*VOXEL, F.col("density").alias("q")), list(VOXEL), "full")
    gap = F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))
    return both.agg(F.max(gap).alias("largest"), F.avg(gap).alias("mean"), F.max(F.greatest(F.coalesce("p", F.lit(0.0)), F.coalesce("q", F.lit(0.0)))).alias("peak"))


def seconds(df: DataFrame) -> float:
    """Time to compute all rows of a plan, thrown away."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def throughput(events: DataFrame, cube: DataFrame) -> dict[str, float]:
    """Events and voxel updates a second."""
    took = seconds(cube)
    n, updates = events.count(), cube.agg(F.sum("hits")).first()[0] or 0
    return {"seconds": took, "events": n / took, "updates": updates / took}
