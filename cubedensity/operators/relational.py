"""Density methods as relational plans.

All methods give the same rows ``(vx, vy, vt, hits, mass)``: a voxel has a row if at least one event covers it; ``hits``
counts those events and ``mass`` is the sum of their integer kernel products, so results do not depend on order,
partitioning or method. ``normalise`` turns masses into densities.

Event-driven methods clip their boxes to the grid before rows are made. They create a row per covered voxel and event,
which is right for small jobs and for checking. Where events meet many voxels, the six sequential methods go over arrays
instead (``sequential``), with the same tests and evaluations.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubedensity.functions.kernels import in_bar, in_disk, spatial, temporal
from cubedensity.operators import sequential
from cubedensity.sources.ingest import inside
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions, constant

VOXEL = ("vx", "vy", "vt")
#: columns of voxels that the voxel-driven scan broadcasts at most
SENT_COLUMNS = 1_000_000
#: events of a block that its voxels meet in one share
CROWDED = 20_000


def _long(v) -> Column:
    return F.lit(v).cast("long")


def centre(voxel: str | Column, grid: GridSpec, options: PlanOptions) -> Column:
    """Sampling point of a voxel along an axis, in lattice steps."""
    v = F.col(voxel) if isinstance(voxel, str) else voxel
    return v.cast("long") * grid.sub + options.offset(grid)


def box(coordinate: str | Column, half: int | Column, cells: int, sub: int) -> Column:
    """Voxels within ``half`` voxels of an event along an axis, clipped to the grid."""
    c = F.col(coordinate) if isinstance(coordinate, str) else coordinate
    own = F.floor(c / sub).cast("int")  # coordinates are far below 2^53
    return span(F.greatest(own - half, F.lit(0)), F.least(own + half, F.lit(cells - 1)))


def span(low: Column, high: Column) -> Column:
    """The whole numbers from low to high; none if high is below low."""
    return F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<int>"))


def accumulate(terms: DataFrame, options: PlanOptions, *extra: str) -> DataFrame:
    """Sum of terms by voxel: partial sums, one shuffle, final sums."""
    kind = {"long": "bigint", "decimal": "decimal(38,0)", "double": "double"}[options.mass]
    return terms.groupBy(*extra, *VOXEL).agg(F.count("*").alias("hits"), F.sum(F.col("term").cast(kind)).cast(kind).alias("mass"))


def _ready(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> DataFrame:
    return inside(events, grid, options, bw.lattice(grid))


def _difference(grid: GridSpec, options: PlanOptions) -> tuple[Column, Column, Column]:
    return tuple(centre(v, grid, options) - F.col(c) for v, c in zip(VOXEL, "xyt"))


def _exact(c: Column, options: PlanOptions) -> Column:
    """Widen a factor where products would not fit a long."""
    return c.cast("decimal(19,0)") if options.mass == "decimal" else c.cast("double") if options.mass == "double" else c


def _terms(rows: DataFrame, grid, bw, options: PlanOptions, *extra: str) -> DataFrame:
    """Rows (event, voxel) -> those in the cylinder, with their kernel products."""
    hx, ht = map(_long, bw.lattice(grid))
    dx, dy, dt = _difference(grid, options)
    near = rows.filter(in_disk(dx, dy, hx) & in_bar(options.edge, dt, ht))
    ks, kt = spatial(options.kernel, dx, dy, hx), temporal(options.kernel, dt, ht)
    return near.select(*extra, *VOXEL, (_exact(ks, options) * _exact(kt, options) * _exact(F.col("w"), options)).alias("term"))


def dealt(events: DataFrame) -> DataFrame:
    """Events in as many partitions as there are workers, where their files make fewer."""
    workers = events.sparkSession.sparkContext.defaultParallelism
    if events.isStreaming or events.rdd.getNumPartitions() >= workers:
        return events
    return events.repartitionById(workers, F.pmod(F.xxhash64("event_id", "x", "y", "t"), F.lit(workers)).cast("int"))


def voxel_scan(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions(), limit: int | None = None) -> DataFrame:
    """The definition: every voxel looks at every event, by joins on inequalities alone.

    The voxels of a column share their test of the disk. Columns and times of the grid go to where the events are, of
    which there may be any number; with ``limit``, more than that are refused.
    """
    ready = _ready(events, grid, bw, options)
    if limit is not None and ready.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} events: use block_scan or an event-driven method")
    if sequential.many("voxel_scan", events, grid, bw, options):
        return sequential.over_arrays("voxel_scan", events, grid, bw, options)
    spark, i = events.sparkSession, F.col("id")
    columns = spark.range(grid.gx * grid.gy).select(F.floor(i / grid.gy).cast("int").alias("vx"), F.pmod(i, F.lit(grid.gy)).cast("int").alias("vy"))
    times = spark.range(grid.gt).select(i.cast("int").alias("vt"))
    hx, ht = map(_long, bw.lattice(grid))
    dx, dy, dt = _difference(grid, options)
    sent = F.broadcast if grid.gx * grid.gy <= SENT_COLUMNS else lambda rows: rows
    disk = dealt(ready).join(sent(columns), in_disk(dx, dy, hx))
    joined = disk.join(F.broadcast(times), in_bar(options.edge, dt, ht))
    return accumulate(_terms(joined, grid, bw, options), options)


def block_scan(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions(), crowded: int = CROWDED) -> DataFrame:
    """Voxel-driven, over blocks as large as the bandwidth: an equality join of the voxels of 27 blocks with the events of the middle one.

    Every event travels once, to its own block; only blocks that hold events have voxels. The events of a block are dealt
    out in shares of about ``crowded``, and its voxels meet each share, so that a crowded block is no single task.
    """
    if sequential.many("block_scan", events, grid, bw, options):
        return sequential.over_arrays("block_scan", events, grid, bw, options)
    hx, ht = bw.lattice(grid)
    axes = list(zip(VOXEL, "xyt", ("bx", "by", "bt"), (hx, hx, ht), grid.shape))
    blocks = [b for _, _, b, _, _ in axes]
    side = _ready(events, grid, bw, options).select("*", *(F.floor(F.col(c) / h).cast("int").alias(b) for _, c, b, h, _ in axes))
    held = side.groupBy(*blocks).agg(F.ceil(F.count("*") / crowded).cast("int").alias("shares"))
    share = F.pmod(F.xxhash64("event_id", "x", "y", "t"), F.col("shares")).cast("int").alias("share")
    side = side.join(held, blocks).select(*blocks, share, "x", "y", "t", "w")
    voxels = held.select("*", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("share"))
    o, s = options.offset(grid), grid.sub
    for v, _, b, h, n in axes:
        # voxels whose sampling point lies in the block or in one beside it
        low, high = F.ceil(((F.col(b).cast("long") - 1) * h - o) / s), F.ceil(((F.col(b).cast("long") + 2) * h - o) / s) - 1
        voxels = voxels.select("*", F.explode(span(F.greatest(low, F.lit(0)).cast("int"), F.least(high, F.lit(n - 1)).cast("int"))).alias(v))
    voxels = voxels.select(*blocks, "share", *VOXEL)
    return accumulate(_terms(side.join(voxels.hint("shuffle_hash"), [*blocks, "share"]), grid, bw, options), options)


def scatter(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions(), *extra: str) -> DataFrame:
    """Event-driven: each event visits the box around it, tests and evaluates both factors at every voxel."""
    if not extra and sequential.many("scatter", events, grid, bw, options):
        return sequential.over_arrays("scatter", events, grid, bw, options)
    hs, ht = bw.whole
    rows = dealt(_ready(events, grid, bw, options))
    rows = rows.select("*", F.explode(box("x", hs, grid.gx, grid.sub)).alias("vx")).select("*", F.explode(box("y", hs, grid.gy, grid.sub)).alias("vy"))
    rows = rows.select("*", F.explode(box("t", ht, grid.gt, grid.sub)).alias("vt"))
    return accumulate(_terms(rows, grid, bw, options, *extra), options, *extra)


def disk_scatter(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """The spatial factor once for each place of the disk, the temporal one at every voxel."""
    if sequential.many("disk_scatter", events, grid, bw, options):
        return sequential.over_arrays("disk_scatter", events, grid, bw, options)
    hs, half = bw.whole
    hx, ht = map(_long, bw.lattice(grid))
    dx, dy, dt = _difference(grid, options)
    rows = dealt(_ready(events, grid, bw, options))
    rows = rows.select("*", F.explode(box("x", hs, grid.gx, grid.sub)).alias("vx")).select("*", F.explode(box("y", hs, grid.gy, grid.sub)).alias("vy"))
    disk = rows.filter(in_disk(dx, dy, hx)).select("vx", "vy", "t", (_exact(spatial(options.kernel, dx, dy, hx), options) * _exact(F.col("w"), options)).alias("ks"))
    full = disk.select("*", F.explode(box("t", half, grid.gt, grid.sub)).alias("vt")).filter(in_bar(options.edge, dt, ht))
    return accumulate(full.select(*VOXEL, (F.col("ks") * _exact(temporal(options.kernel, dt, ht), options)).alias("term")), options)


def bar_scatter(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """The temporal factor once for each time of the bar, the spatial one at every voxel."""
    if sequential.many("bar_scatter", events, grid, bw, options):
        return sequential.over_arrays("bar_scatter", events, grid, bw, options)
    hs, half = bw.whole
    hx, ht = map(_long, bw.lattice(grid))
    dx, dy, dt = _difference(grid, options)
    rows = dealt(_ready(events, grid, bw, options))
    rows = rows.select("*", F.explode(box("t", half, grid.gt, grid.sub)).alias("vt")).filter(in_bar(options.edge, dt, ht))
    bar = rows.select("x", "y", "vt", (_exact(temporal(options.kernel, dt, ht), options) * _exact(F.col("w"), options)).alias("kt"))
    full = bar.select("*", F.explode(box("x", hs, grid.gx, grid.sub)).alias("vx")).select("*", F.explode(box("y", hs, grid.gy, grid.sub)).alias("vy"))
    full = full.filter(in_disk(dx, dy, hx))
    return accumulate(full.select(*VOXEL, (F.col("kt") * _exact(spatial(options.kernel, dx, dy, hx), options)).alias("term")), options)


def bar_table(grid: GridSpec, bw: Bandwidth, options: PlanOptions) -> Column:
    """The temporal invariant of an event as an array: times of the bar, each with its factor."""
    ht = _long(bw.lattice(grid)[1])
    at = lambda v: v.cast("long") * grid.sub + options.offset(grid) - F.col("t")
    times = F.filter(box("t", bw.whole[1], grid.gt, grid.sub), lambda vt: in_bar(options.edge, at(vt), ht))
    return F.transform(times, lambda vt: F.struct(vt.alias("vt"), _exact(temporal(options.kernel, at(vt), ht), options).alias("kt")))


def product_scatter(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """Both factors once per event: the bar as an array beside the event, the disk as its rows; voxels only take products."""
    if sequential.many("product_scatter", events, grid, bw, options):
        return sequential.over_arrays("product_scatter", events, grid, bw, options)
    hs, _ = bw.whole
    hx, _ = map(_long, bw.lattice(grid))
    dx, dy, _ = _difference(grid, options)
    rows = dealt(_ready(events, grid, bw, options)).select("x", "y", "w", bar_table(grid, bw, options).alias("bar"))
    rows = rows.select("*", F.explode(box("x", hs, grid.gx, grid.sub)).alias("vx")).select("*", F.explode(box("y", hs, grid.gy, grid.sub)).alias("vy"))
    disk = rows.filter(in_disk(dx, dy, hx)).select("bar", "vx", "vy", (_exact(spatial(options.kernel, dx, dy, hx), options) * _exact(F.col("w"), options)).alias("ks"))
    full = disk.select("vx", "vy", "ks", F.inline("bar"))
    return accumulate(full.select(*VOXEL, (F.col("ks") * F.col("kt")).alias("term")), options)


def two_pass(events: DataFrame, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """Bars summed for events at one place, then disks once per place and time; equal by distributivity."""
    hs, half = bw.whole
    hx, ht = map(_long, bw.lattice(grid))
    dx, dy, dt = _difference(grid, options)
    kind = {"long": "bigint", "decimal": "decimal(38,0)", "double": "double"}[options.mass]
    rows = _ready(events, grid, bw, options).select("*", F.explode(box("t", half, grid.gt, grid.sub)).alias("vt")).filter(in_bar(options.edge, dt, ht))
    bars = rows.groupBy("x", "y", "vt").agg(
        F.sum((_exact(temporal(options.kernel, dt, ht), options) * _exact(F.col("w"), options)).cast(kind)).cast(kind).alias("kt"), F.count("*").alias("n")
    )
    full = bars.select("*", F.explode(box("x", hs, grid.gx, grid.sub)).alias("vx")).select("*", F.explode(box("y", hs, grid.gy, grid.sub)).alias("vy"))
    full = full.filter(in_disk(dx, dy, hx))
    term = (F.col("kt") * _exact(spatial(options.kernel, dx, dy, hx), options)).cast(kind)
    return full.groupBy(*VOXEL).agg(F.sum("n").alias("hits"), F.sum(term).cast(kind).alias("mass"))


def bandwidth_sweep(events: DataFrame, grid: GridSpec, bandwidths: list[Bandwidth], options: PlanOptions = PlanOptions()) -> DataFrame:
    """Several bandwidths in one pass over the events: ``(bw, vx, vy, vt, hits, mass)``."""
    spark = events.sparkSession
    rows = [(i, *b.whole, *b.lattice(grid)) for i, b in enumerate(bandwidths)]
    table = spark.createDataFrame(rows, "bw int, hs int, half int, hx bigint, ht bigint")
    widest = Bandwidth(max(b.hs for b in bandwidths), max(b.ht for b in bandwidths))
    hx, ht = F.col("hx"), F.col("ht")
    dx, dy, dt = _difference(grid, options)
    full = _ready(events, grid, widest, options).crossJoin(F.broadcast(table))  # one row for each bandwidth asked for
    for v, c, half, cells in (("vx", "x", "hs", grid.gx), ("vy", "y", "hs", grid.gy), ("vt", "t", "half", grid.gt)):
        full = full.select("*", F.explode(box(c, F.col(half), cells, grid.sub)).alias(v))
    near = full.filter(in_disk(dx, dy, hx) & in_bar(options.edge, dt, ht))
    term = _exact(spatial(options.kernel, dx, dy, hx), options) * _exact(temporal(options.kernel, dt, ht), options) * _exact(F.col("w"), options)
    return accumulate(near.select("bw", *VOXEL, term.alias("term")), options, "bw")


def population(events: DataFrame, grid: GridSpec, block: int) -> DataFrame:
    """Events with ``n``, the number of events in their column of ``block`` x ``block`` voxels."""
    size = block * grid.sub
    keyed = events.select("*", F.floor(F.col("x") / size).alias("px"), F.floor(F.col("y") / size).alias("py"))
    counts = keyed.groupBy("px", "py").agg(F.count("*").alias("n"))
    return keyed.join(counts, ["px", "py"]).drop("px", "py")


def adaptive(events: DataFrame, grid: GridSpec, bw: Bandwidth, block: int, crowded: tuple[int, int], options: PlanOptions = PlanOptions()) -> DataFrame:
    """Bandwidth by local population: ``bw`` where a column holds ``crowded[1]`` events or more, twice and four times as
    wide in space where it holds fewer than that and fewer than ``crowded[0]``. Masses are in units of the widest kernel,
    so they stay whole numbers."""
    few, many = crowded
    factor = F.when(F.col("n") >= many, 1).when(F.col("n") >= few, 2).otherwise(4)
    wide = Bandwidth(bw.hs * 4, bw.ht)
    rows = population(_ready(events, grid, wide, options), grid, block).withColumn("f", factor)
    hx0, ht0 = bw.lattice(grid)
    hx, ht = (F.col("f") * hx0).cast("long"), _long(ht0)
    hs, half = bw.whole
    dx, dy, dt = _difference(grid, options)
    for v, c, h, cells in (("vx", "x", F.col("f") * hs, grid.gx), ("vy", "y", F.col("f") * hs, grid.gy), ("vt", "t", F.lit(half), grid.gt)):
        rows = rows.select("*", F.explode(box(c, h.cast("int"), cells, grid.sub)).alias(v))
    near = rows.filter(in_disk(dx, dy, hx) & in_bar(options.edge, dt, ht))
    # (4/f)^power brings numerator and area to the units of the widest disk
    power = {"printed": 6, "mirrored": 6, "epanechnikov": 4, "uniform": 2}[options.kernel]
    unit = F.when(F.col("f") == 1, _long(4**power)).when(F.col("f") == 2, _long(2**power)).otherwise(_long(1))
    term = _exact(spatial(options.kernel, dx, dy, hx), options) * _exact(temporal(options.kernel, dt, ht), options) * _exact(F.col("w"), options) * _exact(unit, options)
    return accumulate(near.select(*VOXEL, term.alias("term")), options)


def normalise(cube: DataFrame, n: DataFrame | int, grid: GridSpec, bw: Bandwidth, options: PlanOptions = PlanOptions()) -> DataFrame:
    """``cube`` with ``density``: the mass times one constant over the number of events (a number, or a one-value table)."""
    count = F.lit(n) if isinstance(n, int) else n.scalar()
    return cube.withColumn("density", F.col("mass").cast("double") * (F.lit(constant(grid, bw, options)) / count.cast("double")))


def with_zeros(cube: DataFrame, grid: GridSpec) -> DataFrame:
    """Every voxel of the grid; those that no event covers have zero hits and mass."""
    axis = lambda n: F.sequence(F.lit(0), F.lit(n - 1))
    voxels = cube.sparkSession.range(grid.gx).select(F.col("id").cast("int").alias("vx"), F.explode(axis(grid.gy)).alias("vy")).select("*", F.explode(axis(grid.gt)).alias("vt"))
    rest = [c for c in cube.columns if c not in VOXEL]
    kinds = dict(cube.dtypes)
    return voxels.join(cube, list(VOXEL), "left").select(*VOXEL, *(F.coalesce(c, F.lit(0).cast(kinds[c])).alias(c) for c in rest))


def merge_cubes(*cubes: DataFrame) -> DataFrame:
    """Cube of the union of disjoint event sets."""
    all_rows = reduce(DataFrame.unionByName, cubes)
    kind = dict(cubes[0].dtypes)["mass"]
    return all_rows.groupBy(*VOXEL).agg(F.sum("hits").alias("hits"), F.sum("mass").cast(kind).alias("mass"))


METHODS = {f.__name__: f for f in (voxel_scan, block_scan, scatter, disk_scatter, bar_scatter, product_scatter, two_pass)}
