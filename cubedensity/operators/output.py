"""What is done with a cube: views, rankings, connected hot spots, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubedensity.operators.relational import VOXEL
from cubedensity.plans.durable import durable


def pyramid(cube: DataFrame, sizes: tuple[int, ...] = (1, 2, 4)) -> DataFrame:
    """Masses at several voxel sizes: ``(size, vx, vy, vt, hits, mass)``."""
    each = cube.select("*", F.explode(F.array(*map(F.lit, sizes))).alias("size"))
    keys = [F.floor(F.col(v) / F.col("size")).cast("int").alias(v) for v in VOXEL]
    return each.groupBy("size", *keys).agg(F.sum("hits").alias("hits"), F.sum("mass").cast(dict(cube.dtypes)["mass"]).alias("mass"))


def slice_at(cube: DataFrame, vt: int) -> DataFrame:
    return cube.filter(F.col("vt") == vt).drop("vt")


def matrix(cube: DataFrame, columns: int) -> DataFrame:
    """A row for each (vt, vy), a column for each vx: hits."""
    return cube.groupBy("vt", "vy").pivot("vx", list(range(columns))).agg(F.sum("hits"))


def top(cube: DataFrame, k: int, skip: int = 0) -> DataFrame:
    return cube.orderBy(F.desc("mass"), *VOXEL).offset(skip).limit(k)


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Mass of the first less that of the second, over voxels of either."""
    both = a.select(*VOXEL, F.col("mass").alias("p")).join(b.select(*VOXEL, F.col("mass").alias("q")), list(VOXEL), "full")
    return both.select(*VOXEL, (F.coalesce("p", F.lit(0)) - F.coalesce("q", F.lit(0))).alias("change"))


def moving_mean(cube: DataFrame, reach: int) -> DataFrame:
    """Sum of masses over the rows around each voxel of its column, along time."""
    w = Window.partitionBy("vx", "vy").orderBy("vt").rowsBetween(-reach, reach)
    return cube.withColumn("around", F.sum("mass").over(w))


def running_share(cube: DataFrame) -> DataFrame:
    """Running mass of the voxels from the heaviest on, exact without a global window.

    Sums are decimals; they are returned as BIGINT where the last of them fits one, as DECIMAL(38) beyond. Voxels are dealt into ranges of the order, which hold about as many each even where masses are equal; only the sums of the
    ranges meet in one task, one row a range.
    """
    order = [F.desc("mass"), *VOXEL]
    ranged = durable(cube.select(*VOXEL, "mass").repartitionByRange(*order).withColumn("part", F.spark_partition_id()))
    wide = F.col("mass").cast("decimal(38,0)")
    sums = ranged.groupBy("part").agg(F.sum(wide).cast("decimal(38,0)").alias("s"))
    total = sums.agg(F.sum("s")).first()[0] or 0
    kind = "bigint" if total < 1 << 63 else "decimal(38,0)"
    before = sums.withColumn("before", F.sum("s").over(Window.orderBy("part")) - F.col("s")).drop("s")
    inside = Window.partitionBy("part").orderBy(*order)
    return ranged.withColumn("inside", F.sum(wide).over(inside.rowsBetween(Window.unboundedPreceding, 0))).join(F.broadcast(before), "part").select(
        *VOXEL, "mass", (F.col("inside") + F.col("before")).cast(kind).alias("running")
    )


def hot_spots(cube: DataFrame, level: int, most_rounds: int = 200) -> DataFrame:
    """``(vx, vy, vt, label)``: voxels of at least ``level``, labelled by the least voxel they connect to (26 neighbours)."""
    hot = durable(cube.filter(F.col("mass") >= level).select(*VOXEL))
    key = lambda x, y, t: (x.cast("long") * (1 << 42)) + (y.cast("long") * (1 << 21)) + t
    nodes = durable(hot.select(*VOXEL, key(*map(F.col, VOXEL)).alias("id")))
    steps = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.lit(k).alias("k")) for i in (-1, 0, 1) for j in (-1, 0, 1) for k in (-1, 0, 1)))
    near = nodes.select("id", F.explode(steps).alias("s"), *VOXEL).select("id", key(F.col("vx") + F.col("s.i"), F.col("vy") + F.col("s.j"), F.col("vt") + F.col("s.k")).alias("other"))
    edges = durable(near.join(nodes.select(F.col("id").alias("other")), "other", "left_semi"))
    labels = durable(nodes.select("id", F.col("id").alias("label")))
    for _ in range(most_rounds):
        spread = edges.join(labels.withColumnRenamed("id", "other"), "other").groupBy("id").agg(F.min("label").alias("label"))
        # follow the label's own label as well, so that chains halve
        jumped = spread.join(labels.select(F.col("id").alias("label"), F.col("label").alias("further")), "label").select("id", F.least("label", "further").alias("label"))
        new = durable(jumped)
        if new.join(labels.withColumnRenamed("label", "old"), "id").filter("label <> old").isEmpty():
            return nodes.join(new, "id").select(*VOXEL, "label")
        labels = new
    raise RuntimeError("hot spots did not settle")


def write_cube(cube: DataFrame, path: str, slab: int = 16, kind: str = "parquet") -> None:
    """Cube partitioned by slabs of time, voxels of a column together."""
    out = cube.withColumn("slab", F.floor(F.col("vt") / slab).cast("int"))
    out.repartition("slab", "vx").sortWithinPartitions("slab", "vx", "vy", "vt").write.partitionBy("slab").mode("overwrite").format(kind).save(path)


def write_bucketed(cube: DataFrame, table: str, buckets: int = 8) -> None:
    """Cube as a table bucketed by column, so that joins of cubes on columns need no shuffle."""
    cube.write.mode("overwrite").bucketBy(buckets, "vx", "vy").sortBy("vt").saveAsTable(table)


def write_slices(cube: DataFrame, path: str) -> None:
    cube.withColumn("slice", F.col("vt")).write.partitionBy("slice").mode("overwrite").option("header", True).csv(path)
