"""From tables to events on the integer lattice: ``(event_id, x, y, t, w)``, all longs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.spec import GridSpec, PlanOptions

EVENTS = "event_id bigint, x bigint, y bigint, t bigint, w bigint"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def event_view(df: DataFrame, event_id: str, x: str, y: str, t: str, w: str = "1") -> DataFrame:
    """Five columns by SQL expressions over any table; the scan reads only what they name."""
    return df.select(*(F.expr(e).alias(n) for n, e in (("event_id", event_id), ("x", x), ("y", y), ("t", t), ("w", w))))


def snap(df: DataFrame, grid: GridSpec, x_den, y_den, t_den) -> DataFrame:
    """Fractions ``num/den`` of the domain, given as columns x, y, t of whole numerators, to lattice steps.

    A denominator is a number, a Column, or a one-value DataFrame (a scalar subquery, as for a largest key).
    """

    def step(name: str, den, cells: int) -> Column:
        den = F.lit(den).cast("long") if isinstance(den, int) else den.scalar() if isinstance(den, DataFrame) else den
        num = F.col(name) * (cells * grid.sub)
        return F.when(num >= 0, F.call_function("div", num, den))  # whole quotient, exact where a double would round

    return df.select(
        "event_id", step("x", x_den, grid.gx).alias("x"), step("y", y_den, grid.gy).alias("y"), step("t", t_den, grid.gt).alias("t"), "w"
    )


def inside(events: DataFrame, grid: GridSpec, options: PlanOptions, reach: tuple[int, int] = (0, 0)) -> DataFrame:
    """Events of the domain under an outside rule: dropped, kept as far as they reach, or an error."""
    s = grid.sub
    hx, ht = reach if options.outside == "halo" else (0, 0)
    ok = F.lit(True)
    for name, cells, h in (("x", grid.gx, hx), ("y", grid.gy, hx), ("t", grid.gt, ht)):
        ok = ok & F.col(name).between(-h, cells * s - 1 + h)
    ok = F.coalesce(ok, F.lit(False))
    if options.outside == "error":
        return events.filter(ok | F.raise_error(F.lit("an event lies outside the grid")).cast("boolean"))
    return events.filter(ok)


def extents(events: DataFrame) -> DataFrame:
    """One row: least and largest coordinates and the number of events, by one aggregate."""
    return events.agg(*(f(c).alias(f"{n}_{c}") for c in "xyt" for n, f in (("min", F.min), ("max", F.max))), F.count("*").alias("n"))


def collapse(events: DataFrame) -> DataFrame:
    """Events at one lattice place merged, with the sum of their weights; exact for masses, ``n`` keeps hits exact."""
    return events.groupBy("x", "y", "t").agg(F.min("event_id").alias("event_id"), F.sum("w").alias("w"), F.count("*").alias("n"))


def scale_up(events: DataFrame, copies: int, grid: GridSpec) -> DataFrame:
    """Each event ``copies`` times, the later ones moved by a few lattice steps that depend on id and copy only."""
    j = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
    moved = F.when(F.col("copy") == 0, F.col("x")).otherwise(
        F.greatest(F.lit(0).cast("long"), F.least(F.lit(grid.gx * grid.sub - 1).cast("long"), F.col("x") + F.pmod(F.col("event_id") * 31 + F.col("copy") * 17, F.lit(7)) - 3))
    )
    return events.select("*", j).select((F.col("event_id") * copies + F.col("copy")).alias("event_id"), moved.alias("x"), "y", "t", "w")


def reader(spark: SparkSession, kind: str, path: str, schema: str, **options) -> DataFrame:
    """Events from csv, json, orc, parquet or text files with a declared schema; bad records become nulls, and are kept
    in ``_bad`` if the schema names it."""
    if kind in ("csv", "json"):
        options = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_bad", **options}
    return spark.read.schema(schema).options(**options).format(kind).load(path)
