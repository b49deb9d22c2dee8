"""Streams of events: windows, deduplication, interval joins, and cubes that are kept up to date.

Every ``run_*`` helper drains what is there (``availableNow``) into a folder of the shared store and returns the rows.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.operators.relational import merge_cubes, scatter
from cubedensity.plans.durable import shared_folder
from cubedensity.sources.ingest import event_view, inside, snap
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions


def folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def read_events(spark: SparkSession, base: str, name: str = "events", files_per_trigger: int | None = None) -> DataFrame:
    """Parquet files of events as a stream; timestamps in the session's zone, so that watermarks apply.

    The table may be one file or a folder of files: it is named by a pattern, since a stream source takes no single file.
    """
    schema = spark.read.parquet(f"{base}/{name}.parquet").schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(f"{base}/{name}.parque[t]").withColumn("ts", F.col("ts").cast("timestamp"))


def run_append(stream: DataFrame) -> DataFrame:
    """Rows of a stream in append mode."""
    spark, at = stream.sparkSession, folder(stream.sparkSession)
    query = stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start(f"{at}/rows")
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/rows")


def run_complete(stream: DataFrame) -> DataFrame:
    """Final state of an aggregate in complete mode; each trigger replaces the rows of the last."""
    spark, at = stream.sparkSession, folder(stream.sparkSession)

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/rows")

    query = stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/rows")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    return _windowed(events, F.window("ts", size))


def sliding(events: DataFrame, size: str = "7 days", step: str = "1 day") -> DataFrame:
    """A window that moves is a temporal bandwidth that moves, for the uniform kernel."""
    return _windowed(events, F.window("ts", size, step))


def _windowed(events: DataFrame, window) -> DataFrame:
    found = events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.floor(F.col("value") * 100 + 0.5).cast("long")).alias("cents"))
    return found.select(F.unix_micros("w.start").alias("opens"), F.unix_micros("w.end").alias("closes"), "event_type", "n", "cents")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    found = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return found.select(F.unix_micros("w.start").alias("opens"), F.unix_micros("w.end").alias("closes"), "user_id", "n")


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Repeated reports of an event dropped as long as they come within the delay."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def closed_slabs(events: DataFrame, slab: str, bandwidth: str) -> DataFrame:
    """Counts of slabs that no later event can change: events later than the bandwidth are left out."""
    found = events.withWatermark("ts", bandwidth).groupBy(F.window("ts", slab).alias("w")).agg(F.count("*").alias("n"))
    return found.select(F.unix_micros("w.start").alias("opens"), "n")


def run_late(spark: SparkSession, events: DataFrame, first: str, slab: str, bandwidth: str) -> DataFrame:
    """Closed slabs of a stream whose rows come in two parts, those of a condition first: ``opens, n``, and in ``late_slabs``
    how many slabs rows came for after they had closed (counted by task, of which a small file has one)."""
    at = folder(spark)
    kept = events.select("event_id", "ts")
    # lateness is judged by the watermark of the trigger before the last, so an empty trigger goes before the late rows
    for k, part in enumerate((kept.filter(first), kept.limit(0), kept.filter(f"not ({first})"), kept.limit(0))):
        part.coalesce(1).write.mode("append").parquet(f"{at}/in/{k}")
    stream = spark.readStream.schema(kept.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{at}/in").withColumn("ts", F.col("ts").cast("timestamp"))
    query = closed_slabs(stream, slab, bandwidth).writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start(f"{at}/rows")
    query.awaitTermination()
    late = sum(int(s["numRowsDroppedByWatermark"]) for p in query.recentProgress for s in p["stateOperators"])
    return spark.read.schema("opens bigint, n bigint").parquet(f"{at}/rows").withColumn("late_slabs", F.lit(late).cast("bigint"))


def neighbours(a: DataFrame, b: DataFrame, reach: str = "1 hour") -> DataFrame:
    """Pairs of events of one user within ``reach``: two streams joined by an interval."""
    left = a.select(F.col("event_id").alias("first"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", reach)
    right = b.select(F.col("event_id").alias("second"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", reach)
    near = F.expr(f"u1 = u2 and first < second and t2 between t1 - interval {reach} and t1 + interval {reach}")
    return left.join(right, near).select("first", "second")


def on_lattice(events: DataFrame, grid: GridSpec, users: int) -> DataFrame:
    """Events of the stream table on a lattice; the largest user is declared, as a stream has none."""
    view = event_view(events, "event_id", "user_id", "least(cast(floor(value * 100 + 0.5) as bigint), 39999)", "unix_micros(ts) - 1704067200000000")
    return inside(snap(view, grid, users, 40_000, 30 * 86_400_000_000), grid, PlanOptions())


def live_cube(events: DataFrame, grid: GridSpec, bw: Bandwidth, users: int) -> DataFrame:
    """Standing cube: the event-driven method over a stream, masses summed in the state store."""
    return scatter(on_lattice(events, grid, users), grid, bw)


def run_merged(events: DataFrame, grid: GridSpec, bw: Bandwidth, users: int, slab: int = 8, keep_back: int | None = None) -> DataFrame:
    """Cube kept as versions of slabs of time: each trigger adds the cube of its own events to the slabs that they reach.

    Version k of a slab is a function of its version before and trigger k alone, so a trigger that runs again writes the same;
    only slabs that a trigger's events reach are read and written, and the version before the last is dropped, since no
    trigger that can run again needs it. With ``keep_back``, in voxels of time, state expires: slabs that end more than the
    bandwidth and that far before the newest event are closed, stay as they are, and later events for them are left out.
    """
    spark, at = events.sparkSession, folder(events.sparkSession)
    versions: dict[int, list[int]] = {}  # of each slab; bounded by the slabs of the grid
    newest = -1
    fs = spark._jvm.org.apache.hadoop.fs.Path(at).getFileSystem(spark._jsc.hadoopConfiguration())

    def fold(batch: DataFrame, epoch: int) -> None:
        nonlocal newest
        ready = on_lattice(batch, grid, users).persist()
        last = ready.agg(F.max("t")).first()[0]
        newest = max(newest, -1 if last is None else last // grid.sub)
        new = scatter(ready, grid, bw).withColumn("slab", F.floor(F.col("vt") / slab).cast("int"))
        if keep_back is not None:
            new = new.filter((F.col("slab") + 1) * slab > newest - keep_back - bw.whole[1])
        new.write.mode("overwrite").partitionBy("slab").parquet(f"{at}/new-{epoch}")
        made = spark.read.schema(new.schema).parquet(f"{at}/new-{epoch}")
        for k in sorted(r["slab"] for r in made.select("slab").distinct().collect()):
            mine = made.filter(F.col("slab") == k).drop("slab")
            before = [v for v in versions.get(k, []) if v != epoch]
            if before:
                mine = merge_cubes(spark.read.parquet(f"{at}/slab-{k}/v{before[-1]}"), mine)
            mine.write.mode("overwrite").parquet(f"{at}/slab-{k}/v{epoch}")
            for v in before[:-1]:
                fs.delete(spark._jvm.org.apache.hadoop.fs.Path(f"{at}/slab-{k}/v{v}"), True)
            versions[k] = [*before[-1:], epoch]
        ready.unpersist()

    query = events.writeStream.foreachBatch(fold).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    paths = [f"{at}/slab-{k}/v{v[-1]}" for k, v in sorted(versions.items())]
    schema = "vx int, vy int, vt int, hits bigint, mass bigint"
    return spark.read.schema(schema).parquet(*paths) if paths else spark.createDataFrame([], schema)
