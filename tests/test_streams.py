"""Streams drained over several triggers equal the batch result; late and repeated rows."""

from pyspark.sql import functions as F

from cubedensity.operators.relational import scatter
from cubedensity.spec import Bandwidth, GridSpec
from cubedensity.streaming import stream

GRID, BW = GridSpec(6, 6, 6), Bandwidth(1, 1)
SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double"


def files(spark, tmp_path, parts):
    for part in parts:
        df = spark.createDataFrame(part, "event_id bigint, at string, user_id bigint, event_type string, value double")
        df.select("event_id", F.col("at").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value").coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    return str(tmp_path)


def day(n, hour=0):
    return f"2024-01-{n:02d} {hour:02d}:00:00"


def test_cube_over_triggers(spark, tmp_path):
    parts = [[(i, day(1 + (i * 7) % 28, i % 24), i % 5, "view", float(i * 3 % 390)) for i in range(k, k + 10)] for k in (0, 10, 20)]
    base = files(spark, tmp_path, parts)
    want = {tuple(r) for r in scatter(stream.on_lattice(spark.read.parquet(f"{base}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")), GRID, 5), GRID, BW).collect()}
    merged = stream.run_merged(stream.read_events(spark, base, files_per_trigger=1), GRID, BW, 5)
    assert {tuple(r) for r in merged.collect()} == want
    live = stream.run_complete(stream.live_cube(stream.read_events(spark, base, files_per_trigger=1), GRID, BW, 5))
    assert {tuple(r) for r in live.collect()} == want


def test_repeats_are_dropped(spark, tmp_path):
    parts = [[(1, day(1), 1, "view", 1.0), (1, day(1), 1, "view", 1.0)], [(1, day(1), 1, "view", 1.0), (2, day(1, 5), 1, "view", 1.0)]]
    got = stream.run_append(stream.deduplicated(stream.read_events(spark, files(spark, tmp_path, parts), files_per_trigger=1)))
    assert sorted(r.event_id for r in got.collect()) == [1, 2]


def test_late_events_are_left_out(spark, tmp_path):
    # the fourth file is older than the watermark that the second one set; lateness is judged by the trigger before
    base = files(spark, tmp_path, [[(1, day(1), 1, "view", 1.0)], [(2, day(20), 1, "view", 1.0)], [(5, day(21), 1, "view", 1.0)], [(3, day(1, 2), 1, "view", 1.0)], [(4, day(25), 1, "view", 1.0)]])
    got = stream.run_append(stream.closed_slabs(stream.read_events(spark, base, files_per_trigger=1), "1 day", "1 day"))
    rows = {r.opens // 86_400_000_000 - 19722: r.n for r in got.collect()}
    assert rows[1] == 1 and 25 not in rows
