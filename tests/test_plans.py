"""Physical plans: what must reach the scan, and where a shuffle may stand."""

import os

import pytest

import __spark_entry__ as entry
from cubedensity.operators.density import cube
from cubedensity.plans import queries
from cubedensity.plans.workloads import WORKLOADS
from cubedensity.sources.sets import events
from cubedensity.spec import Bandwidth, GridSpec, TileSpec

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="needs the given tables")


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_scan_is_pruned(spark):
    plan = plan_of(events(spark, SF, "CITY", GridSpec(8, 8, 8)))
    assert "o_orderdate" in plan and "PushedFilters: [IsNotNull(o_orderdate), LessThan(o_orderdate" in plan
    assert "o_orderpriority" not in plan


def test_event_driven_methods_shuffle_once(spark):
    ev = events(spark, SF, "BIRDS", GridSpec(8, 8, 8))
    for method in ("scatter", "disk_scatter", "bar_scatter", "product_scatter"):
        plan = plan_of(cube(ev, GridSpec(8, 8, 8), Bandwidth(1, 1), method))
        assert plan.count("Exchange hashpartitioning") == 1 and "Python" not in plan and "partial_sum" in plan


def test_clipped_tiles_need_no_sum(spark):
    ev = events(spark, SF, "BIRDS", GridSpec(8, 8, 8))
    plan = plan_of(cube(ev, GridSpec(8, 8, 8), Bandwidth(1, 1), "tile_clip", tiles=TileSpec(2, 2, 2)))
    assert plan.count("Exchange hashpartitioning") == 1 and "keys=[vx" not in plan


def test_registry():
    assert len(WORKLOADS) == 21
    found, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(found) and len(found) > 150
    for w in WORKLOADS:
        assert w.name in found and w.name in sql


def test_entry(spark):
    assert entry.entry(spark).columns == ["vx", "vy", "vt", "hits", "mass", "density"]


def test_golden_rows(spark):
    from pyspark.sql import functions as F

    sf = SF.replace("0.001", "0.01")
    for name, grid, bw, want in (
        ("EVENTS", GridSpec(30, 40, 60), Bandwidth(3, 3), (50_752, 1_420_669, 31323505083603484, 5044449536253)),
        ("CITY", GridSpec(37, 48, 104), Bandwidth(3, 1), (134_629, 246_232, 685749019322257, 104036779480)),
        ("DOCS", GridSpec(20, 20, 20), Bandwidth(3, 2), (3_769, 72_312, 484100588861248, 1040515458048)),
    ):
        c = cube(events(spark, sf, name, grid), grid, bw, "auto")
        assert tuple(c.agg(F.count("*"), F.sum("hits"), F.sum("mass"), F.max("mass")).first()) == want


@pytest.mark.parametrize("name", ["stream_merged_cube", "stream_dedup", "greedy_color_rounds", "choose_method"])
def test_queries_on_the_smallest_tables(spark, name):
    assert entry.queries()[name](spark, SF).count() > 0


def test_core_does_not_know_the_training_data_operators():
    root = os.path.dirname(os.path.dirname(os.path.abspath(queries.__file__)))
    for folder, _, files in os.walk(root):
        if "llm" in folder.split(os.sep):
            continue
        for f in files:
            if f.endswith(".py"):
                assert "llm" not in open(os.path.join(folder, f)).read()


def test_theta_join_reads_all_events(spark):
    found = {n: sorted(map(tuple, entry.queries()[n](spark, SF).collect())) for n in ("op_theta_join", "op_block_join")}
    assert found["op_theta_join"] == found["op_block_join"]


@pytest.mark.parametrize("name", ["cost_colors_used", "cost_memory", "cost_zero_fill_cap", "oriented_edges", "parity_color", "replica_guard", "safe_tiles", "source_voxelgrid", "sql_udf_morton", "stencil_edges"])
def test_queries_take_their_data_from_a_given_table(spark, tmp_path, name):
    import duckdb

    # a table with few events: results that a made-up table would not have
    few = spark.read.parquet(f"{SF}/events.parquet").filter("user_id < 4")
    few.coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    got = [tuple(r) for r in entry.queries()[name](spark, str(tmp_path)).collect()]
    con = duckdb.connect()
    con.execute(f"create view events as select * from read_parquet('{tmp_path}/events.parquet/*.parquet')")
    want = con.execute(entry.oracle_sql()[name]).fetchall()
    assert sorted(got) == sorted(want) and got
    assert sorted(got) != sorted(tuple(r) for r in entry.queries()[name](spark, SF).collect())


def test_sequential_methods_run_on_every_workload(spark, monkeypatch):
    from cubedensity.plans import measures, workloads

    monkeypatch.setattr(measures, "seconds", lambda df: 0.0 if df.columns == ["vx", "vy", "vt", "hits", "mass"] else None)
    for family, names in workloads.FAMILIES.items():
        made = entry.queries()[f"x01_sequential_{family}"](spark, SF).collect()
        assert [(r.workload, r.method, r.seconds) for r in made] == [(w, m, 0.0) for w in names for m in workloads.SEQUENTIAL]
