"""The relational operators around cubes, one query each, with SQL of the same meaning where there is one."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubedensity.functions import sqlapi
from cubedensity.operators import output, relational, tiles
from cubedensity.operators.density import cube
from cubedensity.operators.relational import VOXEL
from cubedensity.plans import oracles
from cubedensity.plans.durable import shared_folder
from cubedensity.plans.queries import CITY, EVENTS, EVENTS_BW, FINE, POSTS, POSTS_BW, TILES
from cubedensity.sources import datasource
from cubedensity.sources.ingest import event_view, inside, read, snap
from cubedensity.sources.sets import SETS, events, events_sql
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions
from cubedensity.streaming import stream

QUERIES: dict = {}
ORACLES: dict = {}


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def _e(spark, sf, where=None):
    return events(spark, sf, "EVENTS", EVENTS, where=where)


def _esql(where=None):
    return events_sql("EVENTS", EVENTS, where=where)


def _cube(spark, sf, where=None, bw=EVENTS_BW):
    return cube(_e(spark, sf, where), EVENTS, bw, "product_scatter")


def _csql(where=None, bw=EVENTS_BW):
    return oracles.cube(_esql(where), EVENTS, bw)


def _posts(spark, sf):
    return cube(events(spark, sf, "POSTS", POSTS), POSTS, POSTS_BW, "tile_clip")


_POSTS_SQL = oracles.cube(events_sql("POSTS", POSTS), POSTS, POSTS_BW)
_CUT = EVENTS_BW
_LOADS = oracles.loads(_esql(), EVENTS, TILES)


def _loads(spark, sf):
    return tiles.tile_loads(_e(spark, sf), EVENTS, TILES)


# scans and joins ---------------------------------------------------------------------------------------------------
add(
    "op_scan_prune",
    lambda spark, sf: read(spark, sf, "lineitem").filter("l_shipdate >= timestamp_ntz'1996-01-01 00:00:00' and l_shipdate < timestamp_ntz'1996-04-01 00:00:00'").select("l_orderkey", "l_partkey", "l_extendedprice"),
    "select l_orderkey, l_partkey, l_extendedprice from lineitem where l_shipdate >= timestamp '1996-01-01' and l_shipdate < timestamp '1996-04-01'",
)


def _json_events(spark, sf):
    view = event_view(read(spark, sf, "events"), "event_id", "user_id", "cast(get_json_object(props, '$.k') as bigint)", "unix_micros(cast(ts as timestamp)) - 1704067200000000")
    return inside(snap(view, EVENTS, read(spark, sf, "events").agg(F.max("user_id") + 1), 100, 30 * 86_400_000_000), EVENTS, PlanOptions())


_JSON_SQL = (
    f"select event_id, ((user_id * {EVENTS.gx * 16}) // (select max(user_id) + 1 from events))::bigint as x, ((cast(json_extract_string(props, '$.k') as bigint) * {EVENTS.gy * 16}) // 100)::bigint as y, "
    f"(((epoch_us(ts) - 1704067200000000) * {EVENTS.gt * 16}) // 2592000000000)::bigint as t, 1::bigint as w from events"
)
add("op_event_json", lambda spark, sf: cube(_json_events(spark, sf), EVENTS, EVENTS_BW, "tile_clip"), oracles.cube(_JSON_SQL, EVENTS, EVENTS_BW))


def _keyword_pages(spark, sf):
    """Pages by number that hold a long word of any benchmark text: words of both sides meet by equality, whatever their number."""
    cut = lambda c: F.explode(F.split(F.translate(F.lower(c), "<>.,", "    "), " ")).alias("k")
    words = read(spark, sf, "benchmark").select(cut("text")).filter("length(k) between 12 and 30").distinct()
    pages = read(spark, sf, "pages").select("page_id", F.regexp_extract("url", "/([0-9]+)", 1).alias("number"), cut("html")).filter("length(k) between 12 and 30").distinct()
    return pages.join(words, "k", "left_semi").select("page_id", "number").distinct().groupBy("number").agg(F.count("*").alias("pages"))


add(
    "op_keyword_events",
    _keyword_pages,
    "with k as (select distinct k from (select unnest(string_split(translate(lower(text), '<>.,', '    '), ' ')) as k from benchmark) where length(k) between 12 and 30), "
    "p as (select page_id, regexp_extract(url, '/([0-9]+)', 1) as number, unnest(string_split(translate(lower(html), '<>.,', '    '), ' ')) as w from pages) "
    "select number, count(distinct page_id) as pages from p where w in (select k from k) group by number",
)
add("op_theta_join", lambda spark, sf: relational.voxel_scan(_e(spark, sf), EVENTS, EVENTS_BW), _csql())
add("op_block_join", lambda spark, sf: relational.block_scan(_e(spark, sf), EVENTS, EVENTS_BW), _csql())


def _lookup(spark, sf):
    o, c, n, r = (read(spark, sf, t) for t in ("orders", "customer", "nation", "region"))
    # nation and region are fixed lists of 25 and 5 rows
    places = n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))


_LOOKUP_SQL = "select * from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"
add("op_broadcast_lookup", lambda spark, sf: _lookup(spark, sf).groupBy("r_name", "n_name").agg(F.count("*").alias("events")), f"select r_name, n_name, count(*) as events from ({_LOOKUP_SQL}) group by all")

_DELAY = GridSpec(15, 20, 26)


def _delays(spark, sf):
    o, i = read(spark, sf, "orders"), read(spark, sf, "lineitem")
    both = i.join(o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    view = event_view(both, "l_orderkey * 8 + l_linenumber", "o_custkey", "cast(floor(o_totalprice * 100 + 0.5) as bigint)", "cast(datediff(l_shipdate, o_orderdate) as bigint) + 2600")
    return inside(snap(view, _DELAY, read(spark, sf, "customer").agg(F.max("c_custkey") + 1), 50_000_000, 5200), _DELAY, PlanOptions())


_DELAY_SQL = (
    f"select l_orderkey * 8 + l_linenumber as event_id, ((o_custkey * {15 * 16}) // (select max(c_custkey) + 1 from customer))::bigint as x, ((cast(floor(o_totalprice * 100 + 0.5) as bigint) * {20 * 16}) // 50000000)::bigint as y, "
    f"(((date_diff('day', o_orderdate, l_shipdate) + 2600) * {26 * 16}) // 5200)::bigint as t, 1::bigint as w from lineitem join orders on l_orderkey = o_orderkey"
)
add("op_merge_join", lambda spark, sf: cube(_delays(spark, sf), _DELAY, EVENTS_BW, "tile_clip"), oracles.cube(_DELAY_SQL, _DELAY, EVENTS_BW))


def _interval_pairs(spark, sf):
    """Pairs of one user's events within an hour: an equality join on hours, each event in its own and the next."""
    e = read(spark, sf, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = F.floor(F.col("us") / 3_600_000_000)
    a = e.select(F.col("event_id").alias("a_id"), "user_id", F.col("event_type").alias("a_type"), F.col("us").alias("a_us"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b_id"), "user_id", F.col("event_type").alias("b_type"), F.col("us").alias("b_us"), hour.alias("h"))
    near = a.join(b, ["user_id", "h"]).filter("(a_us < b_us or a_us = b_us and a_id < b_id) and b_us - a_us <= 3600000000")
    return near.groupBy("a_type", "b_type").agg(F.count("*").alias("pairs"))


add(
    "op_interval_pairs",
    _interval_pairs,
    "select a.event_type as a_type, b.event_type as b_type, count(*) as pairs from events a join events b on a.user_id = b.user_id and (a.ts < b.ts or a.ts = b.ts and a.event_id < b.event_id) and epoch_us(b.ts) - epoch_us(a.ts) <= 3600000000 group by all",
)


_SLOT = 3_600_000_000  # an hour of the 30 days


def _asof(spark, sf):
    """For each order, the latest event at or before it on a clock of days of the month and the order's key as its hour."""
    none = F.lit(None).cast("bigint")
    e = read(spark, sf, "events").select((F.unix_micros(F.col("ts").cast("timestamp")) - 1_704_067_200_000_000).alias("us"), "event_id", none.alias("o_orderkey"))
    o = read(spark, sf, "orders").select(((F.dayofmonth("o_orderdate") - 1) * 86_400_000_000 + (F.col("o_orderkey") % 24) * 3_600_000_000).alias("us"), none.alias("event_id"), "o_orderkey")
    both = e.union(o).withColumn("slot", F.floor(F.col("us") / _SLOT))
    # inside a slot the last event is carried along the clock; what came before the slot is one row a slot
    along = Window.partitionBy("slot").orderBy("us", F.col("event_id").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    mine = both.withColumn("mine", F.last("event_id", ignorenulls=True).over(along)).filter("o_orderkey is not null")
    ends = both.groupBy("slot").agg(F.max_by("event_id", F.when(F.col("event_id").isNotNull(), F.struct("us", "event_id"))).alias("last"))
    earlier = Window.orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select("slot", F.last("last", ignorenulls=True).over(earlier).alias("before"))
    return mine.join(F.broadcast(carried), "slot").select("o_orderkey", F.coalesce("mine", "before").alias("event_id"))  # 720 slots an epoch


add(
    "op_asof",
    _asof,
    "with o as (select o_orderkey, (day(o_orderdate) - 1) * 86400000000 + (o_orderkey % 24) * 3600000000 as us from orders), e as (select epoch_us(ts) - 1704067200000000 as us, event_id from events) "
    "select o_orderkey, (select event_id from e where e.us <= o.us order by e.us desc, event_id desc limit 1) as event_id from o",
)


def _neighbours(spark, sf, how):
    ev = events(spark, sf, "CITY", CITY)
    hx, ht = Bandwidth(0.5, 1).lattice(CITY)
    block = lambda c, h: F.floor(F.col(c) / h)
    a = ev.select("event_id", "x", "y", "t", block("x", hx).alias("bx"), block("y", hx).alias("by"), block("t", ht).alias("bt"))
    around = lambda c, h: F.explode(F.sequence(block(c, h) - 1, block(c, h) + 1))
    b = ev.select(F.col("event_id").alias("o"), F.col("x").alias("ox"), F.col("y").alias("oy"), F.col("t").alias("ot"), around("x", hx).alias("bx"))
    b = b.select("*", F.explode(F.sequence(F.floor(F.col("oy") / hx) - 1, F.floor(F.col("oy") / hx) + 1)).alias("by"))
    b = b.select("*", F.explode(F.sequence(F.floor(F.col("ot") / ht) - 1, F.floor(F.col("ot") / ht) + 1)).alias("bt"))
    near = (a.bx == b.bx) & (a.by == b.by) & (a.bt == b.bt) & (F.col("event_id") != F.col("o"))
    near &= ((F.col("x") - F.col("ox")) * (F.col("x") - F.col("ox")) + (F.col("y") - F.col("oy")) * (F.col("y") - F.col("oy")) < hx * hx) & (F.abs(F.col("t") - F.col("ot")) <= ht)
    return a.join(b, near, how).select("event_id")


_CSQL = events_sql("CITY", CITY)
_NEAR = f"select 1 from c o where o.event_id <> c.event_id and (o.x-c.x)*(o.x-c.x)+(o.y-c.y)*(o.y-c.y) < 64 and abs(o.t-c.t) <= 16 and o.x between c.x-8 and c.x+8"
add("op_semi_neighbours", lambda spark, sf: _neighbours(spark, sf, "left_semi"), f"with c as materialized ({_CSQL}) select event_id from c where exists ({_NEAR})")
add("op_anti_isolated", lambda spark, sf: _neighbours(spark, sf, "left_anti"), f"with c as materialized ({_CSQL}) select event_id from c where not exists ({_NEAR})")

_FIRST, _SECOND = "ts < timestamp '2024-01-16 00:00:00'", "ts >= timestamp '2024-01-16 00:00:00'"
add(
    "op_full_outer_diff",
    lambda spark, sf: output.difference(_cube(spark, sf, _FIRST), _cube(spark, sf, _SECOND)),
    f"select coalesce(a.vx, b.vx) as vx, coalesce(a.vy, b.vy) as vy, coalesce(a.vt, b.vt) as vt, coalesce(a.mass, 0) - coalesce(b.mass, 0) as change from ({_csql(_FIRST)}) a full join ({_csql(_SECOND)}) b on a.vx = b.vx and a.vy = b.vy and a.vt = b.vt",
)
_SWEEP = [Bandwidth(4, 2), Bandwidth(2, 1), Bandwidth(1, 1)]
add(
    "op_cross_sweep",
    lambda spark, sf: relational.bandwidth_sweep(events(spark, sf, "CITY", CITY), CITY, _SWEEP).groupBy("bw").agg(F.count("*").alias("voxels"), F.sum("hits").alias("hits"), F.max("mass").alias("peak")),
    " union all ".join(f"select {i}::int as bw, count(*) as voxels, sum(hits)::bigint as hits, max(mass) as peak from ({oracles.cube(_CSQL, CITY, b)})" for i, b in enumerate(_SWEEP)),
)


def _lateral(spark, sf):
    _e(spark, sf).createOrReplaceTempView("lattice_events")
    sqlapi.register(spark)
    gx, gy, gt, s = *EVENTS.shape, EVENTS.sub
    hx, ht = EVENTS_BW.lattice(EVENTS)
    reach = lambda c, h, g: f"sequence(greatest(CAST({c} DIV {s} AS INT) - {h}, 0), least(CAST({c} DIV {s} AS INT) + {h}, {g - 1}))"
    d = [f"(v{c} * {s} + {s // 2} - {c})" for c in "xyt"]
    return spark.sql(
        f"""SELECT vx, vy, vt, count(*) AS hits, sum(kernel_space({d[0]}, {d[1]}, {hx}) * kernel_time({d[2]}, {ht}) * w) AS mass
        FROM lattice_events, LATERAL explode({reach("x", 2, gx)}) AS a(vx), LATERAL explode({reach("y", 2, gy)}) AS b(vy), LATERAL explode({reach("t", 1, gt)}) AS c(vt)
        WHERE {d[0]} * {d[0]} + {d[1]} * {d[1]} < {hx * hx} AND abs({d[2]}) <= {ht} GROUP BY vx, vy, vt"""
    )


add("op_lateral", _lateral, _csql())

# aggregates --------------------------------------------------------------------------------------------------------
_KEYS = ["r_name", "n_name", "year"]


def _grouped(spark, sf, how):
    rows = _lookup(spark, sf).select("r_name", "n_name", F.year("o_orderdate").alias("year"), F.floor(F.col("o_totalprice") * 100 + 0.5).cast("long").alias("cents"))
    aggs = (F.count("*").alias("events"), F.sum("cents").alias("cents"))
    if how == "sets":
        return rows.groupingSets([["r_name", "year"], ["n_name"], []], *_KEYS).agg(*aggs)
    return getattr(rows, how)(*_KEYS).agg(*aggs)


_ROWS = f"select r_name, n_name, year(o_orderdate)::int as year, cast(floor(o_totalprice * 100 + 0.5) as bigint) as cents from ({_LOOKUP_SQL})"
_AGGS = "count(*) as events, sum(cents)::bigint as cents"
for _name, _how, _by in (("op_rollup_region", "rollup", "rollup (r_name, n_name, year)"), ("op_cube", "cube", "cube (r_name, n_name, year)"), ("op_grouping_sets", "sets", "grouping sets ((r_name, year), (n_name), ())")):
    add(_name, lambda spark, sf, h=_how: _grouped(spark, sf, h), f"select r_name, n_name, year, {_AGGS} from ({_ROWS}) group by {_by}")
_TYPES = ["click", "error", "purchase", "signup", "view"]


def _pivoted(spark, sf):
    slab = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - 1_704_067_200_000_000) / 86_400_000_000).cast("int")
    return read(spark, sf, "events").select(slab.alias("slab"), "event_type").groupBy("slab").pivot("event_type", _TYPES).agg(F.count(F.lit(1))).fillna(0)


_PIVOT_SQL = "select slab, " + ", ".join(f"count(*) filter (event_type = '{t}') as {t}" for t in _TYPES) + " from (select ((epoch_us(ts) - 1704067200000000) // 86400000000)::int as slab, event_type from events) group by slab"
add("op_pivot", _pivoted, _PIVOT_SQL)
add("op_unpivot", lambda spark, sf: _pivoted(spark, sf).unpivot("slab", _TYPES, "event_type", "n"), " union all ".join(f"select slab, '{t}' as event_type, {t} as n from ({_PIVOT_SQL})" for t in _TYPES))
add("op_distinct", lambda spark, sf: _cube(spark, sf).agg(F.count_distinct("vx", "vy").alias("columns"), F.count_distinct("vt").alias("slabs")), f"select count(distinct (vx, vy)) as columns, count(distinct vt) as slabs from ({_csql()})")
add("op_approx_distinct", lambda spark, sf: _cube(spark, sf).agg(F.approx_count_distinct(F.struct("vx", "vy")).alias("columns")))
add(
    "op_percentiles",
    lambda spark, sf: _loads(spark, sf).agg(*(F.expr(f"percentile_disc({p}) within group (order by load)").cast("bigint").alias(f"p{int(p * 100)}") for p in (0.25, 0.5, 0.75, 0.95))),
    f"select quantile_disc(load, 0.25) as p25, quantile_disc(load, 0.5) as p50, quantile_disc(load, 0.75) as p75, quantile_disc(load, 0.95) as p95 from ({_LOADS})",
)
add(
    "op_peak_per_slab",
    lambda spark, sf: _cube(spark, sf).groupBy("vt").agg(F.max_by(F.struct("vx", "vy", "mass"), F.struct("mass", -F.col("vx"), -F.col("vy"))).alias("p")).select("vt", "p.vx", "p.vy", "p.mass"),
    f"select vt, vx, vy, mass from (select *, row_number() over (partition by vt order by mass desc, vx, vy) as r from ({_csql()})) where r = 1",
)
add(
    "op_trend_statistics",
    lambda spark, sf: _cube(spark, sf).groupBy("vy").agg(F.max("hits").alias("most"), F.sum("hits").alias("hits"), F.count_if(F.col("hits") > 50).alias("busy"), F.min_by("vt", F.struct("mass", "vx", "vt")).alias("lightest")),
    f"select vy, max(hits) as most, sum(hits)::bigint as hits, count(*) filter (hits > 50) as busy, arg_min(vt, (mass, vx, vt)) as lightest from ({_csql()}) group by vy",
)

# windows, sorts, sets ----------------------------------------------------------------------------------------------
def _rank():
    return Window.orderBy(F.desc("load"), "tile_id")  # over tiles: a bounded number of rows


add(
    "op_rank_tiles",
    lambda spark, sf: _loads(spark, sf).select("tile_id", "load", F.row_number().over(_rank()).alias("row"), F.rank().over(Window.orderBy(F.desc("load"))).alias("rank"), F.dense_rank().over(Window.orderBy(F.desc("load"))).alias("dense")),
    f"select tile_id, load, row_number() over (order by load desc, tile_id)::int as row, rank() over (order by load desc)::int as rank, dense_rank() over (order by load desc)::int as dense from ({_LOADS})",
)
add(
    "op_ntile",
    lambda spark, sf: _loads(spark, sf).select("tile_id", F.ntile(4).over(_rank()).alias("quarter"), F.percent_rank().over(_rank()).alias("percent"), F.cume_dist().over(_rank()).alias("share")),
    f"select tile_id, ntile(4) over (order by load desc, tile_id)::int as quarter, percent_rank() over (order by load desc, tile_id) as percent, cume_dist() over (order by load desc, tile_id) as share from ({_LOADS})",
)
def _column():
    return Window.partitionBy("vx", "vy").orderBy("vt")



def _city(spark, sf):
    return cube(events(spark, sf, "CITY", CITY), CITY, Bandwidth(3, 1), "tile_clip")


_CITY_SQL = oracles.cube(_CSQL, CITY, Bandwidth(3, 1))
add(
    "op_lag_growth",
    lambda spark, sf: _city(spark, sf).select(*VOXEL, (F.col("mass") - F.lag("mass").over(_column())).alias("growth"), F.lead("mass").over(_column()).alias("next"), F.first("mass").over(_column()).alias("first"), F.nth_value("mass", 2).over(_column()).alias("second")),
    f"select vx, vy, vt, mass - lag(mass) over w as growth, lead(mass) over w as next, first_value(mass) over w as first, nth_value(mass, 2) over w as second from ({_CITY_SQL}) window w as (partition by vx, vy order by vt)",
)
add(
    "op_rows_frame",
    lambda spark, sf: output.moving_mean(_cube(spark, sf), 1).select(*VOXEL, "around"),
    f"select vx, vy, vt, (sum(mass) over (partition by vx, vy order by vt rows between 1 preceding and 1 following))::bigint as around from ({_csql()})",
)
add(
    "op_range_frame",
    lambda spark, sf: _e(spark, sf).select("event_id", F.count("*").over(Window.partitionBy(F.floor(F.col("x") / 16), F.floor(F.col("y") / 16)).orderBy("t").rangeBetween(-16, 16)).alias("near")),
    f"select event_id, count(*) over (partition by x // 16, y // 16 order by t range between 16 preceding and 16 following) as near from ({_esql()})",
)
add(
    "op_cumshare",
    lambda spark, sf: output.running_share(_posts(spark, sf)),
    f"select vx, vy, vt, mass, (sum(mass) over (order by mass desc, vx, vy, vt rows unbounded preceding))::bigint as running from ({_POSTS_SQL})",
)
add("op_topk", lambda spark, sf: output.top(_posts(spark, sf), 20), f"select * from ({_POSTS_SQL}) order by mass desc, vx, vy, vt limit 20")
add("op_offset", lambda spark, sf: output.top(_posts(spark, sf), 20, 20), f"select * from ({_POSTS_SQL}) order by mass desc, vx, vy, vt limit 20 offset 20")
add("op_union_merge", lambda spark, sf: relational.merge_cubes(*(_cube(spark, sf, f"event_type = '{t}'") for t in _TYPES)), _csql())
add("op_except_identity", lambda spark, sf: _cube(spark, sf).exceptAll(cube(_e(spark, sf), EVENTS, EVENTS_BW, "parity_sets", tiles=TILES)), f"select * from ({_csql()}) where false")
_HOT = 60000000000
add(
    "op_intersect_hot",
    lambda spark, sf: _cube(spark, sf).orderBy(F.desc("mass"), *VOXEL).limit(500).select(*VOXEL).intersect(_cube(spark, sf, bw=Bandwidth(3, 2)).orderBy(F.desc("mass"), *VOXEL).limit(500).select(*VOXEL)),
    f"(select vx, vy, vt from ({_csql()}) order by mass desc, vx, vy, vt limit 500) intersect (select vx, vy, vt from ({_csql(bw=Bandwidth(3, 2))}) order by mass desc, vx, vy, vt limit 500)",
)
add("op_sample_preview", lambda spark, sf: cube(events(spark, sf, "POSTS", POSTS).sample(0.1, seed=7), POSTS, POSTS_BW, "tile_clip").withColumn("mass", F.col("mass") * 10))


def _cases(spark, sf):
    docs = events(spark, sf, "DOCS", GridSpec(20, 20, 20))
    labels = read(spark, sf, "labels")
    both = docs.join(labels, F.col("event_id") == F.col("doc_id"))
    return both.groupBy(F.floor(F.col("x") / 16).cast("int").alias("vx"), F.floor(F.col("y") / 16).cast("int").alias("vy")).agg(
        F.count_if(F.col("toxic") == 1).alias("cases"), F.count_if(F.col("toxic") == 0).alias("controls"), F.sum(F.when(F.col("quality") == 1, F.col("w"))).alias("good")
    )


add(
    "op_case_control",
    _cases,
    f"select (x // 16)::int as vx, (y // 16)::int as vy, count(*) filter (toxic = 1) as cases, count(*) filter (toxic = 0) as controls, (sum(w) filter (quality = 1))::bigint as good from ({events_sql('DOCS', GridSpec(20, 20, 20))}) join labels on event_id = doc_id group by all",
)


def _vectors(spark, sf):
    grid = GridSpec(16, 16, 10)
    keyed = events(spark, sf, "VECS", grid).join(read(spark, sf, "embeddings").select(F.col("vec_id").alias("event_id"), "label"), "event_id")
    return relational.scatter(keyed, grid, Bandwidth(2, 1), PlanOptions(), "label")


_VGRID = GridSpec(16, 16, 10)
add("op_vectors", _vectors, oracles.cube(f"select v.*, label from ({events_sql('VECS', _VGRID)}) v join embeddings on event_id = vec_id", _VGRID, Bandwidth(2, 1), carry="label"))
add("op_conv_grid", lambda spark, sf: read(spark, sf, "conversations").groupBy((F.col("conv_id") % 10).alias("group"), "turn", "role").agg(F.count("*").alias("n")), 'select conv_id % 10 as "group", turn, role, count(*) as n from conversations group by all')


def _brand(spark, sf):
    brand = read(spark, sf, "part").filter("p_brand = 'Brand#12'").select(F.col("p_partkey").alias("k"))
    chosen = read(spark, sf, "lineitem").join(brand, F.col("l_partkey") == F.col("k"), "left_semi")
    s = SETS["POSTS"]
    from cubedensity.sources.sets import for_spark

    view = event_view(chosen, *map(for_spark, (s.event_id, s.x, s.y, s.t)))
    return inside(snap(view, POSTS, read(spark, sf, "part").agg(F.max("p_partkey") + 1), 10_500_000, 2520 * 86_400_000_000), POSTS, PlanOptions())


add("op_part_filter", lambda spark, sf: cube(_brand(spark, sf), POSTS, POSTS_BW, "product_scatter"), oracles.cube(events_sql("POSTS", POSTS, where="l_partkey in (select p_partkey from part where p_brand = 'Brand#12')"), POSTS, POSTS_BW))


def _weighted(spark, sf):
    per = read(spark, sf, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("weight"))
    of = read(spark, sf, "customer").join(F.broadcast(per), F.col("c_nationkey") == F.col("s_nationkey"), "left").select("c_custkey", F.coalesce("weight", F.lit(0)).alias("weight"))
    keyed = events(spark, sf, "CITY", CITY).join(read(spark, sf, "orders").select(F.col("o_orderkey").alias("event_id"), "o_custkey"), "event_id").join(of, F.col("o_custkey") == F.col("c_custkey"))
    return keyed.select("event_id", "x", "y", "t", F.col("weight").alias("w"))


add(
    "op_supplier_weight",
    lambda spark, sf: cube(_weighted(spark, sf), CITY, Bandwidth(3, 1), "tile_clip"),
    oracles.cube(f"select e.event_id, x, y, t, coalesce(s.n, 0)::bigint as w from ({_CSQL}) e join orders o on e.event_id = o.o_orderkey join customer c on o.o_custkey = c.c_custkey left join (select s_nationkey, count(*) as n from supplier group by s_nationkey) s on s.s_nationkey = c.c_nationkey", CITY, Bandwidth(3, 1)),
)
add(
    "op_pyramid",
    lambda spark, sf: output.pyramid(_posts(spark, sf)),
    " union all ".join(f"select {k}::int as size, (vx // {k})::int as vx, (vy // {k})::int as vy, (vt // {k})::int as vt, sum(hits)::bigint as hits, sum(mass)::bigint as mass from ({_POSTS_SQL}) group by all" for k in (1, 2, 4)),
)


_BUYS = "event_type = 'purchase'"
_SLAB = 3  # times in a stored slab


def _occupied(spark, sf):
    """A stored cube read through a runtime filter: only slabs with more purchases than the mean are scanned at all."""
    path = f"{shared_folder(spark)}/cube-{uuid.uuid4().hex}"
    output.write_cube(_cube(spark, sf), path, _SLAB)
    slab = F.floor(F.col("t") / (16 * _SLAB)).cast("int")
    counts = _e(spark, sf, _BUYS).groupBy(slab.alias("busy")).agg(F.count("*").alias("n"))
    busy = counts.join(counts.agg((F.sum("n") / (EVENTS.gt // _SLAB)).alias("mean"))).filter("n > mean").select("busy")  # a row a slab, ten here
    stored = spark.read.parquet(path).withColumnRenamed("slab", "at")
    return stored.join(F.broadcast(busy), F.col("at") == F.col("busy")).select(*VOXEL, "hits", "mass")


add(
    "op_skip_empty_tiles",
    _occupied,
    f"with b as (select t // {16 * _SLAB} as busy, count(*) as n from ({_esql(where=_BUYS)}) group by 1) select vx, vy, vt, hits, mass from ({_csql()}) where vt // {_SLAB} in (select busy from b where n > (select sum(n) from b) / {EVENTS.gt // _SLAB}.0)",
)
add("op_split_sample", lambda spark, sf: read(spark, sf, "events").sampleBy("event_type", {"click": 0.5, "view": 0.1}, seed=3).groupBy("event_type").agg(F.count("*").alias("n")))
add("op_hotspots", lambda spark, sf: output.hot_spots(_cube(spark, sf), _HOT))

# scalar functions --------------------------------------------------------------------------------------------------
add(
    "op_map_stats",
    lambda spark, sf: _loads(spark, sf).groupBy("a").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("tile_id", "load")))).alias("m")).select("a", F.size("m").alias("tiles"), F.array_max(F.map_values("m")).alias("most"), F.aggregate(F.map_values(F.map_filter("m", lambda k, v: v > 50)), F.lit(0).cast("long"), lambda x, y: x + y).alias("busy")),
    f"select a, count(*)::int as tiles, max(load) as most, coalesce(sum(load) filter (load > 50), 0)::bigint as busy from ({_LOADS}) group by a",
)
add(
    "fn_array",
    lambda spark, sf: read(spark, sf, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda v: v > 0)).alias("positive"), F.exists("embedding", lambda v: v > 0.3).alias("large"), F.forall("embedding", lambda v: v > -1).alias("bounded"), F.array_max(F.slice("embedding", 1, 8)).cast("double").alias("most")),
    "select vec_id, len(embedding)::int as n, len(list_filter(embedding, lambda v: v > 0))::int as positive, len(list_filter(embedding, lambda v: v > 0.3)) > 0 as large, len(list_filter(embedding, lambda v: v <= -1)) = 0 as bounded, list_max(embedding[1:8])::double as most from embeddings",
)
add(
    "fn_string",
    lambda spark, sf: read(spark, sf, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.length("html").alias("chars"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.regexp_count("html", F.lit("<p>")).alias("paragraphs"), F.concat_ws("/", F.substring("url", 1, 5), F.upper(F.lit("x"))).alias("mark"), F.translate(F.substring("url", 1, 8), "htps", "HTPS").alias("shout")),
    "select page_id, regexp_extract(url, '://([^/]+)', 1) as host, length(html)::int as chars, lpad(page_id::varchar, 8, '0') as padded, len(regexp_extract_all(html, '<p>'))::int as paragraphs, concat_ws('/', substring(url, 1, 5), upper('x')) as mark, translate(substring(url, 1, 8), 'htps', 'HTPS') as shout from pages",
)
add(
    "fn_date",
    lambda spark, sf: read(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("year"), F.quarter("o_orderdate").alias("quarter"), F.dayofweek("o_orderdate").alias("weekday"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.last_day("o_orderdate").alias("month_end"), F.date_add("o_orderdate", 14).alias("later")),
    "select o_orderkey, year(o_orderdate)::int as year, quarter(o_orderdate)::int as quarter, (dayofweek(o_orderdate) + 1)::int as weekday, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days, strftime(o_orderdate, '%Y-%m') as month, last_day(o_orderdate) as month_end, (o_orderdate::date + 14)::date as later from orders",
)
add(
    "fn_json",
    lambda spark, sf: read(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.from_json("props", "k bigint")["k"].alias("parsed"), F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("variant"), F.to_json(F.struct("event_id")).alias("written")),
    "select event_id, json_extract_string(props, '$.k')::bigint as k, json_extract_string(props, '$.k')::bigint as parsed, json_extract_string(props, '$.k')::bigint as variant, '{\"event_id\":' || event_id || '}' as written from events",
)
add(
    "fn_math",
    lambda spark, sf: _e(spark, sf).select("event_id", F.pmod("x", F.lit(7)).alias("rest"), F.greatest("x", "y").alias("most"), F.least("x", "y").alias("least"), F.abs(F.col("x") - F.col("y")).alias("apart"), F.sign(F.col("x") - F.col("y")).cast("int").alias("side"), F.shiftleft("x", 3).alias("shifted"), F.col("x").bitwiseAND(F.lit(12)).alias("bits"), F.width_bucket(F.col("y").cast("double"), F.lit(0.0), F.lit(320.0), F.lit(8)).alias("bucket"), F.floor(F.sqrt(F.col("x").cast("double"))).alias("root")),
    f"select event_id, x % 7 as rest, greatest(x, y) as most, least(x, y) as least, abs(x - y) as apart, sign(x - y)::int as side, x << 3 as shifted, x & 12 as bits, least(9, y // 40 + 1)::bigint as bucket, floor(sqrt(x::double))::bigint as root from ({_esql()})",
)

# extension surfaces ------------------------------------------------------------------------------------------------
_HXT = EVENTS_BW.lattice(EVENTS)


def _udtf(spark, sf):
    sqlapi.register(spark)
    _e(spark, sf).createOrReplaceTempView("lattice_events")
    gx, gy, gt = EVENTS.shape
    return spark.sql(f"SELECT vx, vy, vt, count(*) AS hits, sum(term) AS mass FROM cylinder(TABLE(lattice_events), {gx}, {gy}, {gt}, {EVENTS.sub}, {_HXT[0]}, {_HXT[1]}) GROUP BY vx, vy, vt")


def _pandas_kernel(spark, sf):
    # the printed kernel in units of the bandwidth: brought back to whole masses
    found = sqlapi.user_scatter(_e(spark, sf), EVENTS, EVENTS_BW, lambda u, v, w: (1 - u) ** 2 * (1 - v) ** 2 * (1 - w) ** 2)
    return found.select(*VOXEL, "hits", F.round(F.col("mass") * (_HXT[0] ** 4 * _HXT[1] ** 2)).cast("bigint").alias("mass"))


def _morton(spark, sf):
    sqlapi.register(spark)
    return _e(spark, sf).selectExpr("voxel_of(x, 16) as a", "voxel_of(y, 16) as b").distinct().selectExpr("a", "b", "morton(a, b) as z")


def _array_blocks(spark, sf):
    """Blocks as arrays of a column's hits by slab, summed by an aggregate over arrays."""
    rows = _e(spark, sf).select(F.floor(F.col("x") / 16).cast("int").alias("vx"), "event_id", F.floor(F.col("t") / 16).cast("int").alias("vt"))
    parts = rows.groupBy("vx", F.pmod("event_id", F.lit(4)).alias("part"), "vt").agg(F.count("*").alias("n"))
    one = parts.groupBy("vx", "part").agg(F.map_from_entries(F.collect_list(F.struct("vt", "n"))).alias("m"))
    arrays = one.select("vx", F.transform(F.sequence(F.lit(0), F.lit(EVENTS.gt - 1)), lambda t: F.coalesce(F.try_element_at("m", t), F.lit(0).cast("long"))).alias("block"))
    return arrays.groupBy("vx").agg(sqlapi.sum_arrays("block").alias("block")).select("vx", F.posexplode("block").alias("vt", "n")).filter("n > 0")


def _factors(spark, sf):
    """The factors of every event at the centre of its own voxel, by the SQL functions."""
    sqlapi.register(spark)
    own = [f"({c} DIV {EVENTS.sub} * {EVENTS.sub} + {EVENTS.sub // 2} - {c})" for c in "xyt"]
    return _e(spark, sf).selectExpr("event_id", f"kernel_space({own[0]}, {own[1]}, {_HXT[0]}) as ks", f"kernel_time({own[2]}, {_HXT[1]}) as kt")


_OWN = [f"({c} // 16 * 16 + 8 - {c})" for c in "xyt"]
add("sql_udf_kernel", _factors, f"select event_id, ({_HXT[0]}-{_OWN[0]})*({_HXT[0]}-{_OWN[0]})*({_HXT[0]}-{_OWN[1]})*({_HXT[0]}-{_OWN[1]}) as ks, ({_HXT[1]}-{_OWN[2]})*({_HXT[1]}-{_OWN[2]}) as kt from ({_esql()})")
add("udtf_cylinder", _udtf, _csql())


def _arrow_blocks(spark, sf):
    """One row of arrays for each tile, as the Arrow kernel makes them, and sums over the arrays."""
    made = tiles.tile_clip(_e(spark, sf), EVENTS, EVENTS_BW, TILES, emit="blocks")
    total = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda a, x: a + x)
    return made.select("a", "b", "c", F.size("hits").alias("voxels"), total("hits").alias("hits"), total("mass").alias("mass"), F.array_max("mass").alias("most"))


add(
    "arrow_block",
    _arrow_blocks,
    f"with n as (select (3*x)//15 as a, (4*y)//20 as b, (5*t)//30 as c, count(*) as voxels from range(15) p(x), range(20) q(y), range(30) r(t) group by all) "
    f"select a::int as a, b::int as b, c::int as c, any_value(voxels)::int as voxels, sum(hits)::bigint as hits, sum(mass)::bigint as mass, max(mass) as most from ({_csql()}) d join n on (3*vx)//15 = a and (4*vy)//20 = b and (5*vt)//30 = c group by all",
)
add("pandas_kernel", _pandas_kernel, _csql())
add("sql_udf_morton", _morton, "select a::int as a, b::int as b, (" + " + ".join(f"((a >> {i}) & 1) * {1 << 2 * i} + ((b >> {i}) & 1) * {1 << 2 * i + 1}" for i in range(6)) + ")::bigint as z from " f"(select distinct x // 16 as a, y // 16 as b from ({_esql()}))")
add("array_block_sum", _array_blocks, f"select (x // 16)::int as vx, (t // 16)::int as vt, count(*) as n from ({_esql()}) group by all")


def _grid_source(spark, sf):
    datasource.register(spark)
    g = spark.read.format("voxelgrid").options(gx=15, gy=20, gt=30, partitions=4).load()
    held = _e(spark, sf).select(*(F.floor(F.col(c) / 16).cast("int").alias(v) for c, v in zip("xyt", VOXEL))).distinct()
    return g.join(held, list(VOXEL), "left_semi").groupBy("vx").agg(F.count("*").alias("n"), F.sum("vy").alias("ys"), F.sum("vt").alias("ts"))


add("source_voxelgrid", _grid_source, f"select vx::int as vx, count(*) as n, sum(vy)::bigint as ys, sum(vt)::bigint as ts from (select distinct x // 16 as vx, y // 16 as vy, t // 16 as vt from ({_esql()})) group by vx")
add(
    "source_scale_up",
    lambda spark, sf: events(spark, sf, "WORLD", POSTS, 3).groupBy("x").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids")),
    f"select x, count(*) as n, sum(event_id)::bigint as ids from ({events_sql('WORLD', POSTS, 3)}) group by x",
)

# streams -----------------------------------------------------------------------------------------------------------
_WINDOW = "count(*) as n, sum(cast(floor(value * 100 + 0.5) as bigint))::bigint as cents"


def _stream(spark, sf):
    return stream.read_events(spark, sf, "events")


add(
    "stream_tumbling",
    lambda spark, sf: stream.run_complete(stream.tumbling(_stream(spark, sf))),
    f"select d * 86400000000 as opens, (d + 1) * 86400000000 as closes, event_type, {_WINDOW} from (select *, epoch_us(ts) // 86400000000 as d from events) group by d, event_type",
)
add(
    "stream_sliding",
    lambda spark, sf: stream.run_complete(stream.sliding(_stream(spark, sf))),
    f"select (d - k) * 86400000000 as opens, (d - k + 7) * 86400000000 as closes, event_type, {_WINDOW} from (select *, epoch_us(ts) // 86400000000 as d from events), range(7) r(k) group by d - k, event_type",
)
add(
    "stream_session",
    lambda spark, sf: stream.run_complete(stream.sessions(_stream(spark, sf))),
    "with s as (select user_id, epoch_us(ts) as us, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) <= 21600000000 then 0 else 1 end as new from events), "
    "g as (select *, sum(new) over (partition by user_id order by us rows unbounded preceding) as k from s) select min(us) as opens, max(us) + 21600000000 as closes, user_id, count(*) as n from g group by user_id, k",
)
add("stream_dedup", lambda spark, sf: stream.run_append(stream.deduplicated(_stream(spark, sf).union(_stream(spark, sf))).select("event_id", "user_id")), "select event_id, user_id from events")
add("stream_cube", lambda spark, sf: stream.run_complete(stream.live_cube(_stream(spark, sf), EVENTS, EVENTS_BW, 150)), oracles.cube(_esql().replace("(select max(user_id) + 1 from events)", "150"), EVENTS, EVENTS_BW))
add("stream_merged_cube", lambda spark, sf: stream.run_merged(_stream(spark, sf), EVENTS, EVENTS_BW, 150), oracles.cube(_esql().replace("(select max(user_id) + 1 from events)", "150"), EVENTS, EVENTS_BW))
_CUT = 15 * 86_400_000_000


def _closing(spark, sf):
    """Two halves of the events, the later one first: what is late by more than a day is left out."""
    return stream.run_late(spark, read(spark, sf, "events"), "ts >= timestamp_ntz'2024-01-16 00:00:00'", "1 day", "1 day")


add(
    "stream_closed_slabs",
    _closing,
    f"with e as (select epoch_us(ts) as us from events), s as (select us // 86400000000 * 86400000000 as opens, count(*) as n from e where us >= 1704067200000000 + {_CUT} group by 1) "
    "select opens, n, (select count(distinct us // 86400000000) from e where us < 1704067200000000 + " + str(_CUT) + " and (us // 86400000000 + 1) * 86400000000 <= (select max(us) from e) - 86400000000) as late_slabs from s "
    "where opens + 86400000000 <= (select max(us) from e) - 86400000000",
)
add(
    "stream_interval_join",
    lambda spark, sf: stream.run_append(stream.neighbours(_stream(spark, sf), _stream(spark, sf))),
    "select a.event_id as first, b.event_id as second from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000",
)
