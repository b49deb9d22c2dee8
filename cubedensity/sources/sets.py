"""The event sets of the experiments, over the given tables.

Each is stated once, as expressions that mean the same in Spark and in the oracle engine but for three spellings:
``{div}`` whole quotient, ``{micros:column}`` microseconds since 1970 and ``{days:column}`` whole days since 1995.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.sources.ingest import event_view, inside, read, scale_up, snap
from cubedensity.spec import GridSpec, PlanOptions

DAY = 86_400_000_000


@dataclass(frozen=True)
class EventSet:
    source: str  # tables, or a join that both engines read
    event_id: str
    x: str
    y: str
    t: str
    x_den: str  # a number, or max(column)+1 of a table as "table.column"
    y_den: str
    t_den: str
    where: str = "true"
    w: str = "1"


_VALUE = "least(cast(floor(value * 100 + 0.5) as bigint), 39999)"
_GAZ = "orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey"
_AXIS = "element_at(embedding, {n})"
_UNIT = "least(greatest(cast(floor((cast({e} as double) + 1) * 1000000) as bigint), 0), 1999999)"

SETS = {
    "EVENTS": EventSet("events", "event_id", "user_id", _VALUE, "{micros:ts} - 1704067200000000", "events.user_id", "40000", str(30 * DAY)),
    "BIRDS": EventSet("events", "event_id", "user_id", _VALUE, "{micros:ts} - 1704067200000000", "events.user_id", "40000", str(30 * DAY), "event_type = 'purchase'"),
    "CITY": EventSet(
        "orders", "o_orderkey", "o_custkey", "cast(floor(o_totalprice * 100 + 0.5) as bigint)", "{micros:o_orderdate} - 788918400000000",
        "customer.c_custkey", "50000000", str(731 * DAY), "o_orderdate < timestamp '1997-01-01 00:00:00'",
    ),
    "POSTS": EventSet(
        "lineitem", "l_orderkey * 8 + l_linenumber", "l_partkey", "cast(floor(l_extendedprice * 100 + 0.5) as bigint)",
        "{micros:l_shipdate} - 788918400000000", "part.p_partkey", "10500000", str(2520 * DAY),
    ),
    "GAZ": EventSet(
        _GAZ, "o_orderkey",
        "(n_nationkey % 5) * 6000 + 3000 + ((c_custkey * 37) % 41 - 20) * ((c_custkey * 11) % 7) * 10",
        "(n_nationkey {div} 5) * 6000 + 3000 + ((c_custkey * 53) % 41 - 20) * ((c_custkey * 13) % 7) * 10",
        "({micros:o_orderdate} - 788918400000000) {div} 86400000000", "30000", "30000", "2405",
    ),
    "DOCS": EventSet("documents", "doc_id", "cast(substring(source, 4) as bigint)", "least(n_chars, 39999)", "doc_id", "20", "40000", "documents.doc_id"),
    "VECS": EventSet(
        "embeddings", "vec_id", _UNIT.format(e=_AXIS.format(n=1)), _UNIT.format(e=_AXIS.format(n=2)), "vec_id", "2000000", "2000000", "embeddings.vec_id",
    ),
}


def for_spark(expression: str) -> str:
    expression = re.sub(r"\{micros:(\w+)\}", r"unix_micros(cast(\1 as timestamp))", expression)
    return expression.replace("{div}", "div").replace("timestamp '", "timestamp_ntz '")


def for_oracle(expression: str) -> str:
    return re.sub(r"\{micros:(\w+)\}", r"epoch_us(\1)", expression).replace("{div}", "//").replace("element_at(embedding, ", "list_extract(embedding, ")


def _source(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    first, *more = source.split(" join ")
    df = read(spark, sf_dir, first)
    for part in more:
        name, _, on = part.partition(" on ")
        left, right = on.split(" = ")
        df = df.join(read(spark, sf_dir, name), F.col(left) == F.col(right))
    return df


def _denominator(spark: SparkSession, sf_dir: str, den: str):
    if den.isdigit():
        return int(den)
    table, column = den.split(".")
    return read(spark, sf_dir, table).agg((F.max(column) + 1).cast("long"))


def events(spark: SparkSession, sf_dir: str, name: str, grid: GridSpec, copies: int = 1, options: PlanOptions | None = None, where: str | None = None) -> DataFrame:
    """An event set on the lattice of a grid, inside its domain. WORLD is POSTS, each event ``copies`` times."""
    s = SETS["POSTS" if name == "WORLD" else name]
    df = _source(spark, sf_dir, s.source).filter(for_spark(where or s.where))
    view = event_view(df, *map(for_spark, (s.event_id, s.x, s.y, s.t, s.w)))
    out = snap(view, grid, *(_denominator(spark, sf_dir, d) for d in (s.x_den, s.y_den, s.t_den)))
    out = inside(out, grid, options or PlanOptions())
    return scale_up(out, copies, grid) if copies > 1 else out


def events_sql(name: str, grid: GridSpec, copies: int = 1, where: str | None = None) -> str:
    """The same set for the oracle: ``select event_id, x, y, t, w``."""
    s = SETS["POSTS" if name == "WORLD" else name]
    den = lambda d: d if d.isdigit() else "(select max({1}) + 1 from {0})".format(*d.split("."))
    step = lambda e, d, g: f"((({for_oracle(e)}) * {g * grid.sub}) // {den(d)})::bigint"
    sql = (
        f"select {for_oracle(s.event_id)} as event_id, {step(s.x, s.x_den, grid.gx)} as x, {step(s.y, s.y_den, grid.gy)} as y, "
        f"{step(s.t, s.t_den, grid.gt)} as t, {s.w}::bigint as w from {s.source} where {for_oracle(where or s.where)}"
    )
    keep = " and ".join(f"{c} between 0 and {g * grid.sub - 1}" for c, g in zip("xyt", grid.shape))
    sql = f"select * from ({sql}) where {keep}"
    if copies > 1:
        sql = (
            f"select event_id * {copies} + j as event_id, case when j = 0 then x else greatest(0, least({grid.gx * grid.sub - 1}, "
            f"x + (event_id * 31 + j * 17) % 7 - 3)) end as x, y, t, w from ({sql}), range({copies}) r(j)"
        )
    return sql
