"""SQL names for kernels and places, a cylinder table function, and user kernels.

The SQL functions stay expressions of the optimizer; the table function and the user kernel run Arrow batches in Python.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from cubedensity.functions.kernels import in_bar, in_disk, spatial, temporal
from cubedensity.operators.relational import VOXEL, accumulate, box, centre
from cubedensity.spec import Bandwidth, GridSpec, PlanOptions

FUNCTIONS = {
    "kernel_space": "(dx BIGINT, dy BIGINT, hx BIGINT) RETURNS BIGINT RETURN (hx - dx) * (hx - dx) * (hx - dy) * (hx - dy)",
    "kernel_time": "(dt BIGINT, ht BIGINT) RETURNS BIGINT RETURN (ht - dt) * (ht - dt)",
    "voxel_of": "(c BIGINT, sub INT) RETURNS INT RETURN CAST(c DIV sub AS INT)",
    "tile_of": "(v INT, n INT, cells INT) RETURNS INT RETURN CAST((CAST(v AS BIGINT) * n) DIV cells AS INT)",
    # bits of two numbers below 2^16 interleaved, for a layout that keeps neighbours together
    "morton": "(a INT, b INT) RETURNS BIGINT RETURN aggregate(sequence(0, 15), CAST(0 AS BIGINT), (z, i) -> z "
    "| shiftleft(CAST(getbit(a, i) AS BIGINT), 2 * i) | shiftleft(CAST(getbit(b, i) AS BIGINT), 2 * i + 1))",
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions of the session."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("cylinder", Cylinder)


@F.udtf
class Cylinder:
    """``cylinder(TABLE(events), gx, gy, gt, sub, hx, ht)``: a row (vx, vy, vt, term) for each voxel that an event covers."""

    @staticmethod
    def analyze(row: AnalyzeArgument, gx, gy, gt, sub, hx, ht) -> AnalyzeResult:
        return AnalyzeResult(StructType([*(StructField(v, IntegerType()) for v in VOXEL), StructField("term", LongType())]))

    def eval(self, row, gx, gy, gt, sub, hx, ht):
        def at(c, h, g):
            v = np.arange(max(0, (c - h) // sub - 1), min(g, (c + h) // sub + 2), dtype=np.int64)
            return v, v * sub + sub // 2 - c

        (vx, dx), (vy, dy), (vt, dt) = at(row["x"], hx, gx), at(row["y"], hx, gy), at(row["t"], ht, gt)
        ks = np.where(in_disk(dx[:, None], dy[None, :], hx), spatial("printed", dx[:, None], dy[None, :], hx), -1)
        kt = np.where(in_bar("closed_time", dt, ht), temporal("printed", dt, ht), -1)
        for i, j in zip(*np.nonzero(ks >= 0)):
            for k in np.flatnonzero(kt >= 0):
                yield int(vx[i]), int(vy[j]), int(vt[k]), int(ks[i, j] * kt[k]) * row["w"]


def user_kernel(function):
    """A kernel (u, v, w) -> weight on [-1, 1], given over numpy arrays, as a column function; tried on a grid first."""
    u = np.linspace(-1, 1, 5)
    probe = np.asarray(function(u, u, u), float)
    if probe.shape != u.shape or not np.isfinite(probe).all():
        raise ValueError("a kernel returns one finite number for each point of [-1, 1]")

    @pandas_udf("double")
    def weight(u: pd.Series, v: pd.Series, w: pd.Series) -> pd.Series:
        return pd.Series(np.asarray(function(u.to_numpy(), v.to_numpy(), w.to_numpy()), float))

    return weight


def user_scatter(events: DataFrame, grid: GridSpec, bw: Bandwidth, function, options: PlanOptions = PlanOptions(mass="double")) -> DataFrame:
    """Event-driven cube with a kernel of the user's own."""
    hs, half = bw.whole
    hx, ht = bw.lattice(grid)
    rows = events
    for v, c, h, g in zip(VOXEL, "xyt", (hs, hs, half), grid.shape):
        rows = rows.select("*", F.explode(box(c, h, g, grid.sub)).alias(v))
    dx, dy, dt = (centre(v, grid, options) - F.col(c) for v, c in zip(VOXEL, "xyt"))
    near = rows.filter(in_disk(dx, dy, hx) & in_bar(options.edge, dt, ht))
    term = user_kernel(function)(dx / hx, dy / hx, dt / ht) * F.col("w")
    return accumulate(near.select(*VOXEL, term.alias("term")), options)


@pandas_udf(ArrayType(LongType()))
def sum_arrays(blocks: pd.Series) -> list:
    """Element-wise sum of blocks of one length, as an aggregate."""
    return np.sum(np.stack([np.asarray(b, np.int64) for b in blocks]), axis=0).tolist()
