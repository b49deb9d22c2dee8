"""Connected components by alternating star contractions, as DataFrame rounds with reliable checkpoints."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import durable, tidy

#: edges that are followed to their end on the driver instead of in more rounds: some 3 MB
FEW = 200_000


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction: every node hands its larger (or smaller) neighbours to the least node it sees."""
    if large:
        near = edges.union(edges.select("v", "u"))
    else:
        near = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = near.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    moved = near.join(least, "u")
    if large:
        out = moved.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = moved.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(
            least.filter("u <> m").select(F.col("u"), F.col("m").alias("v"))
        )
    return out.filter("u <> v").distinct()


def least_reached(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(nodes, roots)`` of the edges (u, v): every node, with the least node that it reaches."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[a], root[b])
        if (low == root[a]).all() and (low == root[b]).all():
            return nodes, nodes[root]
        # both roots of an edge get the lesser one, then every node the root of its root
        was = root.copy()
        np.minimum.at(root, was[a], low)
        np.minimum.at(root, was[b], low)
        while (root != root[root]).any():
            root = root[root]


def components(edges: DataFrame, few: int = FEW) -> DataFrame:
    """``edges(u, v)`` of longs -> ``(node, root)``: each node that has an edge, with the least node it reaches.

    Only nodes with edges come back. The number of rounds grows with the logarithm of the graph; links stay on
    the executors and each round is a checkpoint, so a lost executor costs one round at most. Once no more than ``few``
    edges are left, they are followed on the driver: rounds over small tables write more files than rows.
    """
    spark = edges.sparkSession
    now = durable(edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    many, mark = now.count(), None
    while many > few:
        now = durable(_star(_star(now, True), False))
        new = now.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("h")).first()
        if new == mark:
            return _named(now)
        many, mark = new.n, new
        tidy(spark)
    held = now.toArrow()
    nodes, roots = least_reached(*(held.column(c).to_numpy() for c in ("u", "v")))
    del now, held
    tidy(spark)
    return spark.createDataFrame(pa.table({"node": nodes, "root": roots}))


def _named(stars: DataFrame) -> DataFrame:
    return stars.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
        stars.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )
