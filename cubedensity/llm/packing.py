"""Packing by optimal length buckets.

The lengths of all documents form one global histogram (exact up to 32,768, in steps of about one in 64 above, each
with the largest length in it, so its size is bounded). Dynamic programming over it finds the boundaries of at most
``buckets`` buckets with the least padding, when every document is padded to the largest length in its bucket. Inside a
bucket, batches of a token budget are formed: rows are dealt by hash into shares of a bounded size, and each share is
cut into batches by its own order, so no bucket is ever sorted in one task; the last batch of a share may be short.

Lengths are counted in white-space words here, or in any token count given as an expression.

Inputs: null and empty texts have length 0 and sit in the first bucket; a text longer than the budget is a batch of
its own; repeated rows are packed each, dealt over the shares, and are interchangeable, as the only ties; an empty table
gives none; extra columns, of whatever name, are not returned.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from cubedensity.llm.common import durable

FINE = 32_768
BUDGET = 65_536
BUCKETS = 16
BATCHES_PER_SHARE = 64


def word_count(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


def bin_of(length: Column) -> Column:
    """The bin of a length: the length itself up to ``FINE``, the next multiple of a growing step above."""
    step = F.pow(F.lit(2.0), F.ceil(F.log2(length.cast("double"))).cast("int") - 7).cast("long")
    return F.when(length <= FINE, length).otherwise(F.ceil(length / step).cast("long") * step)


def histogram(lengths: DataFrame) -> DataFrame:
    """``(bin, edge, rows)``: the largest length of each bin and its rows."""
    return lengths.groupBy(bin_of(F.col("n_tokens")).alias("bin")).agg(F.max("n_tokens").alias("edge"), F.count("*").alias("rows"))


def boundaries(edges: list[int], rows: list[int], buckets: int) -> list[int]:
    """Upper boundaries of at most ``buckets`` buckets with the least padded size. ``edges`` ascend.

    With ``below[i]`` rows in the first i bins, closing a bucket at bin i that begins behind bin j costs
    ``edges[i] * (below[i] - below[j])``: for each j a straight line over the edge. Lines come with falling slopes and
    edges rise, so the lowest line is followed along the hull, in time in proportion to the bins.
    """
    if not edges:
        return []
    n = len(edges)
    below = [0, *np.cumsum(np.array(rows, object)).tolist()]
    cost = [0, *(e * b for e, b in zip(edges, below[1:]))]
    back = [[0] * (n + 1)]
    for _ in range(min(buckets, n) - 1):
        new, by, hull, at = [0] * (n + 1), [0] * (n + 1), [], 0
        for i in range(1, n + 1):
            j = i - 1
            while len(hull) > 1:
                a, b = hull[-2], hull[-1]
                if (cost[j] - cost[a]) * (below[b] - below[a]) > (cost[b] - cost[a]) * (below[j] - below[a]):
                    break
                hull.pop()
            hull.append(j)
            at, x = min(at, len(hull) - 1), edges[i - 1]
            while at + 1 < len(hull) and cost[hull[at + 1]] - x * below[hull[at + 1]] <= cost[hull[at]] - x * below[hull[at]]:
                at += 1
            by[i] = hull[at]
            new[i] = cost[hull[at]] + x * (below[i] - below[hull[at]])
        back.append(by)
        cost = new
    found, i = [], n
    for by in reversed(back):
        if i <= 0:
            break
        found.append(edges[i - 1])
        i = by[i]
    return sorted(set(found))


def _with_copies(lengths: DataFrame) -> DataFrame:
    """``lengths`` with a column that tells equal rows apart by where they stand in the written table, and is 0 for all others."""
    again = durable(lengths.groupBy("doc_id", "_h").agg(F.count("*").alias("n")).filter("n > 1").select(F.col("doc_id").alias("_id"), F.col("_h").alias("_h2")))
    if again.isEmpty():
        return lengths.withColumn("_copy", F.lit(0).cast("long"))
    placed = lengths.withColumn("_at", F.monotonically_increasing_id())
    met = placed.join(again, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_h") == F.col("_h2")), "left")
    return durable(met.select("doc_id", "n_tokens", "_h", F.when(F.col("_h2").isNotNull(), F.col("_at")).otherwise(0).alias("_copy")))


def pack(docs: DataFrame, tokens: Column | None = None, buckets: int = BUCKETS, budget: int = BUDGET) -> DataFrame:
    """``(doc_id, n_tokens, bucket, bucket_length, padding, batch_id, slot)`` for every row of ``docs``."""
    spark = docs.sparkSession
    lengths = durable(
        docs.select("doc_id", (word_count() if tokens is None else tokens.cast("long")).alias("n_tokens"), F.xxhash64("doc_id", "text").alias("_h"))
    )
    lengths = _with_copies(lengths)
    counted = sorted((r["edge"], r["rows"]) for r in histogram(lengths).collect())  # some 34,000 bins at most
    cut = boundaries([x for x, _ in counted], [n for _, n in counted], buckets)
    rows_in = [sum(n for x, n in counted if lo < x <= hi) for lo, hi in zip([-1, *cut], cut)]
    per_batch = [max(1, budget // max(1, hi)) for hi in cut]
    shares = [max(1, -(-n // (p * BATCHES_PER_SHARE))) for n, p in zip(rows_in, per_batch)]
    kind = T.StructType([T.StructField(x, T.LongType()) for x in ("bucket", "bucket_length", "per_batch", "shares")])
    plan = F.broadcast(spark.createDataFrame([(i, c, p, s) for i, (c, p, s) in enumerate(zip(cut, per_batch, shares))], kind))  # one row a bucket
    number = F.aggregate(F.array(*map(F.lit, cut or [0])), F.lit(0).cast("long"), lambda a, c: a + (F.col("n_tokens") > c).cast("long"))
    placed = lengths.withColumn("bucket", number).join(plan, "bucket").withColumn("share", F.pmod(F.xxhash64("_h", "_copy"), F.col("shares")))
    order = Window.partitionBy("bucket", "share").orderBy("n_tokens", "doc_id", "_h")
    at = F.row_number().over(order) - 1
    return placed.withColumn("_at", at).select(
        "doc_id",
        "n_tokens",
        "bucket",
        "bucket_length",
        (F.col("bucket_length") - F.col("n_tokens")).alias("padding"),
        F.concat_ws("-", "bucket", "share", F.floor(F.col("_at") / F.col("per_batch"))).alias("batch_id"),
        F.pmod("_at", "per_batch").cast("int").alias("slot"),
    )
