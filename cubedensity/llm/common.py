"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def durable(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the shared folder of the session.

    The folder is the one named in ``spark.checkpoint.dir``; where that is unset, a temporary folder is used on one machine,
    and a cluster is refused, since its executors would not share that folder.
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def written(df: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """``df`` as a compressed table in the shared folder of the session, and what removes it.

    For wide tables that are read several times, a few columns each: a checkpoint holds rows as they are in memory, some
    three times the bytes, and every reading takes all columns. Types that such files do not hold are checkpointed.
    """
    spark = df.sparkSession
    if any(re.search("void|interval|variant", kind) for _, kind in df.dtypes):
        return durable(df), lambda: None
    place = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(place)

    def remove() -> None:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(place)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    return spark.read.parquet(place), remove


def tidy(spark: SparkSession) -> None:
    """Let the engine's cleaner remove shuffle and checkpoint files that nothing refers to any more.

    It acts when the driver collects garbage, which a driver of a long run of small jobs seldom does by itself.
    """
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def released(run):
    """``run`` for ``mapInArrow``, after which its worker gives back what it freed.

    Workers live on between stages, and the allocators of Arrow and the C library keep freed memory, so without this every
    worker of an executor holds the most that any stage took so far.
    """

    def whole(batches):
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # not every C library has it
            if trim:
                trim(0)

    return whole


def shared_folder(spark: SparkSession) -> str:
    """The folder that the session names for files that all of the cluster share; one of this machine only in local mode."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named and not re.match(r"local(\[|$)", sc.master):
        raise RuntimeError("spark.checkpoint.dir is not set: it must name a folder that the driver and all executors share")
    return (named or tempfile.mkdtemp(prefix="checkpoint-")).rstrip("/")


def bind(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once per row, as a let-expression."""
    return F.transform(F.array(value), body)[0]


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def content_key(id_col: str = "doc_id", text_col: str = "text") -> list[Column]:
    """Key of a row by content: equal rows share it, rows with one id and different texts do not."""
    return [F.col(id_col).alias("_kid"), F.xxhash64(F.col(text_col), F.col(text_col).isNull()).alias("_kh")]


def content_match(left: DataFrame, right: DataFrame) -> Column:
    """Null-safe equality of the keys that content_key made."""
    return left["_kid"].eqNullSafe(right["_kid"]) & (left["_kh"] == right["_kh"])


#: bits of a bitmap of marked keys, at most: 16 MB
MOST_MARKS = 1 << 27
_WORD = 32_768  # bits of one bitmap of the engine


def where_marked(keyed: DataFrame, marked: DataFrame, *key: str) -> tuple[DataFrame, DataFrame]:
    """``keyed`` in two parts by a key, that of content_key as a rule: rows that may have one of ``marked``'s, and rows that
    have none for certain.

    The second part needs no join, so few rows are shuffled where few are marked. The keys are sent as a bitmap over
    their hashes, 16 bits a key and ``MOST_MARKS`` at most; a fuller bitmap lets more rows into the first part, and loses none.
    """
    bits = min(MOST_MARKS, max(_WORD, 1 << (16 * max(1, marked.count()) - 1).bit_length()))
    slot = F.pmod(F.xxhash64(*(key or ("_kid", "_kh"))), F.lit(bits))
    place = [F.floor(slot / _WORD).alias("_word"), F.pmod(slot, F.lit(_WORD)).alias("_spot")]
    words = marked.select(*place).groupBy("_word").agg(F.bitmap_construct_agg("_spot").alias("_marks"))
    byte = F.conv(F.hex(F.substring("_marks", F.floor(F.col("_spot") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = F.coalesce(F.getbit(byte, F.pmod("_spot", F.lit(8)).cast("int")) == 1, F.lit(False))
    told = keyed.select("*", *place).join(F.broadcast(durable(words)), "_word", "left").withColumn("_hit", hit)
    return tuple(told.filter(c).select(*keyed.columns) for c in (F.col("_hit"), ~F.col("_hit")))


#: rows of a list that is sent to all tasks, at most: some 16 MB
SENT = 1_000_000


def sent(rows: DataFrame) -> DataFrame:
    """A written table, to be broadcast if it has no more than ``SENT`` rows, and joined as any other beyond."""
    return F.broadcast(rows) if rows.limit(SENT + 1).count() <= SENT else rows
