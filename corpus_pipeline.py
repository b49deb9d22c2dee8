"""The corpus pipeline: stages over ``documents``, each written as Parquet and read again before the next.

toxicity -> line templates -> near duplicates -> benchmark matches -> packing. All but the last return the columns of
their input; each acts on all rows that its predecessor kept. Models and windows are the operators' own defaults.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from cubedensity.llm import decontam, linededup, packing, simhash, toxicity
from cubedensity.llm.common import shared_folder, table


#: similarity from which texts that share a line count as copies of one text
COPIES = 0.5


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.reject_toxic(docs, table(spark, sf_dir, "labels"))


def line_templates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    # the next stage keeps one text of each group of copies, so lines that only copies share must stay until then
    return linededup.drop_templates(docs, copies=COPIES)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


def benchmark_matches(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def length_buckets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [
    ("toxicity", toxic),
    ("line_templates", line_templates),
    ("near_duplicates", near_duplicates),
    ("benchmark_matches", benchmark_matches),
    ("length_buckets", length_buckets),
]

#: learned scores, fingerprints and templates have no form in SQL; the stages are tested against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, folder = table(spark, sf_dir, "documents"), f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        path = f"{folder}/{k}_{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict:
    return {} if ORACLE_SQL is None else {"pipeline": ORACLE_SQL}
