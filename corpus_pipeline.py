"""Corpus pipeline: five of the training-data operators in a row, each on all that its predecessor kept.

Stages take (spark, docs, sf_dir) and return a DataFrame; all but the last return the columns of documents. Rows with a
null id pass the stages that decide by id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orbitgraph.llm import decontam, linededup, neardup, packing, quality
from orbitgraph.llm.common import broadcast_if_few, materialise, spread
from orbitgraph.session import ship

WINDOW = 2048
NEAR_PERCENT = 80
BROADCAST_GONE = 1_000_000  # ids that may be broadcast; beyond, they join by a shuffle


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the quality rules reject."""
    judged = quality.quality_rules(docs, out="__quality")
    return judged.where(F.col("__quality.kept")).select(*docs.columns)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines repeated across documents; texts and lengths change."""
    ship(spark)
    out = linededup.drop_lines(docs).withColumn("text", F.col("kept_text"))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near duplicates."""
    ship(spark)
    found = neardup.near_duplicates(docs.select("doc_id", "text"), percent=NEAR_PERCENT)
    gone = materialise(found.where(~F.col("kept")).select(F.col("doc_id").alias("__gone")).where(F.col("__gone").isNotNull()).distinct(), "near-gone")
    gone = broadcast_if_few(gone, BROADCAST_GONE)
    return docs.join(gone, F.col("doc_id") == F.col("__gone"), "left_anti")


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark passage."""
    ship(spark)
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return decontam.decontaminate(docs, benchmark)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences."""
    ship(spark)
    return packing.pack(docs.select("doc_id", "text"), window=WINDOW)


STAGES = [
    ("quality_rules", quality_stage),
    ("line_dedup", line_stage),
    ("near_duplicates", near_stage),
    ("decontamination", decontamination_stage),
    ("packing", packing_stage),
]

ORACLE_SQL = None  # likelihood, edit verification and token ids have no SQL; tests compare with brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each result written as Parquet in the shared folder and read again."""
    ship(spark)
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return materialise(STAGES[-1][1](spark, docs, sf_dir), f"stage-{STAGES[-1][0]}")
