"""The corpus pipeline: five stages over documents, each written as Parquet and reread by the next."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.llm.bpe import vocabulary
from graphloom.llm.common import keep_by_score, table
from graphloom.llm.lines import remove_repeated_lines
from graphloom.llm.packing import pack_documents
from graphloom.llm.quality import fit_quality
from graphloom.llm.set_join import near_duplicate_components
from graphloom.llm.toxicity import fit_toxicity
from graphloom.plans.scratch import Scratch


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score of 0.5 or more go. The model learns from the corpus' own labelled rows."""
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))
    return keep_by_score(docs, model.scorer, lambda score: score < 0.5)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a quality score below 0.3 go."""
    model = fit_quality(docs, table(spark, sf_dir, "labels"))
    return keep_by_score(docs, model.scorer, lambda score: score >= 0.3)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated lines go, short ones too, and with them documents that had text and are left with none."""
    cleaned = remove_repeated_lines(docs, short=True)
    emptied = (F.col("n_removed") > 0) & (F.trim(F.regexp_replace("text", r"\s+", " ")) == "")
    return cleaned.where(~F.coalesce(emptied, F.lit(False))).withColumn("n_chars", F.length("text").cast("bigint")).select(*docs.columns)


def minhash(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays: five-word shingles, similarity of 0.8 or more.

    Rows are decided one by one: where ids are null or repeat, rows are numbered in the order of doc_id,
    null ones last, and the numbers stand for the ids.
    """
    rows, ids = docs.agg(F.count("*"), F.count_distinct("doc_id")).first()
    if rows == ids:
        groups = near_duplicate_components(docs, k=5, numerator=80, denominator=100)
        return docs.join(groups.where("kept").select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    row = f"row_{uuid.uuid4().hex}"  # no column of docs
    ordered = docs.orderBy(F.col("doc_id").asc_nulls_last(), "text").withColumn(row, F.monotonically_increasing_id())
    numbered = Scratch(docs.sparkSession, "rows").save(ordered, "numbered")
    groups = near_duplicate_components(numbered.select(F.col(row).alias("doc_id"), "text"), k=5, numerator=80, denominator=100)
    return numbered.join(groups.where("kept").select(F.col("doc_id").alias(row)), row, "left_semi").select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2048 tokens."""
    return pack_documents(docs, vocabulary())


STAGES = [("toxicity", toxicity), ("quality", quality), ("line_dedup", line_dedup), ("minhash", minhash), ("packing", packing)]

#: No stage but the last joins can be written in SQL; tests/llm holds the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, f"pipeline-{uuid.uuid4().hex[:8]}")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return docs
