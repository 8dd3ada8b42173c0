"""Queries of the training-data operators over the given tables: thin digests of the operators' outputs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.llm.bpe import round_trip_digests, vocabulary
from graphloom.llm.chroma import fingerprint_column, link_recordings, melody
from graphloom.llm.common import table
from graphloom.llm.lattice import near_duplicate_vectors
from graphloom.llm.lines import remove_repeated_lines
from graphloom.llm.packing import pack_documents
from graphloom.llm.quality import classify_quality
from graphloom.llm.set_join import near_duplicate_components
from graphloom.llm.sharding import shard_documents
from graphloom.llm.toxicity import classify_toxicity
from graphloom.llm.url_rules import judge_sql, judge_urls


def op1_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def op2_chosen_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_components(table(spark, sf_dir, "documents"))


def op3_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages"))


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip_digests(table(spark, sf_dir, "documents"), vocabulary()).drop("ids_crc32")


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cleaned = remove_repeated_lines(table(spark, sf_dir, "documents"), short=True)
    return cleaned.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), vocabulary())


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_chroma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every turn of every conversation as a recording, with its class and its number of links; turns of conversations divisible by 100 are the queries."""
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("rec_id"), "text")
    printed = fingerprint_column(turns, "rec_id", "text", decode=melody)
    return link_recordings(printed, F.floor(F.col("rec_id") / 1000) % 100 == 0)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(table(spark, sf_dir, "documents"))


def queries() -> dict:
    own = (op1_lattice, op2_chosen_path, op3_url_rules, op4_quality, op5_bpe, op6_line_dedup, op7_packing, op8_toxicity, op9_chroma, op10_sharding)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op3_url_rules": judge_sql()}
