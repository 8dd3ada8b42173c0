"""Readers and writers of graphs: columnar tables, text edge lists, matrix-market text, JSON, CSV, ORC, partitioned folders."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.plans.graph import Graph

EDGE_SCHEMA = "src bigint, dst bigint"


def read_graph(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", weight: str | None = None) -> Graph:
    """A graph from a file or folder. Text forms: 'edgelist' (src dst, # comments) and 'mtx' (1-based, one size line)."""
    if fmt in ("edgelist", "mtx"):
        lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%].*)?$"))
        cells = F.split(F.trim("value"), r"\s+")
        pairs = lines.select(F.get(cells, 0).try_cast("bigint").alias("src"), F.get(cells, 1).try_cast("bigint").alias("dst"), F.size(cells).alias("k"))
        if fmt == "mtx":
            head = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%].*)?$")).limit(1)
            size = F.split(F.trim("value"), r"\s+")
            first = head.select(F.get(size, 0).try_cast("bigint").alias("src"), F.get(size, 1).try_cast("bigint").alias("dst"), F.size(size).alias("k"))
            pairs = pairs.exceptAll(first).select(F.col("src") - 1, F.col("dst") - 1).toDF("src", "dst")
        return Graph.from_edges(pairs, "src", "dst")
    reader = spark.read.format(fmt)
    if fmt in ("csv", "json"):
        reader = reader.schema(f"{src} bigint, {dst} bigint" + (f", {weight} double" if weight else ""))
    if fmt == "csv":
        reader = reader.option("header", True)
    return Graph.from_edges(reader.load(path), src, dst, weight=weight)


def write_graph(g: Graph, path: str, fmt: str = "parquet") -> None:
    if fmt == "edgelist":
        g.edges.select(F.concat_ws(" ", "src", "dst").alias("value")).write.text(path)
    elif fmt == "csv":
        g.edges.write.option("header", True).csv(path)
    elif fmt == "noop":
        g.edges.write.format("noop").mode("overwrite").save()
    else:
        g.edges.write.format(fmt).save(path)


def write_result(df: DataFrame, path: str, fmt: str = "parquet", partition_by: str | None = None) -> None:
    w = df.write.format(fmt)
    (w.partitionBy(partition_by) if partition_by else w).save(path)


def read_stream_edges(spark: SparkSession, folder: str, schema: str = EDGE_SCHEMA, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
