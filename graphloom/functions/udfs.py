"""User-defined functions for SQL users: Arrow scalar, grouped, partition, cogrouped, aggregate and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StructType  # objects: a DDL string would need a session at import

from graphloom.functions.kernels import common_counts
from graphloom.sources.generators import UrandSource


@F.arrow_udf(LongType())
def intersect_count_arrow(a: pa.Array, b: pa.Array) -> pa.Array:
    """Common members of two sorted neighbour lists, by binary search in Arrow buffers."""
    return pa.array(common_counts(a, b))


@F.pandas_udf(DoubleType())
def entropy(n: pd.Series) -> float:
    """Shannon entropy of counts (grouped aggregate; a group must fit a task)."""
    p = n.to_numpy(float)
    p = p / p.sum()
    return float(-(p * np.log(p)).sum())


@F.udtf(returnType=StructType().add("src", LongType()).add("dst", LongType()))
class Arcs:
    """Table function: a vertex and its neighbour list to arcs."""

    def eval(self, id: int, nbrs: list[int]):  # noqa: A002
        for d in nbrs or ():
            yield id, d


def partition_degrees(edges: DataFrame) -> DataFrame:
    """(id, deg) with the partial counts of each partition made in Arrow; the final sum is Spark's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                ids, n = np.unique(b.column(0).to_numpy(), return_counts=True)
                yield pa.RecordBatch.from_pydict({"id": ids, "deg": n.astype(np.int64)})

    return edges.select("src").mapInArrow(run, "id bigint, deg bigint").groupBy("id").agg(F.sum("deg").alias("deg"))


def grouped_triples(edges: DataFrame) -> DataFrame:
    """(id, n): pairs of neighbours of each vertex, by a grouped Arrow function."""

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        n = table.num_rows
        return pa.table({"id": [key[0].as_py()], "n": pa.array([n * (n - 1) // 2], pa.int64())})

    return edges.groupBy("src").applyInArrow(run, "id bigint, n bigint")


def cogrouped_shares(ranks: DataFrame, edges: DataFrame) -> DataFrame:
    """(id, value): contributions of co-grouped ranks and edges of one source block."""

    def run(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        value = dict(zip(left["id"].to_pylist(), left["rank"].to_pylist(), strict=True))
        deg: dict[int, int] = {}
        for s in right["src"].to_pylist():
            deg[s] = deg.get(s, 0) + 1
        rows = [(d, value.get(s, 0.0) / deg[s]) for s, d in zip(right["src"].to_pylist(), right["dst"].to_pylist(), strict=True)]
        return pa.table({"id": pa.array([r[0] for r in rows], pa.int64()), "value": pa.array([r[1] for r in rows], pa.float64())})

    block = lambda c: F.pmod(F.xxhash64(c), F.lit(8)).alias("block")
    a, b = ranks.select(block("id"), "id", "rank"), edges.select(block("src"), "src", "dst")
    return a.groupBy("block").cogroup(b.groupBy("block")).applyInArrow(run, "id bigint, value double").groupBy("id").agg(F.sum("value").alias("value"))


def register(spark: SparkSession) -> None:
    """Make the functions and the generator source known to SQL."""
    spark.udf.register("graph_intersect_count", intersect_count_arrow)
    spark.udf.register("graph_entropy", entropy)
    spark.udtf.register("graph_arcs", Arcs)
    spark.dataSource.register(UrandSource)
