"""Synthetic graphs: uniform random and recursive-quadrant, drawn by md5 so that any engine can repeat them."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from graphloom.plans.graph import md5_32

QUADRANTS = (0.57, 0.19, 0.19, 0.05)


def _undirected(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("s", "d").alias("src"), F.greatest("s", "d").alias("dst")).where("src <> dst").distinct()


def urand(spark: SparkSession, k: int, degree: int = 32, ids: DataFrame | None = None) -> DataFrame:
    """2^k vertices and 2^k * degree / 2 drawn pairs, or one for each row of ids; one row an undirected edge, loops and repeats dropped."""
    i = F.col("id").cast("string")
    draw = lambda tag: F.pmod(md5_32(F.concat(F.lit(f"{tag}:"), i)), F.lit(1 << k))
    return _undirected((spark.range((1 << k) * degree // 2) if ids is None else ids).select(draw("s").alias("s"), draw("d").alias("d")))


def kron(spark: SparkSession, k: int, degree: int = 32, quadrants: tuple[float, ...] = QUADRANTS, ids: DataFrame | None = None) -> DataFrame:
    """Each bit pair of an edge falls into one quadrant of the adjacency matrix by the given shares."""
    a, b, c = (int(sum(quadrants[: i + 1]) * 4294967296) for i in range(3))
    i = F.col("id").cast("string")
    hashes = F.array(*[F.md5(F.concat(F.lit("k:"), i, F.lit(f":{g}")).cast("binary")) for g in range((k + 3) // 4)])
    digits = lambda bit: F.substr(F.get(F.col("h"), (bit / 4).cast("int")), 8 * (bit % 4) + 1, F.lit(8))
    draws = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda bit: F.conv(digits(bit), 16, 10).cast("bigint"))
    drawn = (spark.range((1 << k) * degree // 2) if ids is None else ids).select(hashes.alias("h")).select(draws.alias("u"))
    power = lambda bit: F.call_function("shiftleft", F.lit(1).cast("bigint"), bit)
    add = lambda end: F.aggregate(F.transform("u", end), F.lit(0).cast("bigint"), lambda x, y: x + y)
    zero = F.lit(0).cast("bigint")
    s = add(lambda u, bit: F.when(u >= b, power(bit)).otherwise(zero))
    d = add(lambda u, bit: F.when(((u >= a) & (u < b)) | (u >= c), power(bit)).otherwise(zero))
    return _undirected(drawn.select(s.alias("s"), d.alias("d")))


class UrandSource(DataSource):
    """spark.read.format('urand').option('k', 12): the draws of urand() before dedup, generated where they are read. option('rows', n): ids 0..n-1."""

    @classmethod
    def name(cls) -> str:
        return "urand"

    def schema(self) -> str:
        return "id bigint, src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return _UrandReader(int(self.options.get("k", 10)), int(self.options.get("degree", 32)), int(self.options.get("slices", 8)), int(self.options.get("rows", -1)))


class _Slice(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _UrandReader(DataSourceReader):
    def __init__(self, k: int, degree: int, slices: int, rows: int = -1):
        self.k, self.n, self.slices = k, (1 << k) * degree // 2 if rows < 0 else rows, slices

    def partitions(self) -> list[_Slice]:
        return [_Slice(self.n * i // self.slices, self.n * (i + 1) // self.slices) for i in range(self.slices)]

    def read(self, partition: _Slice) -> Iterator[pa.RecordBatch]:
        draw = lambda tag, i: int(hashlib.md5(f"{tag}:{i}".encode()).hexdigest()[:8], 16) % (1 << self.k)
        for lo in range(partition.lo, partition.hi, 10_000):
            at = range(lo, min(lo + 10_000, partition.hi))
            yield pa.RecordBatch.from_pydict({"id": pa.array(at, pa.int64()), "src": pa.array([draw("s", i) for i in at], pa.int64()), "dst": pa.array([draw("d", i) for i in at], pa.int64())})
