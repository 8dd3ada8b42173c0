"""Joins that SQL has no operator for, as compositions of equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(df: DataFrame, bands: DataFrame, value: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows of df with the bands [lo, hi) that hold value. Bands are listed under each bucket of `width` they touch, then equi-joined."""
    buckets = F.sequence(F.floor(F.col(lo) / width), F.greatest(F.floor(F.col(lo) / width), F.ceil(F.col(hi) / width) - 1))
    listed = bands.withColumn("_bucket", F.explode(buckets))
    keyed = df.withColumn("_bucket", F.floor(F.col(value) / width))
    return keyed.join(listed, "_bucket").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_bucket")


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, take: str) -> DataFrame:
    """Left rows with `take` of the last right row at or before them, for each key. One exchange and one sort: union and a running last."""
    rights = right.select(by, ts, F.col(take), F.lit(0).alias("_side"))
    lefts = left.withColumn("_side", F.lit(1))
    both = lefts.unionByName(rights, allowMissingColumns=True)
    run = Window.partitionBy(by).orderBy(ts, "_side", F.col(take)).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = F.last(F.when(F.col("_side") == 0, F.col(take)), ignorenulls=True).over(run)
    return both.withColumn(take, found).where("_side = 1").drop("_side")


def interval_join(left: DataFrame, right: DataFrame, by: str, at: str, within: int) -> DataFrame:
    """Pairs of one key whose right time is in [left time, left time + within]. Time buckets keep a busy key's rows apart."""
    cell = F.floor(F.col(at) / within)
    a = left.withColumnRenamed(at, "_left").withColumn("_cell", F.explode(F.array(F.floor(F.col("_left") / within), F.floor(F.col("_left") / within) + 1)))
    b = right.withColumn("_cell", cell).withColumnRenamed(at, "_right")
    return a.join(b, [by, "_cell"]).where((F.col("_right") >= F.col("_left")) & (F.col("_right") <= F.col("_left") + within)).drop("_cell", "_left", "_right")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int) -> DataFrame:
    """Inner join of a side with hot keys (left) and one without: left rows get a salt, right rows are repeated for each."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return a.join(b, [on, "_salt"]).drop("_salt")
