"""Sharding by sampled splitters. DataFrame functions only.

A size-weighted sample of the keys gives splitters at its quantiles, which cut the key order into
many fine ranges of near-equal bytes. A range that is overfull in bytes or rows (a large group of
equal texts) is subdivided by the hash of the document id. The ranges are then dealt to the shards,
largest first, each to the lightest shard, so that shard sizes are near equal. What the driver sees is
bounded by the number of ranges, a parameter; rows move once, to be numbered within their range.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphloom.plans.scratch import Scratch

_CELLS = 12  # leading bits of a key by which its splitters are looked up


def _uniform(*columns: str | Column, salt: int) -> Column:
    """A number in [0, 1) decided by the columns."""
    return F.shiftrightunsigned(F.xxhash64(*columns, F.lit(salt)), 11).cast("double") / float(1 << 53)


def sample_splitters(sized: DataFrame, ranges: int, per_range: int) -> list[int]:
    """Keys at quantiles of a sample drawn with chance in proportion to size; about ranges * per_range keys reach the driver."""
    total = sized.agg(F.sum("size").cast("double")).first()[0] or 0.0
    if not total:
        return []
    chance = F.col("size") * (ranges * per_range / total)
    keys = sorted(r.key for r in sized.where(_uniform("doc_id", salt=17) < chance).select("key").collect())
    return sorted({keys[i] for i in range(per_range, len(keys), per_range)} if len(keys) > ranges else set(keys))


def _cell(key: Column) -> Column:
    return F.shiftright(key, 64 - _CELLS)


def range_of(df: DataFrame, splitters: list[int]) -> DataFrame:
    """Adds range: how many splitters are at most the key. The lookup table has 2^12 rows."""
    cells: dict[int, list[int]] = {}
    for s in splitters:
        cells.setdefault(s >> (64 - _CELLS), []).append(s)
    rows, before = [], 0
    for cell in range(-(1 << (_CELLS - 1)), 1 << (_CELLS - 1)):
        own = cells.get(cell, [])
        rows.append((cell, before, own))
        before += len(own)
    lookup = F.broadcast(df.sparkSession.createDataFrame(rows, "cell bigint, before int, own array<bigint>"))
    with_cell = df.withColumn("cell", _cell(F.col("key")))
    return with_cell.join(lookup, "cell").withColumn("range", F.col("before") + F.size(F.filter("own", lambda s: s <= F.col("key")))).drop("cell", "before", "own")


def shard_documents(docs: DataFrame, shards: int = 24, ranges_per_shard: int = 64, samples_per_range: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard: every row in exactly one place, by the law `bytes`.

    Size is the UTF-8 bytes of the text plus 8; null texts count as empty. Equal texts share a key and
    so a range, unless the range is overfull. Repeated rows keep a slot each. No rows in, no rows out.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "shards")
    text = F.coalesce(docs[text_col], F.lit(""))
    sized = scratch.save(
        docs.select(docs[id_col].cast("bigint").alias("doc_id"), (F.octet_length(text) + 8).cast("bigint").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("key")), "sized"
    )
    ranges = shards * ranges_per_shard
    ranged = range_of(sized, sample_splitters(sized, ranges, samples_per_range))
    weights = ranged.groupBy("range").agg(F.sum("size").alias("bytes"), F.count("*").alias("n"))
    bounds = weights.agg(F.sum("bytes"), F.sum("n")).first()
    most_bytes, most_rows = (max(1.0, (x or 0) / ranges) for x in bounds)
    parts = F.ceil(F.greatest(F.col("bytes") / most_bytes, F.col("n") / most_rows) / 2).cast("int")
    split = F.broadcast(weights.where(F.greatest(F.col("bytes") / most_bytes, F.col("n") / most_rows) > 2).select("range", parts.alias("parts")))
    placed = ranged.join(split, "range", "left").withColumn("part", F.floor(_uniform("doc_id", salt=29) * F.coalesce("parts", F.lit(1))).cast("int"))
    loads = placed.groupBy("range", "part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).collect()  # at most 3 * ranges rows
    heap = [(0, s, 0) for s in range(shards)]
    dealt = []
    for r in sorted(loads, key=lambda r: (-r.bytes, r.range, r.part)):
        taken, shard, rows = heap[0]
        heapq.heapreplace(heap, (taken + r.bytes, shard, rows + r.n))
        dealt.append((r.range, r.part, shard, rows))
    deal = F.broadcast(spark.createDataFrame(dealt, "range int, part int, shard int, before bigint"))
    inside = F.row_number().over(Window.partitionBy("range", "part").orderBy("key", "doc_id"))
    return (
        placed.withColumn("inside", inside)
        .join(deal, ["range", "part"])
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("before") + F.col("inside") - 1).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )


def write_shards(docs: DataFrame, placed: DataFrame, path: str) -> None:
    """Write the documents below path, one folder a shard, in slot order."""
    out = docs.join(placed.select("doc_id", "shard", "slot"), "doc_id")
    out.repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
