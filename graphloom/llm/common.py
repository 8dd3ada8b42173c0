"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """run, after which the Python worker hands its free memory back: workers idle on beside the next task's."""

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            trim()

    return held


def trim() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def by_bytes(df: DataFrame) -> DataFrame:
    """df, whose rows go to Python about 4 MB at a time: a setting that a running session takes, and that only bounds Arrow batches."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(4 << 20))
    return df


def table(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def arrow_rows(schema: str, columns: dict) -> pa.RecordBatch:
    """A record batch from Python lists or numpy arrays, typed by a DDL-like list of name:type."""
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "binary": pa.binary(), "boolean": pa.bool_()}
    fields = [f.split() for f in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(columns[n], kinds[t]) for n, t in fields], names=[n for n, _ in fields])


def ints(column: pa.Array) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False)


def texts(column: pa.Array) -> list[str]:
    """Strings of a column, null as empty."""
    return [x or "" for x in column.to_pylist()]


def slices(b: pa.RecordBatch, text_at: int, most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The rows of a batch, some at a time: texts of about `most` bytes, or one longer text."""
    if not b.num_rows:
        return
    ends = np.cumsum(ints(pc.fill_null(pc.binary_length(b.column(text_at)), 0)).astype(np.int64) + 1)
    lo = 0
    while lo < b.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, "right")))
        yield b.slice(lo, hi - lo)
        lo = hi


def joined_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column end to end, and the n+1 offsets; nulls are empty."""
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def by_sorted_group(df: DataFrame, keys: list[str], order: list[str], kernel: Callable[[pa.Table], pa.RecordBatch | None], schema: str, least: int = 2) -> DataFrame:
    """Run kernel on each group of at least `least` rows as an Arrow table, streaming over sorted partitions.

    Cheaper than applyInArrow where most groups are tiny: smaller groups are passed over by array
    operations, the others cost one Python call, and results are joined before they go back. A group is
    held in memory whole, so callers bound it (blocked_pairs).
    """
    dealt = by_bytes(df).repartition(*[F.col(k) for k in keys]).sortWithinPartitions(*keys, *order)
    width = len(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []  # the group that the next batch may go on with
        last = None
        results: list[pa.RecordBatch] = []

        def close(t: pa.Table) -> None:
            if t.num_rows >= least and (out := kernel(t)) is not None:
                results.append(out)

        def flush(rows: int) -> Iterator[pa.RecordBatch]:
            if results and sum(r.num_rows for r in results) >= rows:
                yield pa.concat_batches(results)
                results.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            marks = np.stack([ints(batch.column(i)) for i in range(width)])
            cuts = np.flatnonzero((marks[:, 1:] != marks[:, :-1]).any(axis=0)) + 1
            start, end = np.r_[0, cuts], np.r_[cuts, batch.num_rows]
            if held and tuple(marks[:, 0]) != last:
                close(pa.concat_tables(held))
                held.clear()
            if len(start) > 1:
                close(pa.concat_tables([*held, t.slice(0, end[0])]))
                held.clear()
                inner = np.flatnonzero(end[1:-1] - start[1:-1] >= least) + 1
                for lo, hi in zip(start[inner].tolist(), end[inner].tolist(), strict=True):
                    close(t.slice(lo, hi - lo))
            held.append(t.slice(start[-1], end[-1] - start[-1]))
            last = tuple(marks[:, -1])
            yield from flush(10_000)
        if held:
            close(pa.concat_tables(held))
        yield from flush(1)

    return dealt.mapInArrow(lean(run), schema)


def by_sorted_groups(df: DataFrame, keys: list[str], order: list[str], kernel: Callable[[pa.Table, np.ndarray, np.ndarray], pa.RecordBatch | None], schema: str) -> DataFrame:
    """Run kernel on many whole groups at once: an Arrow table and the groups' starts and ends in it.

    For groups so small that a call for each would cost more than its work. Groups end with a batch or wait
    for the next one, so callers bound them (blocked_pairs).
    """
    dealt = by_bytes(df).repartition(*[F.col(k) for k in keys]).sortWithinPartitions(*keys, *order)
    width = len(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        for batch in _and_none(batches):
            if batch is not None and not batch.num_rows:
                continue
            t = pa.concat_tables([*held, *([pa.Table.from_batches([batch])] if batch is not None else [])]).combine_chunks() if held or batch is not None else None
            if t is None or not t.num_rows:
                return
            marks = np.stack([ints(t.column(i)) for i in range(width)])
            start = np.r_[0, np.flatnonzero((marks[:, 1:] != marks[:, :-1]).any(axis=0)) + 1]
            end = np.r_[start[1:], t.num_rows]
            if batch is not None:  # the last group may go on
                held = [t.slice(start[-1])]
                start, end = start[:-1], end[:-1]
            several = end - start > 1
            if several.any() and (out := kernel(t, start[several], end[several])) is not None:
                yield out

    return dealt.mapInArrow(lean(run), schema)


def _and_none(items: Iterator) -> Iterator:
    yield from items
    yield None


def pairs_within(start: np.ndarray, end: np.ndarray, most: int = 200_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All (i, j), i < j, of rows of the same group, about `most` at a time or those of one row."""
    size = end - start
    row = np.repeat(start - np.r_[0, np.cumsum(size)[:-1]], size) + np.arange(size.sum())
    count = np.repeat(end, size) - 1 - row  # partners after each row
    row, count = row[count > 0], count[count > 0]
    total = np.cumsum(count)
    lo = 0
    while lo < len(row):
        before = total[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(total, before + most, "right")))
        n = count[lo:hi]
        i = np.repeat(row[lo:hi], n)
        yield i, i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n)
        lo = hi


def keep_by_score(docs: DataFrame, make: Callable[[], Callable[[pa.Array], np.ndarray]], passes: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """The rows of docs whose text's score passes, with all their columns, in one narrow pass. make() is called once a task."""
    text_at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = make()
        for batch in batches:
            for b in slices(batch, text_at):
                yield b.filter(pa.array(passes(score(b.column(text_at)))))

    inner = StructType([StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema.fields)])
    return by_bytes(docs).toDF(*inner.names).mapInArrow(lean(run), inner).toDF(*docs.columns)


def blocked_pairs(df: DataFrame, group: list[str], blocks: DataFrame, member: str) -> DataFrame:
    """Rows of each group dealt to pairs of blocks, so that no task holds a whole large group.

    blocks has the group columns and n_blocks. Each row falls into a block by the hash of its
    member id and goes to every block pair (bi <= bj) that holds its block; within a pair of blocks
    the kernel compares rows of bi with rows of bj. Every pair of members meets in at least one
    block pair, and rows of groups of one block are not copied.
    """
    own = F.pmod(F.xxhash64(member), F.col("n_blocks").cast("bigint")).cast("int")
    return (
        df.join(blocks, group)
        .withColumn("block", own)
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n_blocks").cast("int") - 1)))
        .withColumn("bi", F.least("block", "other"))
        .withColumn("bj", F.greatest("block", "other"))
        .drop("n_blocks", "other")
    )
