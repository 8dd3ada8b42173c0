"""Pairs of a relation with itself, tile by tile: nothing is exchanged that grows with the pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.plans.scratch import Scratch

BATCH_BYTES = 4 << 20
_CUT = "ti bigint, tj bigint, us binary, vs binary"
_EDGES = "src bigint, dst bigint"


def _by_bytes(df: DataFrame) -> DataFrame:
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return df


def _pairs_out(src: np.ndarray, dst: np.ndarray, most: int = 200_000) -> Iterator[pa.RecordBatch]:
    for lo in range(0, len(src), most):
        yield pa.RecordBatch.from_pydict({"src": pa.array(src[lo : lo + most], pa.int64()), "dst": pa.array(dst[lo : lo + most], pa.int64())})


def shared_pairs(incidence: DataFrame, key: str, item: str, least: int = 1, width: int = 4096) -> DataFrame:
    """(src, dst), src < dst: items that share at least `least` keys. Items are integers.

    A key's items are cut in blocks of `width` successive ids; each pair of blocks is a tile, to which go the key's items in both. A tile
    counts in a matrix of width * width, so a key of n items costs n times its blocks, not n * n.
    """
    rows = incidence.where(F.col(key).isNotNull() & F.col(item).isNotNull()).groupBy(key).agg(F.collect_set(F.col(item).cast("bigint")).alias("items")).where("size(items) > 1")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, bytes, bytes]] = []
        size = 0
        for b in batches:
            for i in range(b.num_rows):
                ids = np.sort(b.column(0)[i].values.to_numpy())
                block = ids // width
                at = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
                names = block[at].tolist()
                parts = [(p - n * width).astype(np.uint16).tobytes() for n, p in zip(names, np.split(ids, at[1:]), strict=True)]
                for x, us in enumerate(parts):
                    for y in range(x, len(parts)):
                        if y > x or len(us) > 2:
                            held.append((names[x], names[y], us, parts[y]))
                            size += len(us) + len(parts[y]) + 16
                    if size > BATCH_BYTES:
                        yield pa.RecordBatch.from_pydict(dict(zip(("ti", "tj", "us", "vs"), map(list, zip(*held, strict=True)), strict=True)))
                        held, size = [], 0
        if held:
            yield pa.RecordBatch.from_pydict(dict(zip(("ti", "tj", "us", "vs"), map(list, zip(*held, strict=True)), strict=True)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tile, shared, n = None, None, 0

        def close() -> Iterator[pa.RecordBatch]:
            if tile is not None:
                for lo in range(0, width, 256):
                    u, v = np.nonzero(shared[lo : lo + 256] >= least)
                    src, dst = u + lo + tile[0] * width, v + tile[1] * width
                    up = src < dst
                    yield from _pairs_out(src[up], dst[up])

        for b in batches:
            for ti, tj, us, vs in zip(*(b.column(k).to_pylist() for k in range(4)), strict=True):
                if (ti, tj) != tile:
                    yield from close()
                    tile, shared, n = (ti, tj), np.zeros((width, width), np.uint8 if least == 1 else np.uint16), 0
                cells = np.frombuffer(us, np.uint16)[:, None], np.frombuffer(vs, np.uint16)[None, :]
                if least == 1:
                    shared[cells] = 1
                else:
                    if n == 65_535:
                        shared = shared.astype(np.uint32)
                    shared[cells] += 1
                n += 1
        yield from close()

    tiles = _by_bytes(rows.select("items")).mapInArrow(cut, _CUT)
    return tiles.repartition("ti", "tj").sortWithinPartitions("ti", "tj").mapInArrow(count, _EDGES)


def cosine_pairs(vectors: DataFrame, id_col: str, vector_col: str, least: float, block: int = 1024) -> DataFrame:
    """(src, dst), src < dst: all pairs of vectors of one length with cosine >= least, block pair by block pair as matrix products.

    Null vectors and ones with null components link with nothing. Where a product comes near the bound, the sum is
    taken again component by component, from the first on.
    """
    spark = vectors.sparkSession
    clean = vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & ~F.exists(vector_col, lambda x: x.isNull()) & (F.size(vector_col) > 0))
    rows = clean.select(F.col(id_col).cast("bigint").alias("id"), F.col(vector_col).cast("array<double>").alias("e"))
    schema = "block bigint, dim int, ids binary, vectors binary"

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[list[int], list[np.ndarray]]] = {}
        done = 0

        def row(dim: int) -> pa.RecordBatch:
            ids, vs = held.pop(dim)
            name = (TaskContext.get().partitionId() << 32) + done
            return pa.RecordBatch.from_pydict({"block": pa.array([name], pa.int64()), "dim": pa.array([dim], pa.int32()), "ids": [np.array(ids, np.int64).tobytes()], "vectors": [np.concatenate(vs).tobytes()]})

        for b in batches:
            for i, v in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                v = v.values.to_numpy()
                ids, vs = held.setdefault(len(v), ([], []))
                ids.append(i)
                vs.append(v)
                if len(ids) == block:
                    yield row(len(v))
                    done += 1
        for dim in list(held):
            yield row(dim)
            done += 1

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                same, dim, ia, a, ib, c = (b.column(j)[k].as_py() for j in range(6))
                ia, ib = np.frombuffer(ia, np.int64), np.frombuffer(ib, np.int64)
                a, c = (np.frombuffer(x, np.float64).reshape(-1, dim) for x in (a, c))

                def dot(x: np.ndarray, y: np.ndarray) -> np.ndarray:
                    s = np.zeros(len(x))
                    for d in range(dim):
                        s = s + x[:, d] * y[:, d]
                    return s

                with np.errstate(all="ignore"):
                    ra, rc = np.sqrt(dot(a, a)), np.sqrt(dot(c, c))
                    cosine = (a @ c.T) / (ra[:, None] * rc[None, :])
                    x, y = np.nonzero(~(cosine < least - 1e-9))
                    unsure = np.flatnonzero(~(cosine[x, y] > least + 1e-9))
                    keep = np.ones(len(x), bool)
                    xs, ys = x[unsure], y[unsure]
                    keep[unsure] = ~(dot(a[xs], c[ys]) / (ra[xs] * rc[ys]) < least)
                if same:
                    keep &= x < y
                src, dst = np.minimum(ia[x], ib[y]), np.maximum(ia[x], ib[y])
                keep &= src < dst
                yield from _pairs_out(src[keep], dst[keep])

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    blocks = Scratch(spark, "cosine").save(_by_bytes(rows).repartition(max(1, min(parts, -(-rows.count() // block))), "id").mapInArrow(pack, schema), "blocks")
    left, right = blocks.toDF("x", "dx", "ia", "a"), blocks.toDF("y", "dy", "ib", "b")
    dealt = left.repartition(parts) if parts > 1 else left
    pairs = dealt.crossJoin(right).where("x <= y and dx = dy").select((F.col("x") == F.col("y")).alias("same"), "dx", "ia", "a", "ib", "b")
    return pairs.mapInArrow(compare, _EDGES)
