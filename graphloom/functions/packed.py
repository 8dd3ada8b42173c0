"""Neighbour lists in packed blocks: an arc takes a byte or two where it is exchanged or stored.

Arcs are packed before they are dealt by their near ends, and merged and cleared of repeats where they arrive. Block
pairs meet without an exchange: either side is read from its saved table.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.functions.kernels import HeldLists, Places
from graphloom.plans.scratch import Scratch

FLUSH_ROWS = 2_000_000  # that a task packs at once
BLOCK_ARCS = 4_000_000  # of a block, or those of one bucket
SHARING_ARCS = 1_000_000  # of a block whose lists are compared for what they share
WEDGES = 1 << 16  # that are sorted at once: they stay in the cache
BLOCK_VERTICES = 4_000_000  # of a row of degrees
BUCKETS = 16  # for each shuffle partition
BATCH_BYTES = 4 << 20
_WIRE = "bucket int, ids binary, sizes binary, nbrs binary"
_BLOCKS = "block bigint, arcs bigint, ids binary, sizes binary, nbrs binary"
Lists = tuple[np.ndarray, np.ndarray, np.ndarray]  # ids, sizes, members


def squeeze(x: np.ndarray) -> bytes:
    """Integers as compressed planes of their bytes, as few planes as they need."""
    if not len(x):
        return b""
    width = 8 if int(x.min()) < 0 else next(w for w in (1, 2, 4, 8) if int(x.max()) >> 8 * w == 0)
    raw = x.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T.tobytes()
    return bytes([width]) + len(raw).to_bytes(8, "little") + pa.Codec("zstd").compress(raw, asbytes=True)


def expand(b: bytes) -> np.ndarray:
    if not b:
        return np.zeros(0, np.int64)
    raw = np.frombuffer(pa.Codec("zstd").decompress(b[9:], int.from_bytes(b[1:9], "little")), np.uint8)
    return np.ascontiguousarray(raw.reshape(b[0], -1).T).view(f"<u{b[0]}").ravel().astype(np.int64)


def pack_lists(ids: np.ndarray, sizes: np.ndarray, nbrs: np.ndarray) -> tuple[bytes, bytes, bytes]:
    """Lists that are sorted and not empty, as their first members and the gaps between the others."""
    first = np.cumsum(sizes) - sizes
    gaps = np.diff(nbrs, prepend=np.int64(0))
    gaps[first] = nbrs[first]
    return squeeze(ids), squeeze(sizes), squeeze(gaps)


def unpack_lists(ids: bytes, sizes: bytes, nbrs: bytes) -> Lists:
    ids, sizes, gaps = expand(ids), expand(sizes), expand(nbrs)
    first = np.cumsum(sizes) - sizes
    sums = np.cumsum(gaps)
    return ids, sizes, sums - np.repeat(sums[first] - gaps[first], sizes)


def lists_of(src: np.ndarray, dst: np.ndarray) -> Lists:
    """The sorted lists of arcs; repeats fall away."""
    if not len(src):
        return (np.zeros(0, np.int64),) * 3
    lo, hi = min(int(src.min()), int(dst.min())), max(int(src.max()), int(dst.max()))
    names = None
    if hi - lo >= 1 << 31:
        names = np.unique(np.concatenate([src, dst]))
        src, dst, lo = np.searchsorted(names, src), np.searchsorted(names, dst), 0
    key = np.sort((src - lo) << 32 | (dst - lo))
    key = key[np.r_[True, key[1:] != key[:-1]]]
    near, far = (key >> 32) + lo, (key & 0xFFFFFFFF) + lo
    at = np.flatnonzero(np.r_[True, near[1:] != near[:-1]])
    sizes = np.diff(np.r_[at, len(near)])
    return (near[at], sizes, far) if names is None else (names[near[at]], sizes, names[far])


def pick(lists: Lists, rows: np.ndarray) -> Lists:
    ids, sizes, nbrs = lists
    n = sizes[rows]
    at = np.cumsum(n) - n
    return ids[rows], n, nbrs[np.repeat((np.cumsum(sizes) - sizes)[rows] - at, n) + np.arange(int(n.sum()))]


def _dealt(lists: Lists, buckets: int) -> pa.RecordBatch:
    """One row of packed lists for each bucket that has any."""
    bucket = ((lists[0].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % buckets
    order = np.argsort(bucket, kind="stable")
    ids, sizes, nbrs = pick(lists, order)
    cuts = np.flatnonzero(np.diff(bucket[order], prepend=-1))
    ends = np.r_[0, np.cumsum(sizes)]
    rows = [pack_lists(ids[a:b], sizes[a:b], nbrs[ends[a] : ends[b]]) for a, b in zip(cuts.tolist(), np.r_[cuts[1:], len(ids)].tolist(), strict=True)]
    out = dict(zip(("ids", "sizes", "nbrs"), (list(x) for x in zip(*rows, strict=True)), strict=True))
    return pa.RecordBatch.from_pydict({"bucket": pa.array(bucket[order][cuts].astype(np.int32)), **out})


def _pack(both: bool, buckets: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def flush() -> pa.RecordBatch:
            src, dst = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            if both:
                src, dst = np.concatenate([src, dst]), np.concatenate([dst, src])
            return _dealt(lists_of(src, dst), buckets)

        for b in batches:
            if b.num_rows:
                held.append((b.column(0).to_numpy().copy(), b.column(1).to_numpy().copy()))
            if sum(len(x) for x, _ in held) >= FLUSH_ROWS:
                yield flush()
        if held:
            yield flush()

    return run


def _joined(parts: list[Lists]) -> Lists:
    ids, sizes, nbrs = (np.concatenate(x) for x in zip(*parts, strict=True))
    return ids, sizes, nbrs


def _merge(batches: Iterator[pa.RecordBatch], most: int = BLOCK_ARCS) -> Iterator[pa.RecordBatch]:
    """Wire rows in the order of their buckets -> blocks of whole lists, of `most` arcs or those of one bucket."""
    done: list[Lists] = []
    parts: list[Lists] = []
    bucket, n, task = None, 0, TaskContext.get().partitionId()

    def close() -> None:
        ids, sizes, nbrs = _joined(parts)
        done.append(lists_of(np.repeat(ids, sizes), nbrs))
        parts.clear()

    def block() -> pa.RecordBatch:
        ids, sizes, nbrs = _joined(done)
        done.clear()
        packed = pack_lists(ids, sizes, nbrs)
        return pa.RecordBatch.from_pydict({"block": pa.array([(task << 32) + n], pa.int64()), "arcs": pa.array([len(nbrs)], pa.int64()), **{k: [v] for k, v in zip(("ids", "sizes", "nbrs"), packed, strict=True)}})

    for b in batches:
        for i in range(b.num_rows):
            if (at := b.column(0)[i].as_py()) != bucket:
                if parts:
                    close()
                    if sum(len(x[2]) for x in done) >= most:
                        yield block()
                        n += 1
                bucket = at
            parts.append(unpack_lists(*(b.column(k)[i].as_py() for k in (1, 2, 3))))
    if parts:
        close()
    if done:
        yield block()


def _small_batches(df: DataFrame) -> DataFrame:
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return df


def _parts(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _saved(wire: DataFrame, scratch: Scratch, name: str, most: int = BLOCK_ARCS) -> DataFrame:
    out = scratch.save(wire.repartition(_parts(wire), "bucket").sortWithinPartitions("bucket").mapInArrow(lambda batches: _merge(batches, most), _BLOCKS), name)
    scratch.sweep()
    return out


def list_blocks(edges: DataFrame, scratch: Scratch, both: bool) -> DataFrame:
    """(block, arcs, ids, sizes, nbrs): packed lists of distinct arcs, of both directions or from the smaller end only. Edges may repeat; loops and nulls are dropped."""
    ends = edges.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst")).where("src <> dst")
    if not both:
        ends = ends.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return _saved(_small_batches(ends).mapInArrow(_pack(both, BUCKETS * _parts(edges)), _WIRE), scratch, "lists")


def _degrees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def row() -> pa.RecordBatch:
        ids, sizes = (np.concatenate(x) for x in zip(*held, strict=True))
        held.clear()
        order = np.argsort(ids)
        return pa.RecordBatch.from_pydict({"those": [squeeze(ids[order])], "degrees": [squeeze(sizes[order])]})

    for b in batches:
        for i in range(b.num_rows):
            held.append((expand(b.column(0)[i].as_py()), expand(b.column(1)[i].as_py())))
            if sum(len(x) for x, _ in held) >= BLOCK_VERTICES:
                yield row()
    if held:
        yield row()


def by_degree(blocks: DataFrame, scratch: Scratch) -> DataFrame:
    """The blocks of both directions with only the arcs towards the larger (degree, id): each block meets each row of degrees once."""
    degrees = scratch.save(blocks.select("ids", "sizes").coalesce(1).mapInArrow(_degrees, "those binary, degrees binary"), "degrees")
    buckets = BUCKETS * _parts(blocks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                ids, sizes, nbrs = unpack_lists(*(b.column(k)[i].as_py() for k in range(3)))
                those, degree = (expand(b.column(k)[i].as_py()) for k in (3, 4))
                at = np.minimum(np.searchsorted(those, nbrs), len(those) - 1)
                near, mine, its = np.repeat(ids, sizes), np.repeat(sizes, sizes), degree[at]
                keep = (those[at] == nbrs) & ((mine < its) | ((mine == its) & (near < nbrs)))
                if keep.any():
                    yield _dealt(lists_of(near[keep], nbrs[keep]), buckets)

    met = _small_batches(blocks).select("ids", "sizes", "nbrs").crossJoin(degrees.hint("shuffle_replicate_nl"))
    return _saved(met.mapInArrow(run, _WIRE), scratch, "oriented")


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Block pairs, the held one first -> one partial sum a task."""
    block, held, n = None, None, 0
    for b in batches:
        for i in range(b.num_rows):
            if (at := b.column(0)[i].as_py()) != block:
                ids, sizes, nbrs = unpack_lists(*(b.column(k)[i].as_py() for k in (1, 2, 3)))
                block, held = at, HeldLists([ids], [sizes], [nbrs])
            _, sizes, nbrs = unpack_lists(*(b.column(k)[i].as_py() for k in (4, 5, 6)))
            n += held.count(nbrs, np.r_[0, np.cumsum(sizes)])
    if n:
        yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64())})


def common_members(blocks: DataFrame) -> DataFrame:
    """(n): partial sums of the common members of both ends' lists over all arcs. The lists of a block come past each block; nothing is exchanged."""
    held, past = blocks.select("block", "ids", "sizes", "nbrs"), blocks.select("ids", "sizes", "nbrs").toDF("i", "s", "n")
    return _small_batches(held).crossJoin(past.hint("shuffle_replicate_nl")).mapInArrow(_count, "n bigint")


class _Sharing:
    """Lists that stand in one task by their members; the lists that come past are paired with those that share at least `least` members."""

    def __init__(self, lists: Lists, least: int):
        self.ids, sizes, nbrs = lists
        self.least = least
        who = np.repeat(np.arange(len(self.ids), dtype=np.uint32), sizes)
        order = np.argsort(nbrs, kind="stable")
        self.who, members = who[order], nbrs[order]
        self.start = np.flatnonzero(np.r_[True, members[1:] != members[:-1]][: len(members)])
        self.end = np.r_[self.start[1:], len(members)]
        self.members = Places(members[self.start])
        self.after = np.empty(len(order), np.int64)  # where each arc's later ones with the same member begin
        self.after[order] = np.arange(1, len(order) + 1)

    def pairs(self, lists: Lists, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        ids, sizes, nbrs = lists
        if not len(nbrs) or not len(self.ids):
            return
        at, found = self.members.found(nbrs)
        at = np.where(found, at, 0)
        first = self.after if same else self.start[at]  # a block with itself: each pair once
        n = np.where(found, self.end[at] - first, 0)
        ends = np.r_[0, np.cumsum(sizes)]
        met = np.r_[0, np.cumsum(n)][ends]  # wedges of the rows before each
        most = max(1, ((1 << 32) - 1) // len(self.ids))
        lo = 0
        while lo < len(ids):
            hi = min(max(lo + 1, int(np.searchsorted(met, met[lo] + WEDGES, "right")) - 1), lo + most, len(ids))
            a, b = ends[lo], ends[hi]
            k = n[a:b]
            wedge = self.who[np.repeat(first[a:b] - (np.cumsum(k) - k), k) + np.arange(int(k.sum()))]
            wedge += np.repeat((np.repeat(np.arange(hi - lo), sizes[lo:hi]) * len(self.ids)).astype(np.uint32), k)
            wedge.sort()
            met_often = wedge[: len(wedge) - self.least + 1][wedge[self.least - 1 :] == wedge[: len(wedge) - self.least + 1]] if len(wedge) >= self.least else wedge[:0]
            if len(met_often):
                cell = met_often[np.r_[True, met_often[1:] != met_often[:-1]]]
                yield ids[lo + cell // len(self.ids)], self.ids[cell % len(self.ids)]
            lo = hi


def sharing_pairs(arcs: DataFrame, least: int) -> DataFrame:
    """(src, dst), src < dst: near ends of arcs (src, dst) that share at least `least` far ends. Arcs may repeat; nulls are dropped.

    Arcs are exchanged once, packed. Blocks of lists are read past each other, so nothing that grows with the pairs, or with the
    spread of a far end's list over the ids, is exchanged or stored.
    """
    scratch = Scratch(arcs.sparkSession, "sharing")
    ends = arcs.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst")).where("src is not null and dst is not null")
    blocks = _saved(_small_batches(ends).mapInArrow(_pack(False, BUCKETS * _parts(arcs)), _WIRE), scratch, "lists", SHARING_ARCS)

    def enough(b: pa.RecordBatch, i: int, at: int) -> Lists:
        lists = unpack_lists(*(b.column(k)[i].as_py() for k in range(at, at + 3)))
        return pick(lists, np.flatnonzero(lists[1] >= least))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, held = None, None
        for b in batches:
            for i in range(b.num_rows):
                if (at := b.column(0)[i].as_py()) != block:
                    block, held = at, _Sharing(enough(b, i, 1), least)
                for u, v in held.pairs(enough(b, i, 5), b.column(4)[i].as_py() == block):
                    yield pa.RecordBatch.from_pydict({"src": np.minimum(u, v), "dst": np.maximum(u, v)})

    held, past = blocks.select("block", "ids", "sizes", "nbrs"), blocks.select("block", "ids", "sizes", "nbrs").toDF("other", "i", "s", "n")
    return _small_batches(held).crossJoin(past.hint("shuffle_replicate_nl")).where("block <= other").mapInArrow(run, "src bigint, dst bigint")
