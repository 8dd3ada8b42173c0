"""Set-intersection kernels on sorted neighbour lists, and Arrow helpers around them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def intersect_count(a: Column, b: Column) -> Column:
    """Size of the common part of two neighbour lists; stays in the JVM."""
    return F.size(F.array_intersect(a, b)).cast("bigint")


def merge_count(a: np.ndarray, b: np.ndarray) -> int:
    """Common members of two sorted distinct lists, by one merged sort."""
    both = np.concatenate([a, b])
    both.sort(kind="stable")
    return int((both[1:] == both[:-1]).sum())


def search_count(a: np.ndarray, b: np.ndarray) -> int:
    """The same by binary search of the shorter list in the longer one."""
    short, long_ = (a, b) if len(a) <= len(b) else (b, a)
    if not len(long_):
        return 0
    at = np.searchsorted(long_, short)
    return int((long_[np.minimum(at, len(long_) - 1)] == short).sum())


def bitmap_count(a: np.ndarray, b: np.ndarray) -> int:
    """The same by a bitmap over the range of the longer list; for hubs."""
    short, long_ = (a, b) if len(a) <= len(b) else (b, a)
    if not len(long_):
        return 0
    lo = int(long_[0])
    bits = np.zeros(int(long_[-1]) - lo + 1, bool)
    bits[long_ - lo] = True
    inside = short[(short >= lo) & (short <= long_[-1])] - lo
    return int(bits[inside].sum())


KERNELS = {"merge": merge_count, "search": search_count, "bitmap": bitmap_count}


def list_pairs(left: pa.Array, right: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The rows of two list<int64> columns as numpy slices, without copying."""
    sides = []
    for c in (left, right):
        sides.append((c.flatten().to_numpy(zero_copy_only=False), np.asarray(c.offsets) - c.offsets[0].as_py()))
    (x, xo), (y, yo) = sides
    for i in range(len(left)):
        yield x[xo[i] : xo[i + 1]], y[yo[i] : yo[i + 1]]


def common_counts(left: pa.Array, right: pa.Array, kernel: str = "search") -> np.ndarray:
    count = KERNELS[kernel]
    return np.fromiter((count(a, b) for a, b in list_pairs(left, right)), np.int64, len(left))


class Places:
    """Where integers stand in a sorted array; by a table where their range is narrow."""

    WIDEST = 1 << 24

    def __init__(self, where: np.ndarray):
        self.where, self.table = where, None
        if len(where) and (wide := int(where[-1]) - int(where[0]) + 1) <= self.WIDEST:
            self.table = np.full(wide + 1, -1, np.int32)  # the last one is for what is out of range
            self.table[where - where[0]] = np.arange(len(where), dtype=np.int32)

    def found(self, what: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place, whether it stands there)."""
        if self.table is None:
            at = np.searchsorted(self.where, what)
            return at, self.where[np.minimum(at, len(self.where) - 1)] == what
        if len(what) and (what[0] < self.where[0] or what.min() < self.where[0] or what.max() > self.where[-1]):
            at = self.table[np.where((what < self.where[0]) | (what > self.where[-1]), len(self.table) - 1, what - self.where[0])]
        else:
            at = self.table[what - self.where[0]]
        return at, at >= 0


class HeldLists:
    """Neighbour lists that stand in one task; other lists come past and are counted against those of their members.

    Where the lists fill a good part of their range they are rows of bits, and a pair is an AND; else each wedge is looked up in a row of flags.
    """

    FLAGS, STEP = 1 << 23, 1 << 20

    def __init__(self, ids: list[np.ndarray], sizes: list[np.ndarray], targets: list[np.ndarray]):
        self.ids = np.concatenate(ids) if ids else np.zeros(0, np.int64)
        size = np.concatenate(sizes) if sizes else np.zeros(0, np.int64)
        self.range = np.unique(np.concatenate([np.unique(t) for t in targets])) if targets else np.zeros(0, np.int64)
        for i, t in enumerate(targets):  # narrow ones take the place of the wide ones, batch by batch
            targets[i] = np.searchsorted(self.range, t).astype(np.int32)
        flat = np.concatenate(targets) if targets else np.zeros(0, np.int32)
        order = np.argsort(self.ids)
        start = (np.cumsum(size) - size)[order]
        self.ids, self.size, self.start, self.flat = self.ids[order], size[order], start, flat
        self.sources, self.targets = Places(self.ids), Places(self.range)
        words = -(-len(self.range) // 64)
        self.bits = None
        if len(self.ids) and len(self.ids) * words <= 2 * len(flat):
            self.bits = np.empty((len(self.ids), words), np.uint64)
            for i in range(len(self.ids)):
                self.bits[i] = self._row(flat[start[i] : start[i] + self.size[i]], words)
            self.flat = None
        else:
            self.flags = np.zeros((max(1, min(256, self.FLAGS // max(1, len(self.range)))), len(self.range)), bool)

    @staticmethod
    def _row(at: np.ndarray, words: int) -> np.ndarray:
        row = np.zeros(words * 64, np.uint8)
        row[at] = 1
        return np.packbits(row).view(np.uint64)

    def count(self, values: np.ndarray, offsets: np.ndarray) -> int:
        """Common members of each list in values with the held list of each of its members, in all."""
        if not len(self.ids) or not len(values):
            return 0
        source, is_source = self.sources.found(values)
        target, is_target = self.targets.found(values)
        return self._by_bits(offsets, source, is_source, target, is_target) if self.bits is not None else self._by_flags(offsets, source, is_source, target, is_target)

    def _by_bits(self, offsets, source, is_source, target, is_target) -> int:
        n, words = 0, self.bits.shape[1]
        step = max(1, self.STEP // words)
        for lo, hi in zip(offsets[:-1], offsets[1:], strict=True):
            rows = source[lo:hi][is_source[lo:hi]]
            if len(rows):
                own = self._row(target[lo:hi][is_target[lo:hi]], words)
                n += sum(int(np.bitwise_count(self.bits[rows[k : k + step]] & own).sum(dtype=np.int64)) for k in range(0, len(rows), step))
        return n

    def _by_flags(self, offsets, source, is_source, target, is_target) -> int:
        n, at_once = 0, len(self.flags)
        lists = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
        for lo in range(0, len(offsets) - 1, at_once):
            a, b = offsets[lo], offsets[min(lo + at_once, len(offsets) - 1)]
            row = lists[a:b] - lo
            marks = row[is_target[a:b]], target[a:b][is_target[a:b]]
            self.flags[marks] = True
            asks, who = source[a:b][is_source[a:b]], row[is_source[a:b]]
            ends = np.cumsum(self.size[asks])
            k = 0
            while k < len(asks):
                done = ends[k - 1] if k else 0
                e = max(k + 1, int(np.searchsorted(ends, done + self.STEP, "right")))
                size = self.size[asks[k:e]]
                first = np.cumsum(size) - size
                wedge = self.flat[np.repeat(self.start[asks[k:e]] - first, size) + np.arange(int(size.sum()))]
                n += int(np.count_nonzero(self.flags.ravel()[np.repeat(who[k:e] * self.flags.shape[1], size) + wedge]))
                k = e
            self.flags[marks] = False
        return n


def count_in_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(cell, asks, id, nbrs), sorted by cell and asks: lists that stay (asks 0), then those that come past -> one partial sum a cell."""
    cell, n, held, stay = None, 0, None, ([], [], [])
    for b in batches:
        cells, asks = b.column(0).to_numpy(), b.column(1).to_numpy()
        cuts = np.flatnonzero((cells[1:] != cells[:-1]) | (asks[1:] != asks[:-1])) + 1
        for lo, hi in zip(np.r_[0, cuts].tolist(), np.r_[cuts, b.num_rows].tolist(), strict=True):
            if lo == hi:
                continue
            if cells[lo] != cell:
                if n:
                    yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64())})
                cell, n, held, stay = cells[lo], 0, None, ([], [], [])
            lists = b.column(3).slice(lo, hi - lo)
            values, offsets = lists.flatten().to_numpy(zero_copy_only=False), np.asarray(lists.offsets)
            offsets = (offsets - offsets[0]).astype(np.int64)
            if asks[lo] == 0:
                stay[0].append(b.column(2).slice(lo, hi - lo).to_numpy().copy())
                stay[1].append(np.diff(offsets))
                stay[2].append(values.copy())
            else:
                if held is None:
                    held, stay = HeldLists(*stay), ([], [], [])
                n += held.count(values, offsets)
    if n:
        yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64())})
