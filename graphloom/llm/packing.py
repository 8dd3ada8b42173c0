"""Packing by multiway differencing: near-equal windows from partial partitions of opposing imbalance.

Documents are read in partition order. Full windows are cut off long documents, and what remains of
these is cut in small pieces, which even out the windows; other documents stay whole. The items of a
block of documents are dealt to the fewest windows that hold them. Differencing keeps a heap of partial
partitions, each a sorted list of window loads, and merges the two of largest spread, heaviest window
to lightest. While the heaviest window exceeds the capacity, the window count rises and the block is
dealt anew. A block is some hundred windows, so memory is bounded and no row is shuffled.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from graphloom.llm.bpe import borrowed
from graphloom.llm.common import arrow_rows, by_bytes, lean, slices

PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"
END_ID = 1
TAIL_PIECE = 256


def difference(sizes: list[int], windows: int) -> list[list[int]]:
    """Deal items to `windows` windows by multiway differencing; returns the items' indices of each window."""
    n = len(sizes)
    if windows >= n:
        return [[i] for i in range(n)] + [[] for _ in range(windows - n)]
    left, right = [-1] * n, [-1] * n  # merged groups of items as a binary forest; leaves are items
    heap = [(-s, i, np.array([s]), [i]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    serial = n
    while len(heap) > 1:
        _, _, a, a_groups = heapq.heappop(heap)
        _, _, b, b_groups = heap[0]
        loads, groups = a.tolist(), list(a_groups)
        full = len(loads)
        free = min(windows - full, len(b_groups))
        loads += b[:free].tolist()  # the heaviest of b meet empty windows of a
        groups += b_groups[:free]
        for t in range(free, len(b_groups)):  # the others, heaviest first, meet a's windows from the lightest
            at = full - 1 - (t - free)
            loads[at] += int(b[t])
            left.append(groups[at])
            right.append(b_groups[t])
            groups[at] = len(left) - 1
        order = np.argsort(-np.array(loads), kind="stable")
        merged = np.array(loads)[order]
        spread = int(merged[0] - merged[-1]) if len(merged) == windows else int(merged[0])
        heapq.heapreplace(heap, (-spread, serial, merged, [groups[i] for i in order]))
        serial += 1
    out = []
    for root in heap[0][3]:
        items, stack = [], [root]
        while stack:
            g = stack.pop()
            if g < n:
                items.append(g)
            else:
                stack += [left[g], right[g]]
        out.append(items)
    return out + [[] for _ in range(windows - len(out))]


def pack(sizes: list[int], capacity: int, more: int = 0) -> list[list[int]]:
    """Near-equal windows of whole items by differencing, as lists of items. No item exceeds the capacity.

    The window count starts at the fewest that can hold the items (and `more`) and rises as long as the heaviest
    window exceeds the capacity: half the way to where it would not if it stood as far above the mean then.
    """
    if not sizes:
        return []
    total = sum(sizes)
    windows = -(-total // capacity) + more
    while True:
        dealt = [w for w in difference(sizes, windows) if w]
        heaviest = max(sum(sizes[i] for i in w) for w in dealt)
        if heaviest <= capacity:
            return dealt
        above = heaviest - total / windows
        windows += max(1, int((total / max(capacity - above, 1) - windows) / 2))


def pack_documents(docs: DataFrame, path: str, capacity: int = 2048, block_windows: int = 200, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a piece of a document's ids (with the closing id): its place in its document and in its sequence.

    Null and empty texts are one closing id. Repeated rows are packed each. Sequence ids hold the
    partition number in their upper bits and are unique, not gapless. No rows in, no rows out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        close = END_ID.to_bytes(4, "little")
        base = TaskContext.get().partitionId() << 33
        sequence, more = 0, 0
        rows: list[tuple] = []
        rest: list[tuple[int, int, bytes, int]] = []
        waiting = 0

        def settle() -> pa.RecordBatch:
            nonlocal sequence, waiting, more
            windows = pack([len(r[2]) // 4 for r in rest], capacity, max(0, more - 1))
            if waiting >= block_windows * capacity:  # a whole block: the next one will take about as many
                more = len(windows) - -(-waiting // capacity)
            for window in windows:
                offset = 0
                for i in window:
                    doc, start, ids, total = rest[i]
                    rows.append((doc, start, len(ids) // 4, zlib.crc32(ids), total, base + sequence, offset))
                    offset += len(ids) // 4
                sequence += 1
            out = arrow_rows(PIECES, dict(zip([f.split()[0] for f in PIECES.split(", ")], map(list, zip(*rows, strict=True)), strict=True)))
            rows.clear()
            rest.clear()
            waiting = 0
            return out

        with borrowed(path) as a:
            for b in (part for batch in batches for part in slices(batch, 1)):
                for doc, ids in zip(b.column(0).to_pylist(), a.encode_column(b.column(1)), strict=True):
                    ids += close
                    total, start = len(ids) // 4, 0
                    while total - start >= capacity:
                        piece = ids[4 * start : 4 * (start + capacity)]
                        rows.append((doc, start, capacity, zlib.crc32(piece), total, base + sequence, 0))
                        sequence += 1
                        start += capacity
                    step = TAIL_PIECE if start else capacity
                    for at in range(start, total, step):
                        rest.append((doc, at, ids[4 * at : 4 * (at + step)], total))
                    waiting += total - start
                    if waiting >= block_windows * capacity:
                        yield settle()
            if rows or rest:
                yield settle()

    return by_bytes(docs).select(docs[id_col].cast("bigint"), docs[text_col]).mapInArrow(lean(run), PIECES)
