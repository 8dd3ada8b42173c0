"""Connected components by alternating star rewrites, after a contraction inside each partition.

Each partition first replaces its links by the stars of its own union-find forest (narrow, no
exchange). The rounds then point every vertex at the smallest id it sees: first the larger
neighbours, then the smaller ones. All exchanged aggregates are minima, so Catalyst combines them
before the shuffle, and a hub is one partial row per task. Where a vertex' links meet its minimum both
sides are plain exchanges, so adaptive execution may split a hub. Round tables go to the shared scratch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.plans.scratch import Scratch

STAR = "u bigint, v bigint"
_FLUSH = 500_000


def star_edges(left, right) -> tuple[list[int], list[int]]:
    """Links -> (member, smallest member) of each local component, by hooking roots and jumping pointers over arrays."""
    left, right = np.asarray(left, np.int64), np.asarray(right, np.int64)
    ids, at = np.unique(np.concatenate([left, right]), return_inverse=True)
    a, b = at[: len(left)], at[len(left) :]
    low = np.arange(len(ids))
    while True:
        x, y = low[a], low[b]
        apart = x != y
        if not apart.any():
            break
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(low, np.maximum(x, y), np.minimum(x, y))
        while (further := low[low]).tobytes() != low.tobytes():
            low = further
    members = np.flatnonzero(low != np.arange(len(ids)))
    return ids[members].tolist(), ids[low[members]].tolist()


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[np.ndarray] = []
    rows = 0

    def stars() -> np.ndarray:
        u, v = np.concatenate(held, axis=1)
        return np.array(star_edges(u, v), np.int64).reshape(2, -1)

    def batch(x: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(x[0]), pa.array(x[1])], names=["u", "v"])

    for b in batches:
        if b.num_rows:
            held.append(np.stack([b.column(i).to_numpy(zero_copy_only=False) for i in range(2)]))
            rows += b.num_rows
        if rows >= _FLUSH:
            held = [stars()]
            rows = held[0].shape[1]
            if rows >= _FLUSH // 2:
                yield batch(held[0])
                held, rows = [], 0
    if rows:
        yield batch(stars())


def _star(edges: DataFrame, both: bool) -> DataFrame:
    """One star rewrite. both: towards the larger neighbours (large star), else the smaller ones."""
    pairs = edges.union(edges.select("v", "u")) if both else edges
    low = pairs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
    # by the inverted id: else the minima keep the layout of their aggregate, and a join on that is never split
    met = low.select(F.bitwise_not("k").alias("x"), "m")
    joined = pairs.join(met, F.bitwise_not(pairs.u) == met.x)
    if both:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select(F.col("k").alias("u"), F.col("m").alias("v")))
    return out.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def components_of_links(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Links (two id columns) -> (id, component), one row per vertex that has a link.

    component is the smallest id reachable. Nulls and loops are ignored; vertices without links
    are absent, the caller left-joins its own vertex table.
    """
    spark = links.sparkSession
    scratch = Scratch(spark, "components")
    a, b = (F.col(c).cast("bigint") for c in links.columns[:2])
    clean = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v")
    edges = scratch.save(clean.mapInArrow(_contract, STAR), "links")
    seen = None
    for _ in range(max_rounds):
        step = scratch.save(_star(_star(edges, True), False), "round")
        mark = step.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        scratch.drop(edges)
        edges = step
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle")
    out = edges.select(F.col("u").alias("id"), F.col("v").alias("component")).union(edges.select("v", "v").distinct())
    out._scratch_path = edges._scratch_path  # the caller may drop it
    return out
