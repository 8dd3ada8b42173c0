"""Near-duplicate vectors by lattice hashing.

In each of several tables a vector is projected at random to eight dimensions and decoded to the
nearest point of the E8 lattice; it also probes the neighbouring cell that the other coset of the
lattice offers. Vectors that meet in a cell and are alike by 256 sign bits are gathered in clusters.
Within its cluster every vector is then compared in double precision with all others, in pairs of
blocks, which confirms every link, counts each once, and finds those that no table brought together.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloom.llm.common import arrow_rows, blocked_pairs, by_sorted_group, ints, lean
from graphloom.llm.shingles import U, mix
from graphloom.operators.components import components_of_links, star_edges
from graphloom.plans.scratch import Scratch

TABLES, SCALE, BLOCK = 24, 2.0, 1024
BITS = 256
SIGNS = [f"s{i}" for i in range(BITS // 64)]
CELL = "cell bigint, rid bigint, " + ", ".join(f"{s} bigint" for s in SIGNS)
FOUND = "kind int, a bigint, b bigint"


def _even_point(x: np.ndarray) -> np.ndarray:
    """Nearest integer points whose coordinates sum to an even number."""
    r = np.rint(x)
    off = x - r
    odd = np.flatnonzero(r.sum(axis=1) % 2)
    worst = np.abs(off[odd]).argmax(axis=1)
    r[odd, worst] += np.where(off[odd, worst] >= 0, 1, -1)
    return r


def e8_points(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nearest E8 points, doubled to integers, and the best points of the other coset."""
    a, b = _even_point(x), _even_point(x - 0.5) + 0.5
    first = (((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1))[:, None]
    return (2 * np.where(first, a, b)).astype(np.int64), (2 * np.where(first, b, a)).astype(np.int64)


def _frames(width: int, tables: int) -> tuple[np.ndarray, np.ndarray]:
    """Random projections of the tables (width x 8 each) and BITS sign directions; the same in every task."""
    rng = np.random.default_rng(811 + width)
    turns = [np.linalg.qr(rng.normal(size=(max(width, 8), 8)))[0][:width] * np.sqrt(width / 8) * SCALE for _ in range(tables)]
    return np.stack(turns), rng.normal(size=(width, BITS))


def _cells(unit: np.ndarray, rid: np.ndarray, tables: int) -> Iterator[pa.RecordBatch]:
    turns, signs = _frames(unit.shape[1], tables)
    bits = np.packbits(unit @ signs > 0, axis=1).view(np.int64)
    with np.errstate(over="ignore"):
        for t in range(tables):
            keys = []
            for point in e8_points(unit @ turns[t]):
                key = np.full(len(rid), t * 100_003 + unit.shape[1], U)
                for c in range(8):
                    key = mix(key ^ point[:, c].astype(U))
                keys.append(key.view(np.int64))
            yield arrow_rows(CELL, {"cell": np.concatenate(keys), "rid": np.tile(rid, 2), **{s: np.tile(bits[:, i], 2) for i, s in enumerate(SIGNS)}})


def _unit_rows(column: pa.Array) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Rows by vector length: their positions and unit vectors in double precision."""
    rows = column.to_pylist()
    by: dict[int, list[int]] = {}
    for i, v in enumerate(rows):
        by.setdefault(len(v), []).append(i)
    out = {}
    for width, at in by.items():
        m = np.array([rows[i] for i in at], float)
        m /= np.abs(m).max(axis=1, keepdims=True)
        out[width] = np.array(at), m / np.linalg.norm(m, axis=1, keepdims=True)
    return out


def _cell_kernel(most_bits: int):
    def kernel(t: pa.Table) -> pa.RecordBatch | None:
        rid, block = ints(t["rid"]), ints(t["block"])
        s = np.stack([ints(t[c]) for c in SIGNS], axis=1).view(U)
        same = ints(t["bi"])[0] == ints(t["bj"])[0]
        left = np.arange(len(rid)) if same else np.flatnonzero(block == ints(t["bi"])[0])
        right = left if same else np.flatnonzero(block != ints(t["bi"])[0])
        apart = sum(np.bitwise_count(s[left, w][:, None] ^ s[right, w][None, :]).astype(np.int16) for w in range(len(SIGNS)))
        i, j = np.nonzero(apart <= most_bits)
        u, v = star_edges(rid[left[i]].tolist(), rid[right[j]].tolist())
        return arrow_rows("u bigint, v bigint", {"u": u, "v": v}) if u else None

    return kernel


def _exact_kernel(least: float):
    """Links of a pair of blocks: for each class the vectors it links to (kind 0), and stars of the links (kind 1)."""

    def kernel(t: pa.Table) -> pa.RecordBatch | None:
        rid, block, copies = ints(t["rid"]), ints(t["block"]), ints(t["copies"])
        same = ints(t["bi"])[0] == ints(t["bj"])[0]
        us, vs, counts = [], [], np.zeros(len(rid), np.int64)
        for at, unit in _unit_rows(t["embedding"].combine_chunks()).values():
            left = np.arange(len(at)) if same else np.flatnonzero(block[at] == ints(t["bi"])[0])
            right = left if same else np.flatnonzero(block[at] != ints(t["bi"])[0])
            linked = unit[left] @ unit[right].T >= least
            if same:
                np.fill_diagonal(linked, False)
            counts[at[left]] += linked @ copies[at[right]]
            if not same:
                counts[at[right]] += linked.T @ copies[at[left]]
            i, j = np.nonzero(linked)
            u, v = star_edges(rid[at[left[i]]].tolist(), rid[at[right[j]]].tolist())
            us += u
            vs += v
        who = np.flatnonzero(counts)
        return arrow_rows(FOUND, {"kind": [0] * len(who) + [1] * len(us), "a": [*rid[who].tolist(), *us], "b": [*counts[who].tolist(), *vs]})

    return kernel


def comparable(v: Column) -> Column:
    """Neither null, empty nor zero, and without null, NaN or infinite components."""
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(fine & F.exists(v, lambda x: x != 0), F.lit(False))


def near_duplicate_vectors(vectors: DataFrame, least: float = 0.9, tables: int = TABLES, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """vec_id, n_links, component_id, kept: one row for each row of vectors.

    Vectors link where their cosine in double precision is at least `least`. Vectors that are null,
    empty, zero or hold null or non-finite components link with nothing; vectors of different length do
    not link. Equal vectors link with each other. Other columns are not read. No rows in, no rows out.
    """
    scratch = Scratch(vectors.sparkSession, "lattice")
    base = vectors.select(vectors[id_col].cast("bigint").alias("vec_id"), vectors[vector_col].alias("embedding"))
    usable = base.where(comparable(F.col("embedding")))
    classes = scratch.save(usable.groupBy("embedding").agg(F.min("vec_id").alias("rid"), F.count("*").alias("copies")), "classes")

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rid = ints(b.column(0))
            for at, unit in _unit_rows(b.column(1)).values():
                for lo in range(0, len(at), 4096):
                    yield from _cells(unit[lo : lo + 4096], rid[at[lo : lo + 4096]], tables)

    cells = classes.select("rid", "embedding").mapInArrow(lean(decode), CELL)
    sizes = cells.groupBy("cell").agg(F.count("*").alias("size")).where("size > 1").select("cell", F.ceil(F.col("size") / BLOCK).cast("int").alias("n_blocks"))
    angle = np.arccos(least) / np.pi
    most_bits = int(BITS * angle + 6 * np.sqrt(BITS * angle * (1 - angle)))
    coarse = by_sorted_group(blocked_pairs(cells, ["cell"], sizes, "rid").select("cell", "bi", "bj", "rid", "block", *SIGNS), ["cell", "bi", "bj"], ["rid"], _cell_kernel(most_bits), "u bigint, v bigint")
    clusters = scratch.save(components_of_links(coarse).select(F.col("id").alias("rid"), F.col("component").alias("cluster")), "clusters")
    blocks = clusters.groupBy("cluster").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("n_blocks"))
    dealt = blocked_pairs(clusters, ["cluster"], blocks, "rid").join(classes, "rid")
    found = scratch.save(by_sorted_group(dealt.select("cluster", "bi", "bj", "rid", "block", "copies", "embedding"), ["cluster", "bi", "bj"], ["rid"], _exact_kernel(least), FOUND), "found")
    links = found.where("kind = 0").groupBy(F.col("a").alias("rid")).agg(F.sum("b").alias("others"))
    components = components_of_links(found.where("kind = 1").select("a", "b")).select(F.col("id").alias("rid"), "component")
    summary = classes.join(links, "rid", "left").join(components, "rid", "left")
    known = summary.select("embedding", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("component", "rid").alias("component"))
    component = F.coalesce("component", "vec_id")
    return base.join(known, "embedding", "left").select("vec_id", F.coalesce("links", F.lit(0)).cast("bigint").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))
