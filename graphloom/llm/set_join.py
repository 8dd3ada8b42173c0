"""Near-duplicate documents by a chosen-path set similarity join.

Texts with equal shingle sets form a class. In each of several independent trees a node picks one or
two coordinates of the minwise signature (1 / threshold on average) and each class goes to the child
of its token there; two classes above the threshold keep one shared path a tree on average. A node
that is small is compared exhaustively by signatures; a larger one first links its members to a pivot,
lets go of those so near the pivot that all their partners are linked to it too, and branches on. What
is still large at the greatest depth is compared exhaustively in pairs of blocks: nothing is capped.

Signature links only gather coarse clusters, by a threshold many deviations below the real one. Each
class that has company is then read again once, and full sets are compared exactly within its cluster,
so every reported link is confirmed and no link of a cluster is lost.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.llm.common import arrow_rows, blocked_pairs, by_bytes, by_sorted_group, ints, lean
from graphloom.llm.shingles import U, minwise, mix, seeds, shingle_sets
from graphloom.operators.components import components_of_links, star_edges
from graphloom.plans.scratch import Scratch

WIDTH = 128
SMALL, DEPTH, BLOCK = 1024, 6, 1024
PIVOT_BYTES = 8 << 20  # of signatures of large nodes' pivots that go to all tasks
LINK = "u bigint, v bigint"
SIGNED = "doc_id bigint, n bigint, k1 bigint, k2 bigint, sig binary"


def sign_documents(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, n, k1, k2, sig): set size, a 128-bit digest of the set, and its minwise signature."""
    coordinates = seeds(WIDTH)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, k1, k2, sig = [], [], [], []
            for s in shingle_sets(b.column(1), k):
                with np.errstate(over="ignore"):
                    n.append(len(s))
                    k1.append(mix(s + U(7)).sum(dtype=U))
                    k2.append(mix(s + U(11)).sum(dtype=U))
                sig.append(minwise(s, coordinates).tobytes() if len(s) else b"")
            yield arrow_rows(SIGNED, {"doc_id": b.column(0), "n": n, "k1": np.array(k1, U).view(np.int64), "k2": np.array(k2, U).view(np.int64), "sig": sig})

    return by_bytes(docs).select(docs["doc_id"].cast("bigint"), docs["text"]).mapInArrow(lean(run), SIGNED)


def _signatures(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint32).reshape(-1, WIDTH)


def _choices(node: np.ndarray, level: int, threshold: float) -> list[tuple[np.ndarray, np.ndarray]]:
    """(who, coordinate) for the first choice of every node and the second choice that some nodes make."""
    with np.errstate(over="ignore"):
        one = mix(node * U(3) + U(level))
        two = mix(node * U(5) + U(level))
        three = mix(node * U(7) + U(level))
    again = np.flatnonzero((three >> U(11)).astype(float) / (1 << 53) < 1 / threshold - 1)
    first = one % U(WIDTH)
    other = (first + U(1) + two % U(WIDTH - 1)) % U(WIDTH)
    return [(np.arange(len(node)), first), (again, other[again])]


def _children(node: np.ndarray, rid: np.ndarray, sig: np.ndarray, level: int, threshold: float) -> pa.RecordBatch:
    nodes, rids = [], []
    for who, at in _choices(node, level, threshold):
        with np.errstate(over="ignore"):
            nodes.append(mix(mix(node[who] + at * U(0x9E3779B97F4A7C15)) ^ sig[who, at.astype(np.int64)]))
        rids.append(rid[who])
    return arrow_rows("node bigint, rid bigint", {"node": np.concatenate(nodes).view(np.int64), "rid": np.concatenate(rids)})


def _alike(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Share of equal coordinates, rows of a against rows of b."""
    out = np.zeros((len(a), len(b)), np.float32)
    for lo in range(0, len(a), 64):
        out[lo : lo + 64] = (a[lo : lo + 64, None, :] == b[None, :, :]).mean(axis=2, dtype=np.float32)
    return out


def _node_links(least: float):
    """Kernel over a pair of blocks of a node: stars of the members alike by signature."""

    def kernel(t: pa.Table) -> pa.RecordBatch | None:
        rid, block, sig = ints(t["rid"]), ints(t["block"]), _signatures(t["sig"])
        same = ints(t["bi"])[0] == ints(t["bj"])[0]
        left = np.arange(len(rid)) if same else np.flatnonzero(block == ints(t["bi"])[0])
        right = left if same else np.flatnonzero(block != ints(t["bi"])[0])
        if len(left) * len(right) == 4 and same:
            if (sig[0] == sig[1]).mean() < least:
                return None
            return arrow_rows(LINK, {"u": [rid[1]], "v": [rid[0]]})
        i, j = np.nonzero(_alike(sig[left], sig[right]) >= least)
        u, v = star_edges(rid[left[i]].tolist(), rid[right[j]].tolist())
        return arrow_rows(LINK, {"u": u, "v": v}) if u else None

    return kernel


def coarse_links(classes: DataFrame, threshold: float, trees: int, scratch: Scratch) -> DataFrame:
    """(u, v): links that gather every pair above the threshold into one cluster, but for about one pair in a million."""
    deviation = np.sqrt(threshold * (1 - threshold) / WIDTH)
    least = threshold - 6 * deviation
    core, fence = 0.92, min(least, threshold - 0.3)

    def root(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                rid, sig = ints(b.column(0)), _signatures(b.column(1))
                for tree in range(trees):
                    yield _children(np.full(len(rid), mix(np.array([tree + 1], U))[0]), rid, sig, 0, threshold)

    members = classes.select("rid", "sig")
    rows = members.mapInArrow(lean(root), "node bigint, rid bigint")
    links, leaves = [], []
    for level in range(1, DEPTH + 1):
        sizes = rows.groupBy("node").agg(F.count("*").alias("size"), F.min("rid").alias("pivot")).where("size > 1")
        shared = scratch.save(rows.join(sizes, "node"), "nodes")
        leaves.append(shared.where(F.col("size") <= SMALL).select("node", "rid", "size"))
        large = shared.where(F.col("size") > SMALL)
        if level == DEPTH:
            leaves.append(large.select("node", "rid", "size"))
            break
        n_large = large.agg(F.sum(1 / F.col("size"))).first()[0]
        if not n_large:
            break
        pivots = large.where("rid = pivot").select("node", "rid").join(members, "rid").select("node", F.col("sig").alias("pivot_sig"))
        if n_large * WIDTH * 4 <= PIVOT_BYTES:  # else a crowded node's signatures would be dealt by it
            pivots = F.broadcast(pivots)

        def branch(batches: Iterator[pa.RecordBatch], level=level) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                node, rid, pivot = (ints(b.column(i)) for i in range(3))
                sig = _signatures(b.column(3))
                alike = (sig == _signatures(b.column(4))).mean(axis=1)
                near = np.flatnonzero((alike >= fence) & (rid != pivot))
                far = np.flatnonzero(alike < core)
                below = _children(node[far].view(U), rid[far], sig[far], level, threshold)
                n = below.num_rows
                yield arrow_rows("kind int, a bigint, b bigint", {"kind": np.r_[np.zeros(n, np.int32), np.ones(len(near), np.int32)], "a": np.r_[ints(below.column(0)), rid[near]], "b": np.r_[ints(below.column(1)), pivot[near]]})

        nodes_of = large.groupBy("rid").agg(F.collect_list(F.struct("node", "pivot")).alias("nodes"))  # some for each tree: a signature goes once to all of them
        deep = nodes_of.join(members, "rid").select("rid", "sig", F.inline("nodes")).join(pivots, "node").select("node", "rid", "pivot", "sig", "pivot_sig")
        out = scratch.save(deep.mapInArrow(lean(branch), "kind int, a bigint, b bigint"), "branched")
        links.append(out.where("kind = 1").select(F.col("a").alias("u"), F.col("b").alias("v")))
        rows = out.where("kind = 0").select(F.col("a").alias("node"), F.col("b").alias("rid"))
    leaf = leaves[0]
    for x in leaves[1:]:
        leaf = leaf.union(x)
    spread = leaf.withColumn("n_blocks", F.ceil(F.col("size") / BLOCK).cast("int"))
    spread = (
        spread.withColumn("block", F.pmod(F.xxhash64("rid"), F.col("n_blocks").cast("bigint")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)))
        .select("node", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "rid", "block")
    )
    near = by_sorted_group(spread.join(members, "rid").select("node", "bi", "bj", "rid", "block", "sig"), ["node", "bi", "bj"], ["rid"], _node_links(least), LINK)
    for x in links:
        near = near.union(x)
    return near


def _exact_links(numerator: int, denominator: int):
    """Kernel over a pair of blocks of a cluster: stars of the classes whose full sets pass the threshold."""

    def kernel(t: pa.Table) -> pa.RecordBatch | None:
        rid, block = ints(t["rid"]), ints(t["block"])
        sets = [np.frombuffer(x, U) for x in t["hashes"].to_pylist()]
        n = np.array([len(s) for s in sets])
        same = ints(t["bi"])[0] == ints(t["bj"])[0]
        left = np.arange(len(rid)) if same else np.flatnonzero(block == ints(t["bi"])[0])
        right = left if same else np.flatnonzero(block != ints(t["bi"])[0])
        if not len(left) or not len(right):
            return None
        if same and len(rid) == 2:
            both = np.array([[len(sets[0]), c := len(np.intersect1d(*sets, assume_unique=True))], [c, len(sets[1])]], float)
        else:
            flat = np.concatenate(sets)
            owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
            _, column, count = np.unique(flat, return_inverse=True, return_counts=True)
            useful = count[column] > 1
            rank = np.cumsum(count > 1) - 1
            owner, column = owner[useful], rank[column[useful]]
            order = np.argsort(column, kind="stable")
            owner, column = owner[order], column[order]
            both = np.zeros((len(left), len(right)), np.float32)
            width = 2048
            for lo in range(0, int(column[-1]) + 1 if len(column) else 0, width):
                a, b = np.searchsorted(column, [lo, lo + width])
                x = np.zeros((len(sets), width), np.float32)
                x[owner[a:b], column[a:b] - lo] = 1
                both += x[left] @ x[right].T
        union = n[left][:, None] + n[right][None, :] - both
        i, j = np.nonzero(denominator * both.astype(np.float64) >= numerator * union)
        u, v = star_edges(rid[left[i]].tolist(), rid[right[j]].tolist())
        return arrow_rows(LINK, {"u": u, "v": v}) if u else None

    return kernel


def _full_sets(k: int):
    schema = "rid bigint, hashes binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield arrow_rows(schema, {"rid": b.column(0), "hashes": [s.tobytes() for s in shingle_sets(b.column(1), k)]})

    return run, schema


def near_duplicate_components(docs: DataFrame, k: int = 3, numerator: int = 85, denominator: int = 100, trees: int = 12) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row for each row of docs.

    Documents link where denominator * intersection >= numerator * union of their k-word shingle sets
    (fewer words: the whole sequence as one shingle). Null, empty and blank texts have an empty set and
    link with nothing, not even each other. Rows with equal texts share a class. Other columns of docs
    are not read. No rows in, no rows out.
    """
    scratch = Scratch(docs.sparkSession, "setjoin")
    threshold = numerator / denominator
    signed = scratch.save(sign_documents(docs, k), "signed")
    classes = scratch.save(signed.where("n > 0").groupBy("n", "k1", "k2").agg(F.min("doc_id").alias("rid"), F.first("sig").alias("sig")), "classes")
    coarse = components_of_links(scratch.save(coarse_links(classes, threshold, trees, scratch), "coarse"))  # saved, as a task would need two Python workers else
    clusters = scratch.save(coarse.select(F.col("id").alias("rid"), F.col("component").alias("cluster")).join(classes.select("rid", "n"), "rid"), "clusters")
    sizes = clusters.groupBy("cluster").agg(F.ceil(F.greatest(F.count("*") / BLOCK, F.sum("n") / (BLOCK * 8192))).cast("int").alias("n_blocks"))
    run, schema = _full_sets(k)
    sets = docs.select(docs["doc_id"].cast("bigint").alias("rid"), docs["text"]).join(clusters.select("rid"), "rid", "left_semi").mapInArrow(lean(run), schema)
    dealt = blocked_pairs(clusters, ["cluster"], sizes, "rid").join(sets, "rid")
    exact = by_sorted_group(dealt.select("cluster", "bi", "bj", "rid", "block", "hashes"), ["cluster", "bi", "bj"], ["rid"], _exact_links(numerator, denominator), LINK)
    linked = components_of_links(scratch.save(exact, "exact")).select(F.col("id").alias("rid"), "component")
    component = F.coalesce("component", "rid", "doc_id")
    return (
        signed.select("doc_id", "n", "k1", "k2")
        .join(classes.select("n", "k1", "k2", "rid"), ["n", "k1", "k2"], "left")
        .join(linked, "rid", "left")
        .select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), (F.col("doc_id") == component).alias("kept"))
    )
