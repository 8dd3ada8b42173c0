"""PageRank: one relaxation step, fixed steps, until a residual, and its execution variants.

Edges with their source's share are stored once, in buckets of the source, and never exchanged again; only the rank vector moves.
A step refers to the rank frame once, so a few steps make one job whose plan grows linearly, and the
vector is then cut to the shared scratch. Partial sums combine before every exchange.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.functions.superstep import observed
from graphloom.plans.graph import Graph, md5_32, owner
from graphloom.plans.scratch import Scratch

STEPS_A_JOB = 5


class Prepared:
    """The static side of a run: edges with shares, vertices, and their number."""

    def __init__(self, g: Graph, scratch: Scratch, weight: str | None = None):
        self.scratch = scratch
        self.vertices = scratch.save_by(g.vertices(), "vertices", "id")
        self.n = self.vertices.count()
        if weight:
            out = g.edges.groupBy("src").agg(F.sum(weight).alias("deg"))
            shares = g.edges.join(out, "src").select("src", "dst", (F.col(weight) / F.col("deg")).alias("share"))
        else:
            out = g.degrees("out").toDF("src", "deg")
            shares = g.edges.join(out, "src").select("src", "dst", (1.0 / F.col("deg")).alias("share"))
        self.shares = scratch.save_by(shares, "shares", "src")
        self.dangling = self.vertices.join(self.shares.select(F.col("src").alias("id")).distinct(), "id", "left_anti")

    def start(self) -> DataFrame:
        return self.vertices.select("id", F.lit(1.0 / max(self.n, 1)).alias("rank"))


def contributions(p: Prepared, ranks: DataFrame, combine: bool = True) -> DataFrame:
    """(id, value): what each vertex receives. Push: ranks meet the out-edges, sums are combined before the exchange."""
    sent = ranks.toDF("src", "rank").join(p.shares, "src").select(F.col("dst").alias("id"), (F.col("rank") * F.col("share")).alias("value"))
    return sent.groupBy("id").agg(F.sum("value").alias("value")) if combine else sent


def relax(p: Prepared, ranks: DataFrame, d: float, base: DataFrame | None = None, spread: float = 0.0, combine: bool = True) -> DataFrame:
    """New ranks from one snapshot: (1-d)/N (or the restart share) + d * received.

    combine=False ships every contribution by itself and adds up at the target, as without message combination.
    """
    got = contributions(p, ranks, combine)
    if not combine:
        shipped = got.repartition("id").select("id", F.struct("value").alias("x"))  # the exchange stands below the sum, so nothing is summed before it
        got = shipped.groupBy("id").agg(F.sum("x.value").alias("value"))
    out = p.vertices.join(got, "id", "left")
    value = F.coalesce("value", F.lit(0.0)) + spread / max(p.n, 1)
    if base is not None:
        return out.join(base, "id", "left").select("id", ((1 - d) * F.coalesce("restart", F.lit(0.0)) + d * value).alias("rank"))
    return out.select("id", ((1 - d) / max(p.n, 1) + d * value).alias("rank"))


def step(g: Graph, d: float = 0.85) -> DataFrame:
    """(id, old, rank): one step from the uniform start."""
    p = Prepared(g, Scratch(g.edges.sparkSession, "prstep"))
    return relax(p, p.start(), d).select("id", F.lit(1.0 / max(p.n, 1)).alias("old"), "rank")


def pagerank(g: Graph, d: float = 0.85, iters: int = 10, dangling: str = "leak", restart: DataFrame | None = None, weight: str | None = None, scale: str = "one", combine: bool = True, start: DataFrame | None = None) -> DataFrame:
    """(id, rank) after a fixed number of steps. dangling='uniform' gives back the mass of sinks; scale='n' sums to N.

    start, an (id, rank) of earlier ranks, replaces the uniform start: its vertices keep their ranks, new ones
    get the mean, and the whole is scaled to a mass of one.
    """
    p = Prepared(g, Scratch(g.edges.sparkSession, "pagerank"), weight)
    base = None
    if restart is not None:
        base = restart.select("id").distinct().join(p.vertices, "id", "left_semi")
        base = base.crossJoin(base.agg((1.0 / F.count("*")).alias("restart")))
    ranks = p.start()
    if start is not None:
        warm = p.vertices.join(start.select("id", F.col("rank").alias("old")), "id", "left").select("id", F.coalesce("old", F.lit(1.0 / max(p.n, 1))).alias("rank"))
        mass = warm.agg(F.sum("rank")).first()[0] or 1.0
        ranks = p.scratch.save(warm.select("id", (F.col("rank") / mass).alias("rank")), "ranks")
    if dangling == "uniform":
        for _ in range(iters):
            lost = ranks.join(p.dangling, "id", "left_semi").agg(F.sum("rank")).first()[0] or 0.0
            ranks = p.scratch.save(relax(p, ranks, d, base, lost), "ranks")
    else:
        for k in range(iters):
            ranks = relax(p, ranks, d, base, combine=combine)
            if k % STEPS_A_JOB == STEPS_A_JOB - 1 and k < iters - 1:
                ranks = p.scratch.save(ranks, "ranks")
    return ranks.select("id", (F.col("rank") * (p.n if scale == "n" else 1)).alias("rank"))


def pagerank_residuals(g: Graph, d: float = 0.85, tol: float = 1e-6, max_iter: int = 100) -> tuple[DataFrame, list[tuple[int, float, float, float]]]:
    """Ranks once the L1 change is at most tol, and (step, l1, linf, mass) of each step. The residual rides on the step's own job."""
    p = Prepared(g, Scratch(g.edges.sparkSession, "prtol"))
    ranks, log = p.scratch.save(p.start(), "ranks"), []
    for k in range(1, max_iter + 1):
        new = relax(p, ranks, d).join(ranks.toDF("id", "old"), "id")
        change = F.abs(F.col("rank") - F.col("old"))
        kept, seen = observed(new, p.scratch, "ranks", l1=F.sum(change), linf=F.max(change), mass=F.sum("rank"))
        p.scratch.drop(ranks)
        ranks = kept.select("id", "rank")
        ranks._scratch_path = kept._scratch_path
        log.append((k, seen["l1"] or 0.0, seen["linf"] or 0.0, seen["mass"] or 0.0))
        if log[-1][1] <= tol:
            break
    return ranks, log


def pagerank_pull(g: Graph, d: float = 0.85, iters: int = 10) -> DataFrame:
    """Pull: each vertex asks its in-neighbours. Lists of in-neighbours stay; the small (id, rank * share) vector meets them."""
    p = Prepared(g, Scratch(g.edges.sparkSession, "prpull"))
    out = p.scratch.save(p.shares.select("src", "share").distinct(), "out")
    asks = p.scratch.save(g.edges.groupBy(F.col("dst").alias("id")).agg(F.collect_list("src").alias("asks")), "asks")
    ranks = p.start()
    for k in range(iters):
        offer = ranks.toDF("src", "rank").join(out, "src").select("src", (F.col("rank") * F.col("share")).alias("offer"))
        got = asks.select("id", F.explode("asks").alias("src")).join(offer, "src").groupBy("id").agg(F.sum("offer").alias("value"))
        ranks = p.vertices.join(got, "id", "left").select("id", ((1 - d) / max(p.n, 1) + d * F.coalesce("value", F.lit(0.0))).alias("rank"))
        if k % STEPS_A_JOB == STEPS_A_JOB - 1 and k < iters - 1:
            ranks = p.scratch.save(ranks, "ranks")
    return ranks


def _scatter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sum contributions with one target inside a batch: the in-place fold of the local arm."""
    for b in batches:
        if b.num_rows:
            ids, at = np.unique(b.column(0).to_numpy(), return_inverse=True)
            yield pa.RecordBatch.from_pydict({"id": ids, "value": np.bincount(at, b.column(1).to_numpy(), len(ids))})


def pagerank_partitioned(g: Graph, parts: int = 8, d: float = 0.85, iters: int = 10) -> DataFrame:
    """Same-owner contributions are folded in place, the cut part is shipped, one final sum folds both."""
    p = Prepared(g, Scratch(g.edges.sparkSession, "prpart"))
    here, there = owner(F.col("src"), parts), owner(F.col("dst"), parts)
    split = p.scratch.save(p.shares.withColumn("local", here == there), "split")
    ranks = p.start()
    for k in range(iters):
        sent = ranks.toDF("src", "rank").join(split, "src").select("local", F.col("dst").alias("id"), (F.col("rank") * F.col("share")).alias("value"))
        local = sent.where("local").select("id", "value").mapInArrow(_scatter, "id bigint, value double")
        remote = sent.where("not local").groupBy("id").agg(F.sum("value").alias("value"))
        got = local.union(remote).groupBy("id").agg(F.sum("value").alias("value"))
        ranks = p.vertices.join(got, "id", "left").select("id", ((1 - d) / max(p.n, 1) + d * F.coalesce("value", F.lit(0.0))).alias("rank"))
        if k < iters - 1:
            ranks = p.scratch.save(ranks, "ranks")
    return ranks


def pagerank_block_sweeps(g: Graph, blocks: int = 2, d: float = 0.85, sweeps: int = 30) -> DataFrame:
    """Relaxed order: blocks of vertices are updated in turn and read what is already new. Same fixpoint, fewer sweeps."""
    p = Prepared(g, Scratch(g.edges.sparkSession, "prblock"))
    block = F.pmod(md5_32(F.col("id")), F.lit(blocks))
    ranks = p.scratch.save(p.start(), "ranks")
    for _ in range(sweeps):
        old = ranks
        for b in range(blocks):
            inside = p.shares.where(F.pmod(md5_32(F.col("dst")), F.lit(blocks)) == b)
            got = ranks.toDF("src", "rank").join(inside, "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") * F.col("share")).alias("value"))
            new = (1 - d) / max(p.n, 1) + d * F.coalesce("value", F.lit(0.0))
            ranks = ranks.join(got, "id", "left").select("id", F.when(block == b, new).otherwise(F.col("rank")).alias("rank"))
        ranks = p.scratch.save(ranks, "ranks")
        change = ranks.join(old.toDF("id", "old"), "id").agg(F.sum(F.abs(F.col("rank") - F.col("old")))).first()[0] or 0.0
        p.scratch.drop(old)
        if change < 1e-9:
            break
    return ranks


def top_ranked(ranks: DataFrame, k: int) -> DataFrame:
    return ranks.orderBy(F.desc("rank"), "id").limit(k)
