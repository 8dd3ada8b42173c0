"""Breadth-first search: parent trees, levels, and its execution variants.

Each level is one job: the frontier meets the edges, proposals are combined to the least parent before
the exchange, visited vertices are dropped by an anti-join, and the frontier's size is read off the
write. The static edges are saved once, in buckets of the source; only frontiers and the visited ids move.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import count

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.functions.superstep import observed
from graphloom.operators.components import components_of_links
from graphloom.plans.graph import Graph, owner
from graphloom.plans.scratch import Scratch

TREE = "id bigint, parent bigint, level int"


def bfs(g: Graph, source: int | DataFrame, dedupe: str = "visited", direction: str = "push", max_depth: int | None = None, target: int | None = None, alpha: int = 14) -> DataFrame:
    """(id, parent, level); the parent is the least id of the level before, a source is its own.

    dedupe='two_level' checks new vertices against the two newest levels only (symmetric graphs).
    direction='auto' lets unvisited vertices look for a parent when the frontier's arcs exceed m / alpha.
    max_depth and target stop early. A source that is no vertex of the graph is an error.
    """
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs")
    edges = scratch.save_by(g.edges.select("src", "dst"), "edges", "src")
    if isinstance(source, DataFrame):
        seeds = source.select(F.col("id").cast("bigint").alias("id"))
    else:
        seeds = spark.createDataFrame([(source,)], "id bigint")
        known = edges.where((F.col("src") == source) | (F.col("dst") == source)).limit(1).count()
        if not known and not (g.vertex_table is not None and g.vertices().where(F.col("id") == source).count()):
            raise ValueError(f"source {source} is not in the graph")
    level_rows = [scratch.save(seeds.select("id", F.col("id").alias("parent"), F.lit(0).alias("level")), "level")]
    arcs = edges.count() if direction == "auto" else 0
    degrees = scratch.save(edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg")), "deg") if direction == "auto" else None
    depth = 0
    while max_depth is None or depth < max_depth:
        depth += 1
        frontier = level_rows[-1].select(F.col("id").alias("src"))
        seen = level_rows[-2:] if dedupe == "two_level" else level_rows
        visited = reduce(DataFrame.union, [t.select("id") for t in seen])
        pull = False
        if direction == "auto":
            pull = (level_rows[-1].join(degrees, "id").agg(F.sum("deg")).first()[0] or 0) * alpha > arcs
        if pull:
            open_ends = edges.join(visited.select(F.col("id").alias("dst")), "dst", "left_anti")
            new = open_ends.join(frontier, "src", "left_semi").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
        else:
            proposals = edges.join(frontier, "src").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
            new = proposals.join(visited, "id", "left_anti")
        kept, seen_now = observed(new.select("id", "parent", F.lit(depth).alias("level")), scratch, "level", n=F.count("*"), hit=F.count_if(F.col("id") == (target if target is not None else -1)))
        if not seen_now["n"]:
            break
        level_rows.append(kept)
        if target is not None and seen_now["hit"]:
            break
    return reduce(DataFrame.union, level_rows)


def bfs_levels(g: Graph, source: int) -> DataFrame:
    return bfs(g, source).select("id", "level")


def bfs_range(g: Graph, source: int) -> DataFrame:
    """The vertices in level order: (place, id, level)."""
    from pyspark.sql import Window

    tree = bfs(g, source)
    starts = tree.groupBy("level").agg(F.count("*").alias("n"))
    before = starts.select("level", F.coalesce(F.sum("n").over(Window.orderBy("level").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # one row a level
    inside = F.row_number().over(Window.partitionBy("level").orderBy("id")) - 1
    return tree.withColumn("k", inside).join(F.broadcast(before), "level").select((F.col("base") + F.col("k")).cast("bigint").alias("place"), "id", "level")


def _settle_block(table: pa.Table) -> dict[int, int]:
    """Levels of one block at its local fixpoint: label-correcting relaxation over the arcs inside the block."""
    level: dict[int, int] = {}
    arcs: dict[int, list[int]] = {}
    for kind, a, b in zip(table["kind"].to_pylist(), table["a"].to_pylist(), table["b"].to_pylist(), strict=True):
        if kind == 0:
            level[a] = min(b, level.get(a, b))
        else:
            arcs.setdefault(a, []).append(b)
    wave = sorted(level, key=level.get)
    while wave:
        nxt = []
        for u in wave:
            for v in arcs.get(u, ()):
                if level[u] + 1 < level.get(v, 1 << 60):
                    level[v] = level[u] + 1
                    nxt.append(v)
        wave = nxt
    return level


def bfs_async_blocks(g: Graph, source: int, parts: int = 4, max_rounds: int | None = None) -> DataFrame:
    """Levels by local fixpoints: each block relaxes its own arcs until nothing improves, then offers along cut arcs are exchanged.

    Fewer exchanges than levels where paths run inside blocks; parents are the least predecessor one
    level up, found at the end, so that the tree equals bfs(). A block's arcs must fit a task. Rounds go
    on until nothing improves; if max_rounds are not enough for that, it raises.
    """
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfsblocks")
    e = scratch.save(g.edges.select("src", "dst", owner(F.col("src"), parts).alias("p"), owner(F.col("dst"), parts).alias("q")), "edges")
    inner = e.where("p = q").select("p", F.lit(1).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"))
    cut = e.where("p <> q").select("src", "dst")
    levels = scratch.save(spark.createDataFrame([(source, 0)], "id bigint, level bigint"), "levels")

    def settle(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        got = _settle_block(table)
        return pa.table({"id": pa.array(list(got), pa.int64()), "level": pa.array(list(got.values()), pa.int64())})

    mark = None
    for _ in count() if max_rounds is None else range(max_rounds):
        offers = cut.join(levels.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), (F.col("level") + 1).alias("level"))
        merged = levels.union(offers).groupBy("id").agg(F.min("level").alias("level"))
        state = merged.select(owner(F.col("id"), parts).alias("p"), F.lit(0).alias("kind"), F.col("id").alias("a"), F.col("level").alias("b"))
        new, seen = observed(inner.union(state).groupBy("p").applyInArrow(settle, "id bigint, level bigint"), scratch, "levels", n=F.count("*"), s=F.sum("level"))
        scratch.drop(levels)
        levels = new
        if (seen["n"], seen["s"]) == mark:
            break
        mark = (seen["n"], seen["s"])
    else:
        raise RuntimeError("levels did not settle")
    up = e.select("src", "dst").join(levels.toDF("src", "ls"), "src").join(levels.toDF("dst", "ld"), "dst").where("ld = ls + 1")
    parents = up.groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
    return levels.join(parents, "id", "left").select("id", F.coalesce("parent", "id").alias("parent"), F.col("level").cast("int").alias("level"))


def shortest_path(g: Graph, source: int, target: int) -> DataFrame:
    """(hop, id) along the tree's path; empty if the target is not reached. The walk reads one row a hop."""
    tree = bfs(g, source, target=target)
    spark = tree.sparkSession
    path, at = [], target
    while True:
        row = tree.where(F.col("id") == at).first()
        if row is None:
            return spark.createDataFrame([], "hop int, id bigint")
        path.append((row.level, row.id))
        if row.level == 0:
            return spark.createDataFrame(sorted(path), "hop int, id bigint")
        at = row.parent


def components(g: Graph) -> DataFrame:
    """(id, component): the least id reachable, edges taken both ways."""
    found = components_of_links(g.edges.select("src", "dst"))
    return g.vertices().join(found, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


def bfs_profile(g: Graph, source: int) -> DataFrame:
    """(level, vertices, arcs_out): how the frontier swings."""
    tree = bfs(g, source)
    return tree.join(g.degrees("out"), "id", "left").groupBy("level").agg(F.count("*").alias("vertices"), F.coalesce(F.sum("deg"), F.lit(0)).alias("arcs_out"))


def closeness(g: Graph, sources: list[int]) -> DataFrame:
    """(source, reached, distance_sum, closeness) of a batch of sources, all traversed together with the key (source, id)."""
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "closeness")
    edges = scratch.save(g.edges.select("src", "dst"), "edges")
    levels = [scratch.save(spark.createDataFrame([(s, s, 0) for s in sources], "source bigint, id bigint, level int"), "level")]
    while True:
        seen = reduce(DataFrame.union, [t.select("source", "id") for t in levels])
        new = levels[-1].join(edges, F.col("id") == F.col("src")).select("source", F.col("dst").alias("id")).distinct().join(seen, ["source", "id"], "left_anti")
        kept, watch = observed(new.withColumn("level", F.lit(len(levels))), scratch, "level", n=F.count("*"))
        if not watch["n"]:
            break
        levels.append(kept)
    tree = reduce(DataFrame.union, levels)
    out = tree.groupBy("source").agg(F.count("*").alias("reached"), F.sum("level").alias("distance_sum"))
    return out.select("source", "reached", "distance_sum", F.round(F.when(F.col("distance_sum") > 0, (F.col("reached") - 1) / F.col("distance_sum")).otherwise(0.0), 9).alias("closeness"))


def dfs_preorder(tree: DataFrame, root: int) -> DataFrame:
    """(place, id, depth) of a parent tree (src -> dst) in depth-first preorder, children by id.

    Sorted by root paths, which is exact for forests; a lexicographic depth-first order of a general
    graph is inherently sequential and is not offered.
    """
    spark = tree.sparkSession
    scratch = Scratch(spark, "dfs")
    pad = lambda c: F.lpad(c.cast("string"), 19, "0")
    level = scratch.save(spark.createDataFrame([(root,)], "id bigint").select("id", F.lit(0).alias("depth"), pad(F.col("id")).alias("path")), "paths")
    levels = [level]
    while True:
        nxt = level.join(tree, F.col("id") == F.col("src")).select(F.col("dst").alias("id"), (F.col("depth") + 1).alias("depth"), F.concat("path", F.lit("/"), pad(F.col("dst"))).alias("path"))
        level, seen = observed(nxt, scratch, "paths", n=F.count("*"))
        if not seen["n"]:
            break
        levels.append(level)
    return reduce(DataFrame.union, levels).select("path", "id", "depth")


def bfs_sql(g: Graph, source: int, depth: int = 4) -> DataFrame:
    """Shallow BFS as one recursive SQL query (it walks paths, so only for small depth and size)."""
    text = f"""WITH RECURSIVE walk(id, level) AS (
        SELECT CAST({source} AS BIGINT), 0
        UNION ALL
        SELECT e.dst, w.level + 1 FROM walk w JOIN {{edges}} e ON e.src = w.id WHERE w.level < {depth})
      SELECT id, min(level) AS level FROM walk GROUP BY id"""
    return g.edges.sparkSession.sql(text, edges=g.edges)
