"""Triangle counting: naive, partitioned with late reduction, oriented, relational, tiled, and estimates.

Neighbour lists are packed in blocks, and each block is read past each other: what is exchanged are the arcs,
packed, once (twice where they are oriented by degree). partitioned() keeps lists with owners and sends the list of an
arc's near end, once for all of its arcs that end there, to the part that holds the list of its far end.
"""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphloom.functions.kernels import count_in_cells, intersect_count
from graphloom.functions.packed import by_degree, common_members, list_blocks
from graphloom.plans.graph import Graph, md5_32, owner
from graphloom.plans.scratch import Scratch

BROADCAST_BYTES = 64 << 20
HELD_ARCS = 12_000_000  # that one part holds in memory, about


def total(counts: DataFrame, divide: int = 1) -> DataFrame:
    """The deferred reduction: all outstanding counts to one row. Exact beyond 2^63 until the last cast."""
    s = F.coalesce(F.sum(F.col("n").cast("decimal(38,0)")), F.lit(0))
    return counts.agg((s / divide).cast("bigint").alias("triangles"))


def _with_lists(arcs: DataFrame, lists: DataFrame, hint: str | None = None) -> DataFrame:
    near, far = lists.toDF("src", "near"), lists.toDF("dst", "far")
    if hint == "broadcast":
        near, far = F.broadcast(near), F.broadcast(far)
    return arcs.join(near, "src").join(far, "dst")


def _kept(o: Graph) -> tuple[Graph, int]:
    """The graph with its arcs saved once, and their number; shuffle files of its making are let go."""
    scratch = Scratch(o.edges.sparkSession, "arcs")
    arcs = scratch.save(o.edges.select("src", "dst"), "arcs")
    scratch.sweep()
    return Graph(arcs), arcs.count()


def _past_held_lists(o: Graph, place: Callable[[Column], Column], parts: int, splits: int, owners: int = 0) -> DataFrame:
    """(n): partial sums of the common members of both ends' lists, over all arcs.

    Each part holds the lists of its vertices; a list comes past, whole and once, each part that holds
    one of its members. splits: tasks that share a part's passing lists. owners: tasks in all, each with
    the same number of parts, where one task is to take all parts of an owner.
    """
    spark = o.edges.sparkSession
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(4 << 20))
    rows = o.edges.select("src", "dst", place(F.col("dst")).alias("there"))
    lists = rows.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"), F.collect_set("there").alias("theres"))
    cell = lambda part, split: (part.cast("int") * splits + split).cast("int").alias("cell")
    share = F.pmod(F.hash("id"), F.lit(splits))
    stay = F.array(*[F.struct(cell(place(F.col("id")), F.lit(k)), F.lit(0).alias("asks")) for k in range(splits)])
    pass_by = F.when(F.size("nbrs") > 1, F.transform("theres", lambda p: F.struct(cell(p, share), F.lit(1).alias("asks")))).otherwise(F.array().cast("array<struct<cell:int,asks:int>>"))
    sent = lists.select(F.explode(F.concat(stay, pass_by)).alias("to"), "id", "nbrs").select("to.cell", "to.asks", "id", "nbrs")
    if owners:
        dealt = sent.repartition(owners, F.floor(F.col("cell") * owners / parts).cast("int"))
    else:
        dealt = sent.repartition(parts * splits, "cell")
    return dealt.sortWithinPartitions("cell", "asks").mapInArrow(count_in_cells, "n bigint")


def _splits(o: Graph, parts: int) -> int:
    return max(1, min(4, int(o.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")) // parts))


def _counts(g: Graph, by: str | None = None) -> DataFrame:
    """(n): partial sums over the arcs of both directions (by None), towards the larger id, or the larger (degree, id). Edges of g may repeat."""
    scratch = Scratch(g.edges.sparkSession, "triangles")
    blocks = list_blocks(g.edges, scratch, both=by != "id")
    if by == "degree":
        both, blocks = blocks, by_degree(blocks, scratch)
        scratch.drop(both)
    return common_members(blocks)


def naive(g: Graph) -> DataFrame:
    """Every arc of the symmetric graph counts the common neighbours of its ends; each triangle is met six times."""
    return total(_counts(g), 6)


def oriented(g: Graph, by: str = "degree", hint: str | None = None) -> DataFrame:
    """Each triangle once, on the acyclic orientation; by degree, hubs keep short lists."""
    if hint == "broadcast":
        o = g.orient(by)
        return total(_with_lists(o.edges, o.neighbour_lists(), hint).select(intersect_count(F.col("near"), F.col("far")).alias("n")))
    return total(_counts(g, by))


def broadcast_lists(g: Graph, by: str = "degree", most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Small graphs: neighbour lists broadcast, no shuffle of arcs. Beyond the size bound the shuffled plan runs."""
    o = g.orient(by)
    arcs = o.edges.count()
    return oriented(g, by, "broadcast" if 16 * arcs <= most_bytes else None)


def partitioned(g: Graph, parts: int = 8, orient: str = "degree", outer: str = "par") -> DataFrame:
    """Lists stay with the owners of their vertices, one late sum.

    Arcs whose far end has the same owner meet their second list in place; for the others, the near list
    is shipped to the far end's owner, once for all that end there. outer='seq' gives each owner one task, 'par' shares an owner's
    lists that come past among several. An owner of many arcs holds them a slice at a time.
    """
    o, arcs = _kept(g.orient(orient))
    slices = -(-arcs // (parts * HELD_ARCS)) or 1
    place = lambda v: owner(v, parts) * slices + F.pmod(F.xxhash64(v), F.lit(slices)).cast("int")
    if outer == "seq":
        return total(_past_held_lists(o, place, parts * slices, 1, parts))
    return total(_past_held_lists(o, place, parts * slices, _splits(o, parts)))


def by_edges(g: Graph, by: str = "id") -> DataFrame:
    """Wedges of the orientation closed by its edges where these stand: no wedge is exchanged."""
    return total(_counts(g, by))


def list_triangles(g: Graph, by: str = "id") -> DataFrame:
    """(u, v, w), u < v < w: one row a triangle."""
    e = g.orient(by).edges.select("src", "dst")
    wedge = e.toDF("a", "b").join(e.toDF("b", "c"), "b")
    closed = wedge.join(e.toDF("a", "c"), ["a", "c"], "left_semi")
    s = F.sort_array(F.array("a", "b", "c"))
    return closed.select(s[0].alias("u"), s[1].alias("v"), s[2].alias("w"))


def tiled(g: Graph, colors: int = 4) -> DataFrame:
    """Vertices get colours; each colour triple is one task's own small problem. An edge is sent to `colors` tiles."""
    color = lambda c: F.pmod(md5_32(c), F.lit(colors))
    e = g.undirected().edges.select("src", "dst", color(F.col("src")).alias("x"), color(F.col("dst")).alias("y"))
    third = F.explode(F.sequence(F.lit(0), F.lit(colors - 1))).alias("z")
    tiles = e.select("src", "dst", third, "x", "y").select("src", "dst", F.array_join(F.sort_array(F.array("x", "y", "z")), "-").alias("tile")).distinct()
    schema = "tile string, n bigint"

    def solve(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        tile = key[0].as_py()
        out: dict[int, set[int]] = {}
        for a, b in zip(table["src"].to_pylist(), table["dst"].to_pylist(), strict=True):
            out.setdefault(a, set()).add(b)
        own = sorted(int(x) for x in tile.split("-"))
        n = 0
        for a, nbrs in out.items():
            for b in nbrs:
                for c in nbrs & out.get(b, set()):
                    n += sorted((tint(a, colors), tint(b, colors), tint(c, colors))) == own
        return pa.table({"tile": [tile], "n": pa.array([n], pa.int64())})

    return total(tiles.groupBy("tile").applyInArrow(solve, schema))


def tint(vertex: int, colors: int) -> int:
    import hashlib

    return int(hashlib.md5(str(vertex).encode()).hexdigest()[:8], 16) % colors


def sparsified(g: Graph, keep: int = 8, of: int = 16) -> DataFrame:
    """Keep an edge with chance keep/of by its hash, count, and scale by the inverse cube."""
    u = g.undirected()
    kept = u.edges.where(F.pmod(md5_32(F.concat(F.lit("e:"), F.col("src").cast("string"), F.lit(":"), F.col("dst").cast("string"))), F.lit(of)) < keep)
    return oriented(Graph(kept)).select(F.round(F.col("triangles") * float((of / keep) ** 3), 3).alias("estimate"))


def wedge_sampled(g: Graph, samples: int = 2000, seed: int = 7) -> DataFrame:
    """Share of sampled wedges that are closed, times a third of all wedges. Wedges are drawn by centre in proportion to their number."""
    s = g.symmetrize()
    deg = s.degrees("out").where("deg > 1").withColumn("w", F.col("deg") * (F.col("deg") - 1) / 2)
    wedges = deg.agg(F.sum("w")).first()[0] or 0.0
    if not wedges:
        return deg.sparkSession.createDataFrame([(0.0, 0, 0.0)], "estimate double, sampled bigint, wedges double")
    lists = s.neighbour_lists().join(deg.select("id", "w"), "id").withColumn("draws", F.floor(F.col("w") * samples / wedges + F.rand(seed)).cast("int")).where("draws > 0")
    drawn = lists.select("id", "nbrs", F.explode(F.sequence(F.lit(1), F.col("draws"))).alias("k"))
    i = F.floor(F.rand(seed + 1) * F.size("nbrs")).cast("int")
    j = F.floor(F.rand(seed + 2) * (F.size("nbrs") - 1)).cast("int")
    ends = drawn.select("nbrs", i.alias("i"), j.alias("j")).select(F.get("nbrs", F.col("i")).alias("a"), F.get("nbrs", F.when(F.col("j") >= F.col("i"), F.col("j") + 1).otherwise(F.col("j"))).alias("b"))
    closed = ends.join(s.edges.toDF("a", "b").withColumn("hit", F.lit(1)), ["a", "b"], "left")
    return closed.agg((F.avg(F.coalesce("hit", F.lit(0))) * (wedges / 3)).alias("estimate"), F.count("*").alias("sampled")).withColumn("wedges", F.lit(float(wedges)))


def per_vertex(g: Graph) -> DataFrame:
    """(id, n): triangles at each vertex that has any edge."""
    hits = list_triangles(g, "degree").select(F.explode(F.array("u", "v", "w")).alias("id")).groupBy("id").agg(F.count("*").alias("k"))
    return g.vertices().join(hits, "id", "left").select("id", F.coalesce("k", F.lit(0)).alias("n"))


def per_edge(g: Graph) -> DataFrame:
    """(src, dst, n): triangles over each undirected edge."""
    s = g.symmetrize()
    return _with_lists(g.undirected().edges, s.neighbour_lists()).select("src", "dst", intersect_count(F.col("near"), F.col("far")).alias("n"))


def clustering(g: Graph) -> DataFrame:
    """(id, coefficient): closed share of the wedges centred at a vertex; 0 below degree 2."""
    deg = g.undirected().degrees("total")
    pairs = F.col("deg") * (F.col("deg") - 1)
    return per_vertex(g).join(deg, "id").select("id", F.round(F.when(pairs > 0, 2 * F.col("n") / pairs).otherwise(0.0), 9).alias("coefficient"))


def transitivity(g: Graph) -> DataFrame:
    """triangles, wedges, and three times their ratio."""
    w = g.undirected().degrees("total").agg(F.coalesce(F.sum((F.col("deg") * (F.col("deg") - 1) / 2).cast("bigint")), F.lit(0)).alias("wedges"))
    return oriented(g).crossJoin(w).select("triangles", "wedges", F.round(F.when(F.col("wedges") > 0, 3 * F.col("triangles") / F.col("wedges")).otherwise(0.0), 9).alias("transitivity"))
