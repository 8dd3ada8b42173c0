"""The baselines that the methods are compared with."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import count

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloom.functions.superstep import observed
from graphloom.operators import pagerank as pr
from graphloom.plans.graph import Graph, owner
from graphloom.plans.scratch import Scratch


def triangles_sequential(g: Graph) -> DataFrame:
    """One task, one pass: the local algorithm on a whole neighbour map. Small graphs only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nbrs: dict[int, set[int]] = {}
        for b in batches:
            for s, d in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                nbrs.setdefault(s, set()).add(d)
        n = sum(len(own & nbrs.get(v, set())) for own in nbrs.values() for v in own)
        yield pa.RecordBatch.from_pydict({"triangles": pa.array([n], pa.int64())})

    return g.orient("id").edges.coalesce(1).mapInArrow(run, "triangles bigint")


def triangles_by_probes(g: Graph) -> DataFrame:
    """(triangles, probes): one row moved for each element read of a remote list; shows why lists are shipped whole."""
    e = g.orient("id").edges
    probes = e.toDF("a", "b").join(e.toDF("b", "c"), "b").select("a", "c")
    hit = probes.join(e.toDF("a", "c").withColumn("hit", F.lit(1)), ["a", "c"], "left")
    return hit.agg(F.count("hit").alias("triangles"), F.count("*").alias("probes"))


def ghost_pagerank(g: Graph, parts: int = 4, d: float = 0.85, iters: int = 10) -> DataFrame:
    """Superstep program with ghost copies: each part holds a copy of every remote source it reads, refreshed each step."""
    p = pr.Prepared(g, Scratch(g.edges.sparkSession, "ghostpr"))
    e = p.scratch.save(p.shares.withColumn("part", owner(F.col("dst"), parts)), "edges")
    copies = p.scratch.save(e.select("part", F.col("src").alias("id")).distinct(), "ghosts")
    ranks = p.start()
    for k in range(iters):
        refreshed = copies.join(ranks, "id").withColumnRenamed("id", "src")
        got = refreshed.join(e, ["part", "src"]).groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") * F.col("share")).alias("value"))
        ranks = p.vertices.join(got, "id", "left").select("id", ((1 - d) / max(p.n, 1) + d * F.coalesce("value", F.lit(0.0))).alias("rank"))
        if k < iters - 1:
            ranks = p.scratch.save(ranks, "ranks")
    return ranks


def ghost_bfs(g: Graph, source: int, parts: int = 4) -> DataFrame:
    """Level program with ghost copies of the frontier on every part that has arcs out of it."""
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "ghostbfs")
    e = scratch.save(g.edges.select("src", "dst", owner(F.col("dst"), parts).alias("part")), "edges")
    copies = scratch.save(e.select("part", "src").distinct(), "ghosts")
    state = scratch.save(spark.createDataFrame([(source, source, 0)], "id bigint, parent bigint, level int"), "state")
    depth = 0
    while True:
        depth += 1
        active = copies.join(state.where(F.col("level") == depth - 1).select(F.col("id").alias("src")), "src")
        offers = active.join(e, ["part", "src"]).groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
        new = offers.join(state.select("id"), "id", "left_anti").withColumn("level", F.lit(depth))
        kept, seen = observed(new.select("id", "parent", "level"), scratch, "new", n=F.count("*"))
        if not seen["n"]:
            return state
        state = scratch.save(state.union(kept), "state")


def vertex_program(g: Graph, init: DataFrame, send: Callable[[DataFrame], DataFrame], merge, apply: Callable[[DataFrame], DataFrame], supersteps: int | None, settle: bool = False) -> DataFrame:
    """Vertex-centric supersteps with a barrier and a checkpoint each.

    init: (id, value, active). send: joined (src, value, dst[, ...]) -> (id, message). merge: an
    aggregate of message. apply: (id, value, message) -> (id, value, active). Ends when none is active,
    or after so many supersteps (None: no bound); with settle it raises if some are active then.
    """
    scratch = Scratch(g.edges.sparkSession, "vprog")
    edges = scratch.save(g.edges, "edges")
    state = scratch.save(init, "state")
    for _ in count() if supersteps is None else range(supersteps):
        sent = send(state.where("active").select(F.col("id").alias("src"), "value").join(edges, "src"))
        got = sent.groupBy("id").agg(merge(F.col("message")).alias("message"))
        new, seen = observed(apply(state.join(got, "id", "left")).select("id", "value", "active"), scratch, "state", n=F.count_if("active"))
        scratch.drop(state)
        state = new
        if not seen["n"]:
            break
    else:
        if settle:
            raise RuntimeError("vertex program did not settle")
    return state.select("id", "value")


def vertex_program_bfs(g: Graph, source: int, supersteps: int | None = None) -> DataFrame:
    """(id, level) as a vertex program, until no vertex is active; raises if a bound on supersteps ends it before."""
    init = g.vertices().select("id", F.when(F.col("id") == source, 0).alias("value"), (F.col("id") == source).alias("active"))
    better = F.col("message").isNotNull() & (F.col("value").isNull() | (F.col("message") < F.col("value")))
    return vertex_program(
        g, init, lambda j: j.select(F.col("dst").alias("id"), (F.col("value") + 1).alias("message")), F.min, lambda s: s.select("id", F.when(better, F.col("message")).otherwise(F.col("value")).alias("value"), F.coalesce(better, F.lit(False)).alias("active")), supersteps, settle=True
    ).where("value is not null").select("id", F.col("value").alias("level"))


def vertex_program_pagerank(g: Graph, d: float = 0.85, iters: int = 10) -> DataFrame:
    """(id, rank) as a vertex program."""
    n = g.vertices().count()
    deg = g.degrees("out").toDF("src", "deg")
    weighted = Graph(g.edges.join(deg, "src"), g.vertices())
    init = g.vertices().select("id", F.lit(1.0 / max(n, 1)).alias("value"), F.lit(True).alias("active"))
    out = vertex_program(weighted, init, lambda j: j.select(F.col("dst").alias("id"), (F.col("value") / F.col("deg")).alias("message")), F.sum, lambda s: s.select("id", ((1 - d) / max(n, 1) + d * F.coalesce("message", F.lit(0.0))).alias("value"), F.lit(True).alias("active")), iters)
    return out.select("id", F.col("value").alias("rank"))


def spmv(g: Graph, x: DataFrame, semiring: str = "sum_times") -> DataFrame:
    """(id, value): the transposed adjacency matrix times a sparse vector (id, value), over sum-times or min-plus-one."""
    joined = x.toDF("src", "x").join(g.edges, "src")
    if semiring == "sum_times":
        w = F.col("w") if "w" in g.edges.columns else F.lit(1.0)
        return joined.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("x") * w).alias("value"))
    return joined.groupBy(F.col("dst").alias("id")).agg((F.min("x") + 1).alias("value"))


def masked_square(g: Graph) -> DataFrame:
    """Sum of A masked over A times A on the id orientation: the triangle count in matrix terms."""
    e = g.orient("id").edges
    squared = e.toDF("i", "k").join(e.toDF("k", "j"), "k").groupBy("i", "j").agg(F.count("*").alias("paths"))
    return squared.join(e.toDF("i", "j"), ["i", "j"]).agg(F.coalesce(F.sum("paths"), F.lit(0)).alias("triangles"))


def rdd_library(g: Graph, what: str, iters: int = 10, source: int = 0) -> DataFrame:
    """Spark's bundled RDD graph library through its public classes: pagerank or triangles, with a text hand-off.

    Its ranks sum to N. Small graphs: vertices and edges are RDD objects.
    """
    spark = g.edges.sparkSession
    jvm, sc = spark._jvm, spark.sparkContext._jsc.sc()
    root = Scratch(spark, "rddlib").root
    g.edges.select(F.concat_ws(" ", "src", "dst").alias("value")).write.text(f"{root}/edges")
    level = jvm.org.apache.spark.storage.StorageLevel.MEMORY_AND_DISK()
    graph = jvm.org.apache.spark.graphx.GraphLoader.edgeListFile(sc, f"{root}/edges", False, -1, level, level)
    ints = getattr(jvm.scala.reflect, "ClassTag").Int()
    if what == "pagerank":
        out = getattr(jvm.org.apache.spark.graphx.lib, "PageRank").run(graph, iters, 0.15, ints, ints).vertices()
    elif what == "triangles":
        parted = graph.partitionBy(getattr(jvm.org.apache.spark.graphx, "PartitionStrategy$RandomVertexCut$").__getattr__("MODULE$"))
        out = getattr(jvm.org.apache.spark.graphx.lib, "TriangleCount").run(parted, ints, ints).vertices()
    elif what == "bfs":  # hops to the vertex `source`, along the arcs
        landmark = jvm.java.util.stream.LongStream.of(source).boxed().collect(jvm.java.util.stream.Collectors.toList())
        out = getattr(jvm.org.apache.spark.graphx.lib, "ShortestPaths").run(graph, jvm.scala.jdk.javaapi.CollectionConverters.asScala(landmark).toSeq(), ints).vertices()
    else:
        raise ValueError(what)
    out.saveAsTextFile(f"{root}/{what}")
    rows = spark.read.text(f"{root}/{what}").select(F.regexp_extract("value", r"^\((-?\d+),", 1).cast("bigint").alias("id"), F.regexp_extract("value", r",(.*)\)$", 1).cast("double").alias("value"))
    if what == "bfs":
        found = F.regexp_extract("value", r"-> (\d+)\)\)$", 1)
        return spark.read.text(f"{root}/{what}").where(found != "").select(F.regexp_extract("value", r"^\((-?\d+),", 1).cast("bigint").alias("id"), found.cast("int").alias("level"))
    return rows

