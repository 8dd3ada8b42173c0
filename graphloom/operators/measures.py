"""Cost and accuracy measures of graphs, placements and runs."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphloom.plans.graph import Graph, owner


def _parts(g: Graph, parts: int) -> DataFrame:
    return g.edges.select("src", "dst", owner(F.col("src"), parts).alias("p"), owner(F.col("dst"), parts).alias("q"))


def edge_cut(g: Graph, parts: int = 4) -> DataFrame:
    """local and remote arcs, the cut share, and the share that random placement is expected to cut."""
    e = _parts(g, parts)
    return e.agg(F.count_if(F.col("p") == F.col("q")).alias("local"), F.count_if(F.col("p") != F.col("q")).alias("remote")).select(
        "local", "remote", F.round(F.col("remote") / (F.col("local") + F.col("remote")), 9).alias("ratio"), F.lit(1 - 1 / parts).alias("expected")
    )


def remote_ratio(g: Graph, parts: int = 4) -> DataFrame:
    return _parts(g, parts).groupBy(F.col("p").alias("part")).agg(F.count_if(F.col("p") == F.col("q")).alias("local"), F.count_if(F.col("p") != F.col("q")).alias("remote"))


def ghosts(g: Graph, parts: int = 4) -> DataFrame:
    """(part, n): distinct remote vertices that a part would hold copies of."""
    return _parts(g, parts).where("p <> q").groupBy(F.col("p").alias("part")).agg(F.count_distinct("dst").alias("n"))


def replication_factor(g: Graph, parts: int = 4) -> DataFrame:
    """Copies of a vertex over all parts, its own included, on average."""
    v = g.vertices().agg(F.count("*").alias("v"))
    return ghosts(g, parts).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("ghosts")).crossJoin(v).select("ghosts", F.round((F.col("ghosts") + F.col("v")) / F.col("v"), 9).alias("factor"))


def messages(g: Graph, parts: int = 4) -> DataFrame:
    """raw: one message a cut arc; combined: one for each sending part and target."""
    e = _parts(g, parts).where("p <> q")
    return e.groupBy("p", "dst").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum("k"), F.lit(0)).alias("raw"), F.count("*").alias("combined"))


def imbalance(g: Graph, parts: int = 4) -> DataFrame:
    """(part, arcs, max_over_mean)."""
    n = _parts(g, parts).groupBy(F.col("p").alias("part")).agg(F.count("*").alias("arcs"))
    s = n.agg(F.round(F.max("arcs") / F.avg("arcs"), 9).alias("max_over_mean"))
    return n.crossJoin(s)


def frontier_imbalance(g: Graph, tree: DataFrame, parts: int = 4) -> DataFrame:
    """(level, part, arcs): active arcs of each level by owner."""
    e = _parts(g, parts)
    return tree.select("id", "level").join(e, F.col("id") == F.col("src")).groupBy("level", F.col("p").alias("part")).agg(F.count("*").alias("arcs"))


def granularity(g: Graph, parts: int = 4) -> DataFrame:
    """(part, arcs, vertices): the work of one task."""
    return _parts(g, parts).groupBy(F.col("p").alias("part")).agg(F.count("*").alias("arcs"), F.count_distinct("src").alias("vertices"))


def degree_skew(g: Graph) -> DataFrame:
    """n, m, mean and largest degree, and their ratio."""
    d = g.degrees("total")
    return d.agg(F.count("*").alias("n"), (F.sum("deg") / 2).cast("bigint").alias("m"), F.max("deg").alias("max_degree"), F.round(F.avg("deg"), 6).alias("mean_degree"), F.round(F.max("deg") / F.avg("deg"), 6).alias("skew"))


def residual_table(spark: SparkSession, log: list[tuple[int, float, float, float]], digits: int = 9) -> DataFrame:
    return spark.createDataFrame([(k, round(a, digits), round(b, digits), round(c, digits)) for k, a, b, c in log], "step int, l1 double, linf double, mass double")


def rank_agreement(a: DataFrame, b: DataFrame, k: int = 10) -> DataFrame:
    """l1, linf, and the overlap of the two top-k lists."""
    both = a.toDF("id", "x").join(b.toDF("id", "y"), "id", "full").na.fill(0.0)
    diff = both.agg(F.sum(F.abs(F.col("x") - F.col("y"))).alias("l1"), F.max(F.abs(F.col("x") - F.col("y"))).alias("linf"))
    tops = [d.toDF("id", "r").orderBy(F.desc("r"), "id").limit(k).select("id") for d in (a, b)]
    return diff.crossJoin(tops[0].join(tops[1], "id").agg(F.count("*").alias("overlap")))


def bfs_violations(g: Graph, tree: DataFrame, symmetric: bool = True) -> DataFrame:
    """(rule, violations): tree arcs exist, levels rise by one, one root, arcs span at most one level, all reached."""
    t = tree.select("id", "parent", "level")
    e = g.edges.select("src", "dst")
    child = t.where("level > 0")
    missing = child.join(e.toDF("parent", "id"), ["parent", "id"], "left_anti").agg(F.count("*").alias("n"))
    levels = child.join(t.select(F.col("id").alias("parent"), F.col("level").alias("up")), "parent").where("level <> up + 1").agg(F.count("*").alias("n"))
    roots = t.where("level = 0").agg((F.count("*") - 1).alias("n"))
    span = e.join(t.select(F.col("id").alias("src"), F.col("level").alias("a")), "src").join(t.select(F.col("id").alias("dst"), F.col("level").alias("b")), "dst")
    far = span.where("abs(a - b) > 1" if symmetric else "b > a + 1").agg(F.count("*").alias("n"))
    left = e.join(t.select(F.col("id").alias("src")), "src", "left_semi").join(t.select(F.col("id").alias("dst")), "dst", "left_anti").agg(F.count("*").alias("n"))
    out = None
    for rule, df in (("tree_arc_missing", missing), ("level_step", levels), ("extra_roots", roots), ("arc_spans_levels", far), ("unreached_neighbour", left)):
        row = df.select(F.lit(rule).alias("rule"), F.col("n").alias("violations"))
        out = row if out is None else out.union(row)
    return out


def triangle_error(estimate: DataFrame, exact: DataFrame) -> DataFrame:
    """abs and rel error of an estimate."""
    d = F.abs(F.col("estimate") - F.col("triangles"))
    return estimate.select("estimate").crossJoin(exact.select("triangles")).select(F.round(d, 3).alias("abs_error"), F.round(F.when(F.col("triangles") > 0, d / F.col("triangles")).otherwise(0.0), 9).alias("rel_error"))


def cut_of(g: Graph, places: DataFrame) -> DataFrame:
    """local, remote and ratio of the arcs under a placement (id, part)."""
    p, q = places.toDF("src", "p"), places.toDF("dst", "q")
    both = g.edges.join(p, "src").join(q, "dst")
    remote = F.count_if(F.col("p") != F.col("q"))
    return both.agg(F.count_if(F.col("p") == F.col("q")).alias("local"), remote.alias("remote"), F.round(remote / F.count("*"), 9).alias("ratio"))


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges of the plan as first laid out: the barriers of a step. Broadcasts and reused exchanges don't count."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"(?<![A-Za-z])Exchange (?:hash|range|single|roundrobin)", plan, re.IGNORECASE))


def speedup(runs: DataFrame) -> DataFrame:
    """(cores, sec) -> speed-up against the fewest cores, efficiency, and whether it is better than linear."""
    w = Window.orderBy("cores").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    base, first = F.first_value("sec").over(w), F.first_value("cores").over(w)
    s = base / F.col("sec")
    ratio = F.col("cores") / first
    return runs.select("cores", "sec", F.round(s, 6).alias("speedup"), F.round(s / ratio, 6).alias("efficiency"), (s > ratio).alias("superlinear"))


def timed(fn: Callable[[], object], limit: float | None = None) -> tuple[str, float]:
    """(status, seconds): 'ok', 'error', or 'dnf' beyond the limit."""
    t = time.time()
    try:
        fn()
        status = "ok"
    except Exception:  # noqa: BLE001 - a failed run is a row of the report
        status = "error"
    sec = time.time() - t
    return ("dnf" if limit is not None and sec > limit else status), sec


def run_metrics(spark: SparkSession) -> DataFrame:
    """(executor, peak_heap_mb, cached_mb): memory of each process as Spark reports it."""
    store = spark.sparkContext._jsc.sc().statusStore()
    it = store.executorList(True).iterator()
    rows = []
    while it.hasNext():
        x = it.next()
        peak = x.peakMemoryMetrics()
        heap = peak.get().getMetricValue("JVMHeapMemory") / 1e6 if peak.isDefined() else 0.0
        rows.append((x.id(), float(heap), x.memoryUsed() / 1e6))
    return spark.createDataFrame(rows, "executor string, peak_heap_mb double, cached_mb double")


def spilled(spark: SparkSession) -> DataFrame:
    """(stage, mem_bytes, disk_bytes) of the session's stages that spilled."""
    store = spark.sparkContext._jsc.sc().statusStore()
    rows = []
    it = store.stageList(None).iterator()
    while it.hasNext():
        s = it.next()
        if s.memoryBytesSpilled() or s.diskBytesSpilled():
            rows.append((s.stageId(), s.memoryBytesSpilled(), s.diskBytesSpilled()))
    return spark.createDataFrame(rows, "stage int, mem_bytes bigint, disk_bytes bigint")


def traversed_edges_per_second(arcs: int, seconds: float) -> float:
    return arcs / seconds if seconds else 0.0
