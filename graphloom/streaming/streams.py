"""Structured Streaming over events: windows, sessions, dedup, joins, and growing graphs.

Each query runs to the end of its input (availableNow) into a table below the shared scratch and
returns that table, so it can be held against the batch query over the same rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.functions import udfs
from graphloom.operators import bfs, pagerank, triangles
from graphloom.operators.components import components_of_links
from graphloom.plans.graph import Graph
from graphloom.plans.scratch import Scratch
from graphloom.registry import load, query
from graphloom.sources import io
from graphloom.sources.graphs import GRAPH_SQL, build, draws

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


class Stream:
    """events of sf_dir as a stream of a few files, and a scratch for its sinks."""

    def __init__(self, spark: SparkSession, sf_dir: str, files: int = 3):
        self.spark, self.scratch = spark, Scratch(spark, "stream")
        e = load(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
        cuts = e.select(F.unix_timestamp("ts").alias("t")).approxQuantile("t", [i / files for i in range(1, files)], 0.01) if files > 1 else []
        for lo, hi in zip([None, *cuts], [*cuts, None], strict=True):  # one after the other: the source reads files by age
            part = e.where(F.unix_timestamp("ts") >= lo) if lo is not None else e
            part = part.where(F.unix_timestamp("ts") < hi) if hi is not None else part
            part.coalesce(1).write.mode("append").parquet(f"{self.scratch.root}/in")
        self.events = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{self.scratch.root}/in")

    def run(self, df: DataFrame, mode: str = "append") -> DataFrame:
        """Run to the end; append goes to Parquet, complete and update keep the last value of each batch's rows."""
        out = f"{self.scratch.root}/out"
        w = df.writeStream.outputMode(mode).option("checkpointLocation", f"{self.scratch.root}/ck").trigger(availableNow=True)
        if mode == "append":
            w.format("parquet").option("path", out).start().awaitTermination()
        else:
            w.foreachBatch(lambda b, k: b.write.mode("overwrite").parquet(out)).start().awaitTermination()
        return self.spark.read.schema(df.schema).parquet(out)

    def fold(self, df: DataFrame, step: Callable[[DataFrame, int], None]) -> None:
        df.writeStream.option("checkpointLocation", f"{self.scratch.root}/ck").trigger(availableNow=True).foreachBatch(step).start().awaitTermination()


_DAY = "strftime(ts, '%Y-%m-%d')"
_text = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query("stream_tumbling", f"SELECT {_DAY} || ' 00:00:00' AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _tumbling(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    out = st.run(st.events.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")), "complete")
    return out.select(_text("window.start").alias("day"), "event_type", "n")


_SLIDE = "SELECT strftime(to_timestamp((floor(epoch(ts) / 21600) - k) * 21600)::TIMESTAMP, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events, range(4) t(k) GROUP BY 1, 2"


@query("stream_sliding", _SLIDE)
def _sliding(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    out = st.run(st.events.groupBy(F.window("ts", "1 day", "6 hours"), "event_type").agg(F.count("*").alias("n")), "complete")
    return out.select(_text("window.start").alias("start"), "event_type", "n")


@query("stream_session", "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, sum(CASE WHEN gap IS NULL OR gap >= INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT *, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events)) GROUP BY user_id, k")
def _session(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    out = st.run(st.events.groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count("*").alias("n")), "complete")
    return out.select("user_id", _text("session_window.start").alias("start"), "n")


@query("stream_watermark_late", f"SELECT {_DAY} AS day, count(*) AS n FROM events GROUP BY 1 HAVING max(ts) < (SELECT date_trunc('day', max(ts)) FROM events)")
def _watermark(s: SparkSession, d: str) -> DataFrame:
    """Days closed by the watermark, appended once each; the last day stays open."""
    st = Stream(s, d)
    out = st.run(st.events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")))
    last = load(s, d, "events").agg(F.max(F.date_trunc("day", "ts")).cast("timestamp").alias("t"))
    return out.join(F.broadcast(last), F.col("window.start") < F.col("t")).select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def _dedup(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    twice = st.events.withColumn("k", F.explode(F.array(F.lit(1), F.lit(2))))
    return st.run(twice.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT user_id, event_type, count(*) AS n FROM events WHERE user_id % 3 = 0 GROUP BY 1, 2")
def _static_join(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    users = load(s, d, "events").select("user_id").distinct().where("user_id % 3 = 0")
    return st.run(st.events.join(users, "user_id").select("user_id", "event_type")).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@query("stream_stream_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _stream_join(s: SparkSession, d: str) -> DataFrame:
    st = Stream(s, d)
    a = st.events.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "40 days")
    b = st.events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("r")).withWatermark("r", "40 days")
    return st.run(a.join(b, F.expr("u = v AND r >= t AND r <= t + INTERVAL 1 HOUR")).select("click", "purchase"))


def _hop_stream(s: SparkSession, d: str) -> tuple[Stream, DataFrame]:
    """The arcs of the event graph as a stream of files."""
    st = Stream(s, d, 1)
    build(s, d, "hop").edges.repartition(3, "src", "dst").write.parquet(f"{st.scratch.root}/arcs")
    return st, io.read_stream_edges(s, f"{st.scratch.root}/arcs")


_HOP = GRAPH_SQL["hop"]
_HOP_SYM = f"SELECT src, dst FROM ({_HOP}) UNION SELECT dst, src FROM ({_HOP})"


@query("stream_degree", f"SELECT src AS id, count(*) AS deg FROM ({_HOP}) GROUP BY src")
def _degree(s: SparkSession, d: str) -> DataFrame:
    st, arcs = _hop_stream(s, d)
    return st.run(arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg")), "complete")


class _Growing:
    """The edge store of a growing undirected graph: appended batches below the scratch."""

    def __init__(self, st: Stream):
        self.st, self.tables = st, []

    def add(self, batch: DataFrame) -> tuple[DataFrame, DataFrame]:
        """(new edges, all edges with them); repeats of stored edges are dropped."""
        new = batch.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src <> dst").distinct()
        for t in self.tables:
            new = new.join(t, ["src", "dst"], "left_anti")
        new = self.st.scratch.save(new, "edges")
        self.tables.append(new)
        out = self.tables[0]
        for t in self.tables[1:]:
            out = out.union(t)
        return new, out


@query("stream_triangles", f"WITH e AS (SELECT DISTINCT least(src,dst) AS src, greatest(src,dst) AS dst FROM ({_HOP})) SELECT count(*) AS triangles FROM e x JOIN e y ON x.dst = y.src JOIN e z ON x.src = z.src AND y.dst = z.dst")
def _stream_triangles(s: SparkSession, d: str) -> DataFrame:
    """A batch adds the triangles that hold a new edge: all of the grown graph's lists meet the new edges only.

    A triangle with k new edges is met k times, so hits are weighed by 1 / k.
    """
    st, arcs = _hop_stream(s, d)
    store, totals = _Growing(st), []

    def step(batch: DataFrame, k: int) -> None:
        new, whole = store.add(batch)
        both = Graph(whole).symmetrize().edges.join(Graph(new).symmetrize().edges.withColumn("fresh", F.lit(1)), ["src", "dst"], "left").select("src", "dst", F.coalesce("fresh", F.lit(0)).alias("fresh"))
        a, b = both.toDF("u", "w", "fu"), both.toDF("v", "w", "fv")
        hit = new.toDF("u", "v").join(a, "u").join(b, ["v", "w"])
        totals.append(hit.agg(F.coalesce(F.sum(6 / (1 + F.col("fu") + F.col("fv"))), F.lit(0.0))).first()[0] / 6)

    st.fold(arcs, step)
    return s.createDataFrame([(round(sum(totals)),)], "triangles bigint")


@query("stream_components", f"WITH e AS MATERIALIZED ({_HOP_SYM}), c0 AS (SELECT DISTINCT src AS id, src AS c FROM e)" + "".join(f", c{k + 1} AS MATERIALIZED (SELECT p.id, least(p.c, min(q.c)) AS c FROM c{k} p JOIN e ON e.src = p.id JOIN c{k} q ON q.id = e.dst GROUP BY p.id, p.c)" for k in range(12)) + " SELECT id, c AS component FROM c12")
def _stream_components(s: SparkSession, d: str) -> DataFrame:
    """Component labels after each batch: the stored stars and the new edges are joined, never the old edges again."""
    st, arcs = _hop_stream(s, d)
    stars = [None]

    def step(batch: DataFrame, k: int) -> None:
        links = batch.select("src", "dst")
        if stars[0] is not None:
            links = links.union(stars[0])
        stars[0] = st.scratch.save(components_of_links(links).toDF("src", "dst"), "stars")

    st.fold(arcs, step)
    return stars[0].toDF("id", "component")


_LEVEL_ROUNDS = 12
_LEVEL_SQL = f"WITH e AS MATERIALIZED ({_HOP_SYM}), v AS (SELECT DISTINCT src AS id FROM e), l0 AS (SELECT id, CASE WHEN id = 0 THEN 0 END AS level FROM v)" + "".join(f", l{k + 1} AS MATERIALIZED (SELECT p.id, least(p.level, min(q.level) + 1) AS level FROM l{k} p LEFT JOIN e ON e.src = p.id LEFT JOIN l{k} q ON q.id = e.dst GROUP BY p.id, p.level)" for k in range(_LEVEL_ROUNDS)) + f" SELECT id, level FROM l{_LEVEL_ROUNDS} WHERE level IS NOT NULL"


@query("stream_bfs", _LEVEL_SQL)
def _stream_bfs(s: SparkSession, d: str) -> DataFrame:
    """Levels from vertex 0 after each batch: new edges lower levels, and what they lower goes on from there; the rest is not touched."""
    st, arcs = _hop_stream(s, d)
    store, levels = _Growing(st), [s.createDataFrame([(0, 0)], "id bigint, level int")]

    def step(batch: DataFrame, k: int) -> None:
        new, whole = store.add(batch)
        both, fresh = Graph(whole).symmetrize().edges, Graph(new).symmetrize().edges
        offers = fresh.join(levels[0], F.col("src") == F.col("id")).select(F.col("dst").alias("id"), (F.col("level") + 1).alias("level"))
        while True:
            best = offers.groupBy("id").agg(F.min("level").alias("level"))
            known = levels[0].withColumnRenamed("level", "old")
            lower = st.scratch.save(best.join(known, "id", "left").where("old is null or level < old").select("id", "level"), "lower")
            if lower.isEmpty():
                return
            levels[0] = st.scratch.save(levels[0].join(lower, "id", "left_anti").union(lower), "levels")
            offers = both.join(lower, F.col("src") == F.col("id")).select(F.col("dst").alias("id"), (F.col("level") + 1).alias("level"))

    st.fold(arcs, step)
    return levels[0]


def _settled_ranks(steps: int = 25, d: float = 0.85) -> str:
    out = [f"WITH e AS MATERIALIZED ({_HOP_SYM}), v AS MATERIALIZED (SELECT DISTINCT src AS id FROM e), n AS (SELECT count(*)::DOUBLE AS n FROM v), dg AS MATERIALIZED (SELECT src AS id, count(*) AS deg FROM e GROUP BY src), r0 AS (SELECT id, 1.0::DOUBLE / n AS rank FROM v, n)"]
    for k in range(steps):
        out.append(f", r{k + 1} AS MATERIALIZED (SELECT e.dst AS id, {1 - d}::DOUBLE / any_value(n.n) + {d}::DOUBLE * sum(r.rank / dg.deg) AS rank FROM e JOIN r{k} r ON r.id = e.src JOIN dg ON dg.id = e.src, n GROUP BY e.dst)")
    return "".join(out) + f" SELECT id, round(rank, 6) AS rank FROM r{steps}"


@query("stream_pagerank", _settled_ranks())
def _stream_pagerank(s: SparkSession, d: str) -> DataFrame:
    """Ranks after each batch, from the ranks before it: a warm start, so a batch takes few steps."""
    st, arcs = _hop_stream(s, d)
    store, ranks = _Growing(st), [None]

    def step(batch: DataFrame, k: int) -> None:
        _, whole = store.add(batch)
        ranks[0] = st.scratch.save(pagerank.pagerank(Graph(whole).symmetrize(), iters=8, start=ranks[0]), "ranks")

    st.fold(arcs, step)
    return ranks[0].select("id", F.round("rank", 6).alias("rank"))


@query("stream_output_modes", "SELECT mode, count(*) AS rows_out, sum(n)::BIGINT AS total FROM (SELECT event_type, count(*) AS n FROM events GROUP BY event_type), (VALUES ('complete'), ('update')) m(mode) GROUP BY mode")
def _modes(s: SparkSession, d: str) -> DataFrame:
    """One aggregate under both output modes that an aggregate without a watermark has: the last state of every key is the same."""
    out = None
    for mode in ("complete", "update"):
        st, last = Stream(s, d), []
        counts = st.events.groupBy("event_type").agg(F.count("*").alias("n"))

        def keep(batch: DataFrame, k: int, st=st, last=last, mode=mode) -> None:
            saved = st.scratch.save(batch, "batch")
            if last and mode == "update":  # only changed keys come: they replace their old rows
                saved = st.scratch.save(saved.union(last[-1].join(saved, "event_type", "left_anti")), "state")
            last.append(saved)

        counts.writeStream.outputMode(mode).option("checkpointLocation", f"{st.scratch.root}/ck").trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
        row = last[-1].agg(F.lit(mode).alias("mode"), F.count("*").alias("rows_out"), F.sum("n").alias("total"))
        out = row if out is None else out.union(row)
    return out


@query("stream_rank_drift")
def _drift(s: SparkSession, d: str) -> DataFrame:
    """L1 drift of ranks between the first half and the whole of the arcs."""
    g = build(s, d, "hop")
    half = Graph(g.edges.where("(src + dst) % 2 = 0"))
    a, b = pagerank.pagerank(half).toDF("id", "x"), pagerank.pagerank(g).toDF("id", "y")
    return a.join(b, "id", "full").na.fill(0.0).agg(F.round(F.sum(F.abs(F.col("x") - F.col("y"))), 6).alias("l1"))


# ---- user-defined functions and I/O round trips --------------------------------------------------

_COMMON = f"WITH e AS ({_HOP_SYM}) SELECT x.src, x.dst, (SELECT count(*) FROM e a JOIN e b ON a.dst = b.dst WHERE a.src = x.src AND b.src = x.dst) AS n FROM e x"


@query("udf_intersect_arrow", _COMMON)
def _udf_intersect(s: SparkSession, d: str) -> DataFrame:
    e = build(s, d, "hop").symmetrize().edges
    lists = triangles._with_lists(e, Graph(e).neighbour_lists())
    return lists.select("src", "dst", udfs.intersect_count_arrow("near", "far").alias("n"))


query("udf_partition_map", f"SELECT src AS id, count(*) AS deg FROM ({_HOP}) GROUP BY src")(lambda s, d: udfs.partition_degrees(build(s, d, "hop").edges))
query("udf_grouped_map", f"SELECT src AS id, count(*) * (count(*) - 1) // 2 AS n FROM ({_HOP}) GROUP BY src")(lambda s, d: udfs.grouped_triples(build(s, d, "hop").edges))


@query("udf_cogroup", f"WITH e AS ({_HOP}), dg AS (SELECT src, count(*) AS deg FROM e GROUP BY src) SELECT e.dst AS id, round(sum(1.0::DOUBLE / dg.deg), 9) AS value FROM e JOIN dg ON dg.src = e.src GROUP BY e.dst")
def _udf_cogroup(s: SparkSession, d: str) -> DataFrame:
    g = build(s, d, "hop")
    return udfs.cogrouped_shares(g.vertices().withColumn("rank", F.lit(1.0)), g.edges).select("id", F.round("value", 9).alias("value"))


@query("udaf_entropy", "WITH t AS (SELECT o_custkey AS id, l_suppkey AS p, count(*)::DOUBLE AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2), s AS (SELECT id, n, sum(n) OVER (PARTITION BY id) AS total FROM t) SELECT id, round(-sum(n / total * ln(n / total)), 6) AS entropy FROM s GROUP BY id")
def _udaf(s: SparkSession, d: str) -> DataFrame:
    t = load(s, d, "orders").join(load(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("id"), "l_suppkey").agg(F.count("*").cast("double").alias("n"))
    return t.groupBy("id").agg(F.round(udfs.entropy("n"), 6).alias("entropy"))


@query("udtf_neighbours", _HOP)
def _udtf(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    return s.sql("SELECT t.src, t.dst FROM {a} a, LATERAL graph_arcs(a.id, a.nbrs) t", a=build(s, d, "hop").neighbour_lists())


@query("udf_sql_registered", _COMMON)
def _udf_sql(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    e = build(s, d, "hop").symmetrize().edges
    return s.sql("SELECT src, dst, graph_intersect_count(near, far) AS n FROM {l}", l=triangles._with_lists(e, Graph(e).neighbour_lists()))


@query("ds_urand_source", GRAPH_SQL["urand"])
def _ds(s: SparkSession, d: str) -> DataFrame:
    """Draws of the Python source, kept where the id is an event's."""
    udfs.register(s)
    k, ids = draws(s, d)
    rows = (ids.agg(F.max("id")).first()[0] or 0) + 1
    drawn = s.read.format("urand").option("k", k).option("rows", rows).option("slices", max(8, rows // 250_000)).load()
    return Graph(drawn.join(ids, "id", "left_semi").where("src <> dst")).undirected().edges


query("urand_edges", GRAPH_SQL["urand"])(lambda s, d: build(s, d, "urand").edges)
for _fmt in ("edgelist", "csv", "json", "orc", "parquet"):

    @query(f"io_{_fmt}_roundtrip", _HOP)
    def _io(s: SparkSession, d: str, fmt: str = _fmt) -> DataFrame:
        path = f"{Scratch(s, 'io').root}/{fmt}"
        io.write_graph(build(s, d, "hop"), path, fmt)
        return io.read_graph(s, path, fmt).edges


@query("io_partition_pruned", "SELECT c_custkey FROM customer WHERE c_nationkey = 3")
def _pruned(s: SparkSession, d: str) -> DataFrame:
    path = f"{Scratch(s, 'io').root}/by_nation"
    io.write_result(load(s, d, "customer").select("c_custkey", "c_nationkey"), path, partition_by="c_nationkey")
    return s.read.parquet(path).where("c_nationkey = 3").select("c_custkey")
