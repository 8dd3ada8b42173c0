"""The experiment graphs on the given tables, as DataFrames and as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphloom.functions.tiles import cosine_pairs, shared_pairs
from graphloom.plans.graph import Graph, md5_32
from graphloom.plans.scratch import Scratch
from graphloom.registry import load
from graphloom.sources.generators import kron, urand

_MD5 = "('0x'||substr(md5({}),1,8))::BIGINT"


def _pairs(key: str, item: str) -> str:
    return f"SELECT DISTINCT a.{item} AS src, b.{item} AS dst FROM lineitem a JOIN lineitem b ON a.{key} = b.{key} AND a.{item} < b.{item}"


#: Draws of the synthetic graphs: one for each event, named by its id, over 2^k vertices, so that a vertex has 16 to 32 of them.
_DRAWS = "WITH t AS (SELECT event_id AS i FROM events), z AS (SELECT greatest(1, least(24, floor(log2(count(*) / 16.0))))::BIGINT AS k FROM t)"


def kron_sql() -> str:
    bits = []
    for b in range(24):
        digits = f"('0x'||substr(md5('k:'||i||':{b // 4}'),{8 * (b % 4) + 1},8))::BIGINT"
        bits.append((b, digits))
    draws = ", ".join(f"{d} AS u{b}" for b, d in bits)
    t = [int(x * 4294967296) for x in (0.57, 0.76, 0.95)]
    src = " + ".join(f"(CASE WHEN {b} < k AND u{b} >= {t[1]} THEN {1 << b} ELSE 0 END)" for b, _ in bits)
    dst = " + ".join(f"(CASE WHEN {b} < k AND ((u{b} >= {t[0]} AND u{b} < {t[1]}) OR u{b} >= {t[2]}) THEN {1 << b} ELSE 0 END)" for b, _ in bits)
    return f"{_DRAWS} SELECT DISTINCT least(s, d) AS src, greatest(s, d) AS dst FROM (SELECT ({src})::BIGINT AS s, ({dst})::BIGINT AS d FROM (SELECT k, {draws} FROM t, z)) WHERE s <> d"


def urand_sql() -> str:
    s, d = (_MD5.format(f"'{c}:'||i") for c in "sd")
    return f"{_DRAWS} SELECT DISTINCT least(s, d) AS src, greatest(s, d) AS dst FROM (SELECT {s} % (1::BIGINT << k) AS s, {d} % (1::BIGINT << k) AS d FROM t, z) WHERE s <> d"


def draws(spark: SparkSession, sf_dir: str) -> tuple[int, DataFrame]:
    """(k, ids): the log of the vertices of urand and kron, and one id a draw."""
    ids = load(spark, sf_dir, "events").select(F.col("event_id").alias("id"))
    return max(1, min(24, (ids.count() // 16).bit_length() - 1)), ids


#: (src, dst) of each graph in DuckDB's SQL. copart, cosupp, coact, knn, neardup, urand and kron have one row an undirected edge.
GRAPH_SQL = {
    "trade": "SELECT DISTINCT 2*o_custkey AS src, 2*l_suppkey+1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "supply": "SELECT DISTINCT 2*l_partkey AS src, 2*l_suppkey+1 AS dst FROM lineitem",
    "copart": _pairs("l_orderkey", "l_partkey"),
    "cosupp": _pairs("l_orderkey", "l_suppkey"),
    "coact": "WITH u AS (SELECT DISTINCT user_id, floor(epoch(ts))::BIGINT // 600 AS b FROM events) SELECT DISTINCT x.user_id AS src, y.user_id AS dst FROM u x JOIN u y ON x.b = y.b AND x.user_id < y.user_id",
    "hop": "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
    "reply": "SELECT DISTINCT a.conv_id*100+a.turn AS src, b.conv_id*100+b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "nation": "SELECT DISTINCT c_nationkey::BIGINT AS src, s_nationkey::BIGINT AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey",
    "link": "SELECT DISTINCT 2*page_id AS src, 2*" + _MD5.format("h") + "+1 AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages)",
    "geo": "SELECT n_regionkey::BIGINT AS src, 100+n_nationkey::BIGINT AS dst FROM nation UNION SELECT 100+c_nationkey::BIGINT, 1000+2*c_custkey FROM customer UNION SELECT 100+s_nationkey::BIGINT, 1001+2*s_suppkey FROM supplier",
    "neardup": "WITH h AS (SELECT DISTINCT doc_id, md5(lower(trim(text))) AS k FROM documents) SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM h a JOIN h b ON a.k = b.k AND a.doc_id < b.doc_id",
    "knn": "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings), n AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS r FROM v) SELECT a.vec_id AS src, b.vec_id AS dst FROM n a JOIN n b ON a.vec_id < b.vec_id AND list_dot_product(a.e, b.e) / (a.r * b.r) >= 0.3",
    "urand": urand_sql(),
    "kron": kron_sql(),
}
UNDIRECTED = {"copart", "cosupp", "coact", "knn", "neardup", "urand", "kron"}


def _co(df: DataFrame, key: str, item: str) -> DataFrame:
    """Unordered pairs of items that share a key value. Quadratic in a key's items; orders are short (shared_pairs is for longer ones)."""
    a, b = df.select(key, F.col(item).alias("src")).distinct(), df.select(key, F.col(item).alias("dst")).distinct()
    return a.join(b, key).where("src < dst").select("src", "dst").distinct()


def _co_repeated(df: DataFrame, key: str, item: str) -> DataFrame:
    """The pairs of _co, once for each key value that they share: only the items are exchanged, never pairs."""
    items = df.where(F.col(key).isNotNull() & F.col(item).isNotNull()).groupBy(key).agg(F.sort_array(F.collect_set(item)).alias("items")).where("size(items) > 1")
    first = items.select("items", F.posexplode("items").alias("at", "src"))
    return first.select("src", F.explode(F.slice("items", F.col("at") + 2, F.size("items"))).alias("dst"))


def successor_edges(events: DataFrame, partitions: int = 8) -> DataFrame:
    """user -> user of the next event in (ts, event_id) order, without one global window.

    Rows are range-partitioned in order; the successor is found inside each range, and each range's
    last row is stitched to the first row of the next non-empty one.
    """
    scratch = Scratch(events.sparkSession, "successor")
    ordered = events.select("ts", "event_id", "user_id").repartitionByRange(partitions, "ts", "event_id")
    ranged = scratch.save(ordered.withColumn("p", F.spark_partition_id()), "ranged")
    inside = ranged.select(F.col("user_id").alias("src"), F.lead("user_id").over(Window.partitionBy("p").orderBy("ts", "event_id")).alias("dst"))
    ends = ranged.groupBy("p").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"), F.max_by("user_id", F.struct("ts", "event_id")).alias("tail")).orderBy("p").collect()
    stitches = [(a["tail"], b["head"]) for a, b in zip(ends, ends[1:], strict=False)]
    return inside.where("dst is not null").union(events.sparkSession.createDataFrame(stitches, "src bigint, dst bigint"))


def build(spark: SparkSession, sf_dir: str, name: str, repeats: bool = False) -> Graph:
    """The graph by name. repeats: its edges may repeat, for methods that clear them themselves."""
    t = lambda n: load(spark, sf_dir, n)
    co = _co_repeated if repeats else _co
    if name == "trade":
        j = t("orders").select("o_orderkey", "o_custkey").join(t("lineitem").select("l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))
        return Graph.from_edges(j, 2 * F.col("o_custkey"), 2 * F.col("l_suppkey") + 1)
    if name == "supply":
        return Graph.from_edges(t("lineitem"), 2 * F.col("l_partkey"), 2 * F.col("l_suppkey") + 1, dedupe=not repeats)
    if name == "copart":
        return Graph(co(t("lineitem"), "l_orderkey", "l_partkey"))
    if name == "cosupp":
        return Graph(co(t("lineitem"), "l_orderkey", "l_suppkey"))
    if name == "coact":
        return Graph(shared_pairs(t("events").select((F.unix_timestamp(F.col("ts").cast("timestamp")) / 600).cast("bigint").alias("b"), "user_id"), "b", "user_id"))
    if name == "hop":
        return Graph.from_edges(successor_edges(t("events")), "src", "dst")
    if name == "reply":
        c = t("conversations")
        return Graph.from_edges(c.join(c.select("conv_id", (F.col("turn") - 1).alias("turn")).distinct(), ["conv_id", "turn"], "left_semi"), F.col("conv_id") * 100 + F.col("turn"), F.col("conv_id") * 100 + F.col("turn") + 1)
    if name == "nation":
        j = t("orders").select("o_orderkey", "o_custkey").join(t("lineitem").select("l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))
        j = j.join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(t("supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
        return Graph.from_edges(j, "c_nationkey", "s_nationkey")
    if name == "link":
        h = t("pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("h"))
        return Graph.from_edges(h, 2 * F.col("page_id"), 2 * md5_32(F.col("h")) + 1)
    if name == "geo":
        n = t("nation").select(F.col("n_regionkey").cast("bigint").alias("src"), (100 + F.col("n_nationkey").cast("bigint")).alias("dst"))
        c = t("customer").select((100 + F.col("c_nationkey").cast("bigint")).alias("src"), (1000 + 2 * F.col("c_custkey")).alias("dst"))
        s = t("supplier").select((100 + F.col("s_nationkey").cast("bigint")).alias("src"), (1001 + 2 * F.col("s_suppkey")).alias("dst"))
        return Graph(n.union(c).union(s).distinct())
    if name == "neardup":
        return Graph(_co(t("documents").select(F.md5(F.lower(F.trim("text")).cast("binary")).alias("k"), "doc_id"), "k", "doc_id"))
    if name == "knn":
        return Graph(cosine_pairs(t("embeddings"), "vec_id", "embedding", 0.3))
    for kind, draw in (("urand", urand), ("kron", kron)):  # drawn by events; or generated, with the log of their size: urand14, kron16
        if name == kind:
            k, ids = draws(spark, sf_dir)
            return Graph(draw(spark, k, ids=ids))
        if name.startswith(kind) and (size := name.removeprefix(kind)).isdigit():
            return Graph(draw(spark, int(size)))
    raise ValueError(name)
