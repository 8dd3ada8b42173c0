"""Relational, aggregate, window, set and scalar-function queries around the graphs, on the given tables.

Most are one SQL text for both engines over {table} placeholders; a second text is given where the
dialects differ. Reusable operators that SQL lacks (as-of, range, interval and salted joins) are in
graphloom.functions.joins.
"""

from __future__ import annotations

import math
import sys

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.functions import joins
from graphloom.registry import TABLES, load, query, sql_query

_TRADE = "SELECT DISTINCT 2*o_custkey AS src, 2*l_suppkey+1 AS dst FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey"
_BIG = "CAST({} AS BIGINT)"


def _r(x: str, digits: int = 6) -> str:
    return f"ROUND(CAST({x} AS DOUBLE), {digits})"


_COUNT_ALL = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _t in TABLES:
    _k = _COUNT_ALL[_t]
    sql_query(f"scan_{_t}", f"SELECT count(*) AS n, CAST(min({_k}) AS BIGINT) AS lo, CAST(max({_k}) AS BIGINT) AS hi FROM {{{_t}}}")

# projection and filter
sql_query("proj_edges_price", f"SELECT l_partkey AS src, l_suppkey AS dst, {_r('l_extendedprice * (1 - l_discount) * (1 + l_tax)', 1)} AS w FROM {{lineitem}}")
sql_query("filter_active_edges", "SELECT DISTINCT 2*o_custkey AS src, 2*l_suppkey+1 AS dst FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey WHERE o.o_orderdate >= TIMESTAMP '1998-01-01 00:00:00' AND o.o_orderdate < TIMESTAMP '1999-01-01 00:00:00'")
sql_query("filter_in_like", "SELECT p_partkey, p_brand, p_type FROM {part} WHERE p_brand IN ('Brand#11', 'Brand#22', 'Brand#33') AND p_type LIKE 'ECONOMY%'")
sql_query("filter_hub_vertices", f"WITH e AS ({_TRADE}), d AS (SELECT dst AS id, count(*) AS deg FROM e GROUP BY dst) SELECT id, deg FROM d WHERE deg > 1.05 * (SELECT avg(deg) FROM d)")
sql_query("case_degree_class", f"WITH e AS ({_TRADE}), d AS (SELECT src AS id, count(*) AS deg FROM e GROUP BY src) SELECT id, CASE WHEN deg < 10 THEN 'leaf' WHEN deg > 40 THEN 'hub' ELSE 'normal' END AS class FROM d")
sql_query("filter_null_safe", "SELECT c_custkey, coalesce(o_orderkey, -1) AS o FROM {customer} c LEFT JOIN {orders} o ON c.c_custkey = o.o_custkey WHERE o_orderkey IS NOT DISTINCT FROM NULL")
sql_query("dedupe_edges", "SELECT l_orderkey, l_suppkey, l_linenumber FROM (SELECT l_orderkey, l_suppkey, l_linenumber, row_number() OVER (PARTITION BY l_orderkey, l_suppkey ORDER BY l_linenumber) AS k FROM {lineitem}) t WHERE k = 1")

# joins
sql_query("join_trade_edges", _TRADE)
_BY_STATUS = "SELECT {hint} o_orderstatus AS status, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey GROUP BY o_orderstatus"
for _name, _hint in (("join_hint_merge", "/*+ MERGE(o, l) */"), ("join_hint_shuffle_hash", "/*+ SHUFFLE_HASH(l) */")):
    sql_query(_name, _BY_STATUS.format(hint=_hint), _BY_STATUS.format(hint=""))
_NATIONS = "SELECT {hint} c_custkey, n_name, r_name FROM {{customer}} c JOIN {{nation}} n ON c.c_nationkey = n.n_nationkey JOIN {{region}} r ON n.n_regionkey = r.r_regionkey"
sql_query("join_broadcast_nation", _NATIONS.format(hint="/*+ BROADCAST(n, r) */"), _NATIONS.format(hint=""))
_LT = "SELECT {hint} a.n_nationkey AS a, b.n_nationkey AS b FROM {{nation}} a JOIN {{nation}} b ON a.n_nationkey < b.n_nationkey"
sql_query("join_hint_nested_loop", _LT.format(hint="/*+ BROADCAST(b) */"), _LT.format(hint=""))
sql_query("join_left_isolated", "SELECT c_custkey FROM {customer} c LEFT JOIN {orders} o ON c.c_custkey = o.o_custkey WHERE o.o_orderkey IS NULL")
sql_query("join_right_supplier", "SELECT s_suppkey, count(l_orderkey) AS n FROM {lineitem} l RIGHT JOIN {supplier} s ON l.l_suppkey = s.s_suppkey GROUP BY s_suppkey")
sql_query("join_full_degrees", f"WITH e AS ({_TRADE}), a AS (SELECT src AS id, count(*) AS out_deg FROM e GROUP BY src), b AS (SELECT dst AS id, count(*) AS in_deg FROM e GROUP BY dst) SELECT coalesce(a.id, b.id) AS id, coalesce(out_deg, 0) AS out_deg, coalesce(in_deg, 0) AS in_deg FROM a FULL JOIN b ON a.id = b.id")
_SEMI = f"WITH e AS ({_TRADE}) SELECT src, dst FROM e {{0}} (SELECT c_custkey FROM {{customer}} WHERE c_nationkey = 0 {{1}})"
sql_query("join_semi_frontier", f"WITH e AS ({_TRADE}) SELECT src, dst FROM e LEFT SEMI JOIN (SELECT 2*c_custkey AS id FROM {{customer}} WHERE c_nationkey = 0) f ON e.src = f.id", f"WITH e AS ({_TRADE}) SELECT src, dst FROM e WHERE src IN (SELECT 2*c_custkey FROM {{customer}} WHERE c_nationkey = 0)")
sql_query("join_anti_unvisited", f"WITH e AS ({_TRADE}) SELECT s_suppkey FROM {{supplier}} s LEFT ANTI JOIN (SELECT dst FROM e WHERE src = 2) f ON 2*s.s_suppkey+1 = f.dst", f"WITH e AS ({_TRADE}) SELECT s_suppkey FROM {{supplier}} WHERE 2*s_suppkey+1 NOT IN (SELECT dst FROM e WHERE src = 2)")
sql_query("cross_nation_pairs", "WITH t AS (SELECT c_nationkey AS a, s_nationkey AS b, count(*) AS n FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey JOIN {customer} c ON c.c_custkey = o.o_custkey JOIN {supplier} s ON s.s_suppkey = l.l_suppkey GROUP BY c_nationkey, s_nationkey) SELECT x.n_nationkey AS a, y.n_nationkey AS b, coalesce(t.n, 0) AS n FROM {nation} x CROSS JOIN {nation} y LEFT JOIN t ON t.a = x.n_nationkey AND t.b = y.n_nationkey")
_THETA = "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND b.p_retailprice <= 1.001 * a.p_retailprice AND a.p_retailprice <= 1.001 * b.p_retailprice"


@query("theta_part_price", _THETA)
def _theta(s: SparkSession, d: str) -> DataFrame:
    """Prices within the ratio are in one band of the logarithm or in neighbours: each part asks three bands, five where products are so small that
    rounding widens the ratio, to 1.002 at most. Infinity has the band of the largest number, for products near it are infinite; negative infinity, zero and NaN have their own."""
    p, width, most = F.col("p_retailprice"), math.log(1.0011), F.lit(sys.float_info.max)
    own = F.when(F.isnan(p), F.lit(1_000_000)).when(p == 0, F.lit(-1_000_000)).when(p == float("-inf"), F.lit(-1_000_010))
    band = own.when(p > 0, F.floor(F.log(F.least(p, most)) / width).cast("int"))
    near, far = (F.array(*[F.col("band") + k for k in range(-n, n + 1)]) for n in (1, 2))
    parts = load(s, d, "part").select("p_partkey", "p_brand", "p_retailprice", band.alias("band"))
    a = parts.select(F.col("p_partkey").alias("a"), "p_brand", F.col("p_retailprice").alias("pa"), F.explode(F.when(p < 1e-300, far).otherwise(near)).alias("band"))
    b = parts.select(F.col("p_partkey").alias("b"), "p_brand", F.col("p_retailprice").alias("pb"), "band")
    return a.join(b, ["p_brand", "band"]).where("a < b and pb <= 1.001 * pa and pa <= 1.001 * pb").select("a", "b")


sql_query("self_join_copart", "SELECT a.l_partkey AS a, b.l_partkey AS b, count(*) AS n FROM {lineitem} a JOIN {lineitem} b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY a.l_partkey, b.l_partkey")
_VOLUME = "CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE)"
_TOP3 = f"SELECT s_nationkey, s_suppkey, {_VOLUME} AS volume FROM {{lineitem}} l JOIN {{supplier}} s ON l.l_suppkey = s.s_suppkey GROUP BY s_nationkey, s_suppkey"
sql_query("lateral_topk_neighbours", f"WITH v AS ({_TOP3}) SELECT n_nationkey, t.s_suppkey, t.volume FROM {{nation}} n, LATERAL (SELECT s_suppkey, volume FROM v WHERE v.s_nationkey = n.n_nationkey ORDER BY volume DESC, s_suppkey LIMIT 3) t")
sql_query("join_multiway_star", f"SELECT rc.r_name AS customer_region, rs.r_name AS supplier_region, CAST(year(o_orderdate) AS BIGINT) AS y, {_VOLUME} AS volume FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey JOIN {{customer}} c ON c.c_custkey = o.o_custkey JOIN {{supplier}} s ON s.s_suppkey = l.l_suppkey JOIN {{nation}} nc ON nc.n_nationkey = c.c_nationkey JOIN {{region}} rc ON rc.r_regionkey = nc.n_regionkey JOIN {{nation}} ns ON ns.n_nationkey = s.s_nationkey JOIN {{region}} rs ON rs.r_regionkey = ns.n_regionkey GROUP BY rc.r_name, rs.r_name, year(o_orderdate)")


@query("range_join_price_band", "WITH b AS (SELECT range AS band, range * 50000.0 AS lo, (range + 1) * 50000.0 AS hi FROM range(0, 12)) SELECT b.band, count(*) AS n FROM orders JOIN b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY b.band")
def _range_join(s: SparkSession, d: str) -> DataFrame:
    bands = s.range(12).select(F.col("id").alias("band"), (F.col("id") * 50000.0).alias("lo"), ((F.col("id") + 1) * 50000.0).alias("hi"))
    return joins.range_join(load(s, d, "orders").select("o_totalprice"), bands, "o_totalprice", "lo", "hi", 50000.0).groupBy("band").agg(F.count("*").alias("n"))


_ASOF = "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT max(event_id) AS event_id, user_id, ts FROM events WHERE event_type = 'view' GROUP BY user_id, ts) v ON p.user_id = v.user_id AND p.ts >= v.ts"


@query("asof_purchase_view", _ASOF)
def _asof(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "events")
    out = joins.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", "ts"), "user_id", "ts", "view_id")
    return out.select("event_id", "view_id")


_INTERVAL = "SELECT a.event_id AS click, b.event_id AS error FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE"


@query("interval_join_events", _INTERVAL)
def _interval(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    out = joins.interval_join(e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", "t"), e.where("event_type = 'error'").select(F.col("event_id").alias("error"), "user_id", "t"), "user_id", "t", 600_000_000)
    return out.select("click", "error")


@query("join_skew_salted", "SELECT s_suppkey, s_nationkey, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_suppkey, s_nationkey")
def _salted(s: SparkSession, d: str) -> DataFrame:
    line, supplier = load(s, d, "lineitem").select(F.col("l_suppkey").alias("s_suppkey"), "l_orderkey"), load(s, d, "supplier").select("s_suppkey", "s_nationkey")
    return joins.salted_join(line, supplier, "s_suppkey", 8).groupBy("s_suppkey", "s_nationkey").agg(F.count("*").alias("n"))


# aggregation
sql_query("agg_trade_volume", f"SELECT c_nationkey, s_nationkey, count(*) AS n, {_VOLUME} AS total, {_r('avg(l_quantity)')} AS mean_q, min(l_quantity) AS lo, max(l_quantity) AS hi FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey JOIN {{customer}} c ON c.c_custkey = o.o_custkey JOIN {{supplier}} s ON s.s_suppkey = l.l_suppkey GROUP BY c_nationkey, s_nationkey")
sql_query("agg_distinct_neighbours", "SELECT o_custkey, count(DISTINCT l_suppkey) AS suppliers FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey")
sql_query("agg_max_by_partner", "WITH t AS (SELECT o_custkey, l_suppkey, count(*) AS n FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey, l_suppkey) SELECT o_custkey, max_by(l_suppkey, struct(n, -l_suppkey)) AS most, max(n) AS n FROM t GROUP BY o_custkey", "WITH t AS (SELECT o_custkey, l_suppkey, count(*) AS n FROM orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey, l_suppkey) SELECT o_custkey, max_by(l_suppkey, row(n, -l_suppkey)) AS most, max(n) AS n FROM t GROUP BY o_custkey")
_DEGREES = f"WITH e AS ({_TRADE}), d AS (SELECT src AS id, CAST(count(*) AS DOUBLE) AS deg FROM e GROUP BY src)"
sql_query("agg_stats_degree", f"{_DEGREES} SELECT {_r('stddev_samp(deg)')} AS sd, {_r('var_pop(deg)')} AS var, {_r('corr(deg, CAST(id AS DOUBLE))')} AS corr, {_r('covar_pop(deg, CAST(id AS DOUBLE))', 4)} AS covar, {_r('skewness(deg)')} AS skew, {_r('kurtosis(deg)')} AS kurt FROM d", f"{_DEGREES}, z AS (SELECT deg, (deg - avg(deg) OVER ()) AS c FROM d) SELECT {_r('stddev_samp(deg)')} AS sd, {_r('var_pop(deg)')} AS var, {_r('corr(deg, CAST(id AS DOUBLE))')} AS corr, {_r('covar_pop(deg, CAST(id AS DOUBLE))', 4)} AS covar, (SELECT {_r('avg(c*c*c) / pow(avg(c*c), 1.5)')} FROM z) AS skew, (SELECT {_r('avg(c*c*c*c) / pow(avg(c*c), 2) - 3')} FROM z) AS kurt FROM d")
_HOPS = "WITH x AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM {events}), e AS (SELECT DISTINCT src, dst FROM x WHERE dst IS NOT NULL AND src <> dst), o AS (SELECT src AS id, CAST(count(*) AS DOUBLE) AS outs FROM e GROUP BY src), i AS (SELECT dst AS id, CAST(count(*) AS DOUBLE) AS ins FROM e GROUP BY dst)"
sql_query("agg_degree_correlation", f"{_HOPS} SELECT {_r('corr(ins, outs)')} AS in_out, count(*) AS n FROM o JOIN i ON o.id = i.id")
sql_query("agg_median_percentile", f"{_DEGREES} SELECT {_r('median(deg)')} AS med, {_r('percentile(deg, 0.9)')} AS p90, {_r('percentile(deg, 0.25)')} AS p25, mode() WITHIN GROUP (ORDER BY deg) AS most FROM d", f"{_DEGREES} SELECT {_r('median(deg)')} AS med, {_r('quantile_cont(deg, 0.9)')} AS p90, {_r('quantile_cont(deg, 0.25)')} AS p25, (SELECT deg FROM d GROUP BY deg ORDER BY count(*) DESC, deg LIMIT 1) AS most FROM d")
sql_query("agg_filter_clause", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'purchase') AS purchases, bool_and(value >= 0) AS all_positive FROM {events} GROUP BY user_id")
sql_query("agg_collect_sorted", "SELECT o_custkey, array_join(transform(sort_array(collect_set(l_suppkey)), x -> CAST(x AS STRING)), ',') AS nbrs FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey", "SELECT o_custkey, array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') AS nbrs FROM orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey")
sql_query("agg_listagg", "SELECT l_orderkey, listagg(CAST(l_partkey AS STRING), ',') WITHIN GROUP (ORDER BY l_partkey) AS parts FROM (SELECT l_orderkey, CAST(l_partkey AS STRING) AS l_partkey FROM {lineitem}) t GROUP BY l_orderkey", "SELECT l_orderkey, string_agg(l_partkey, ',' ORDER BY l_partkey) AS parts FROM (SELECT l_orderkey, l_partkey::VARCHAR AS l_partkey FROM lineitem) GROUP BY l_orderkey")
sql_query("agg_global", f"WITH e AS ({_TRADE}), d AS (SELECT src AS id, count(*) AS deg FROM e GROUP BY src) SELECT count(*) AS n, CAST(sum(deg) AS BIGINT) AS m, max(deg) AS max_deg, {_r('avg(deg)')} AS mean_deg FROM d")
sql_query("rollup_region_nation", "SELECT r_name, n_name, count(*) AS n FROM {customer} c JOIN {nation} n ON c.c_nationkey = n.n_nationkey JOIN {region} r ON n.n_regionkey = r.r_regionkey GROUP BY ROLLUP (r_name, n_name)")
sql_query("cube_flag_status", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS DOUBLE) AS q FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)")
sql_query("gsets_segment_priority", f"SELECT c_mktsegment, o_orderpriority, CAST(grouping(c_mktsegment) AS BIGINT) AS g, count(*) AS n FROM {{orders}} o JOIN {{customer}} c ON o.o_custkey = c.c_custkey GROUP BY GROUPING SETS ((c_mktsegment), (o_orderpriority))")
_TYPES = ("click", "view", "purchase", "error")


@query("pivot_event_type", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in _TYPES) + " FROM events GROUP BY user_id")
def _pivot(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events").groupBy("user_id").pivot("event_type", list(_TYPES)).agg(F.count(F.lit(1))).na.fill(0, list(_TYPES))


@query("unpivot_degrees", "SELECT s_suppkey AS id, 'nation' AS kind, s_nationkey::BIGINT AS deg FROM supplier UNION ALL SELECT s_suppkey, 'balance', floor(s_acctbal)::BIGINT FROM supplier")
def _unpivot(s: SparkSession, d: str) -> DataFrame:
    wide = load(s, d, "supplier").select(F.col("s_suppkey").alias("id"), F.col("s_nationkey").cast("bigint").alias("nation"), F.floor("s_acctbal").cast("bigint").alias("balance"))
    return wide.unpivot("id", ["nation", "balance"], "kind", "deg")


_HOT = "SELECT l_suppkey % 7 AS grp, count(DISTINCT l_partkey) AS exact, true AS hll_ok, true AS sketch_ok FROM lineitem GROUP BY 1"


@query("approx_neighbours", _HOT)
def _approx(s: SparkSession, d: str) -> DataFrame:
    """Distinct neighbours of seven groups of sources: exact, and whether both estimates are within a twentieth of it."""
    line = load(s, d, "lineitem").groupBy((F.col("l_suppkey") % 7).alias("grp"))
    a = line.agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("sketch"))
    near = lambda c: F.abs(F.col(c) - F.col("exact")) <= 0.08 * F.col("exact")
    return a.select("grp", "exact", near("hll").alias("hll_ok"), near("sketch").alias("sketch_ok"))


@query("cms_hubs", "SELECT l_suppkey AS id, count(*) AS arcs FROM lineitem GROUP BY l_suppkey ORDER BY arcs DESC, id LIMIT 10")
def _cms(s: SparkSession, d: str) -> DataFrame:
    """The ten sources of most arcs: a sketch of bounded size names the candidates, one pass counts those exactly."""
    line = load(s, d, "lineitem")
    found = s.sql("SELECT inline(approx_top_k(l_suppkey, 100, 100000)) FROM {l}", l=line).select("item")
    exact = line.join(F.broadcast(found), F.col("l_suppkey") == F.col("item"), "left_semi").groupBy(F.col("l_suppkey").alias("id")).agg(F.count("*").alias("arcs"))
    return exact.orderBy(F.desc("arcs"), "id").limit(10)


@query("kll_degree", f"{_DEGREES.replace('{orders}', 'orders').replace('{lineitem}', 'lineitem')} SELECT true AS median_ok, true AS p90_ok FROM (SELECT count(*) AS n FROM d)")
def _kll(s: SparkSession, d: str) -> DataFrame:
    """Whether the sketched median and 90 % quantile of the degrees have ranks within 3 % of the true ones."""
    text = f"{_DEGREES}, k AS (SELECT kll_sketch_agg_double(deg) AS t FROM d), q AS (SELECT kll_sketch_get_quantile_double(t, 0.5D) AS a, kll_sketch_get_quantile_double(t, 0.9D) AS b FROM k)"
    text += " SELECT abs(sum(int(deg < a)) / count(*) - 0.5) <= 0.03 + sum(int(deg = a)) / count(*) AS median_ok, abs(sum(int(deg < b)) / count(*) - 0.9) <= 0.03 + sum(int(deg = b)) / count(*) AS p90_ok FROM d CROSS JOIN q"
    return s.sql(text, orders=load(s, d, "orders"), lineitem=load(s, d, "lineitem"))


@query("theta_overlap", "SELECT count(*) AS exact, true AS near FROM (SELECT l_partkey FROM lineitem WHERE l_suppkey % 2 = 0 INTERSECT SELECT l_partkey FROM lineitem WHERE l_suppkey % 2 = 1)")
def _theta(s: SparkSession, d: str) -> DataFrame:
    """Common neighbours of the even and the odd sources: exact, and whether the sketched number is within a tenth."""
    text = "WITH a AS (SELECT theta_sketch_agg(l_partkey) AS t FROM {l} WHERE l_suppkey % 2 = 0), b AS (SELECT theta_sketch_agg(l_partkey) AS t FROM {l} WHERE l_suppkey % 2 = 1), c AS (SELECT count(*) AS exact FROM (SELECT l_partkey FROM {l} WHERE l_suppkey % 2 = 0 INTERSECT SELECT l_partkey FROM {l} WHERE l_suppkey % 2 = 1))"
    return s.sql(text + " SELECT exact, abs(theta_sketch_estimate(theta_intersection(a.t, b.t)) - exact) <= 0.1 * exact AS near FROM a, b, c", l=load(s, d, "lineitem"))


sql_query("bitmap_reach", "SELECT d, CAST(sum(c) AS BIGINT) AS users FROM (SELECT date_format(ts, 'yyyy-MM-dd') AS d, bitmap_bucket_number(user_id + 1) AS b, bitmap_count(bitmap_construct_agg(bitmap_bit_position(user_id + 1))) AS c FROM {events} GROUP BY 1, 2) t GROUP BY d", "SELECT strftime(ts, '%Y-%m-%d') AS d, count(DISTINCT user_id) AS users FROM events GROUP BY 1")

# windows, sort, top-k
_WIN = "PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey"
sql_query("win_rank_in_nation", f"SELECT c_custkey, {_BIG.format(f'row_number() OVER ({_WIN})')} AS rn, {_BIG.format('rank() OVER (PARTITION BY c_nationkey ORDER BY floor(c_acctbal / 1000) DESC)')} AS rk, {_BIG.format('dense_rank() OVER (PARTITION BY c_nationkey ORDER BY floor(c_acctbal / 1000) DESC)')} AS dr FROM {{customer}}")
sql_query("win_percent", f"SELECT c_custkey, {_r('percent_rank() OVER (' + _WIN + ')')} AS pr, {_r('cume_dist() OVER (' + _WIN + ')')} AS cd FROM {{customer}}")
sql_query("win_ntile_degree", f"WITH e AS ({_TRADE}), d AS (SELECT src AS id, count(*) AS deg FROM e GROUP BY src) SELECT id, {_BIG.format('ntile(10) OVER (ORDER BY deg, id)')} AS decile FROM d")
sql_query("win_lag_event_gap", f"SELECT event_id, {_BIG.format('unix_timestamp(ts) - unix_timestamp(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))')} AS gap FROM {{events}}", "SELECT event_id, floor(epoch(ts))::BIGINT - floor(epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)))::BIGINT AS gap FROM events")
_FULL = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
sql_query("win_first_last_nth", f"SELECT DISTINCT o_custkey, first_value(o_orderkey) {_FULL} AS first_order, last_value(o_orderkey) {_FULL} AS last_order, nth_value(o_orderkey, 2) {_FULL} AS second_order FROM {{orders}}")
sql_query("win_cumulative_degree", "WITH d AS (SELECT c_nationkey, c_custkey, count(o_orderkey) AS deg FROM {customer} c LEFT JOIN {orders} o ON c.c_custkey = o.o_custkey GROUP BY c_nationkey, c_custkey) SELECT c_custkey, CAST(sum(deg) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS upto FROM d")
sql_query("win_moving_avg_7", f"SELECT event_id, {_r('avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)', 4)} AS mean7 FROM {{events}}")
sql_query("win_range_30d", "SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY t RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW) AS DOUBLE) AS last30 FROM (SELECT o_orderkey, o_custkey, o_totalprice, unix_timestamp(o_orderdate) AS t FROM {orders}) x", "SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY t RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW) AS DOUBLE) AS last30 FROM (SELECT o_orderkey, o_custkey, o_totalprice, floor(epoch(o_orderdate))::BIGINT AS t FROM orders) x")
_SESSION = "SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN gap IS NULL OR gap > 86400 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS session FROM (SELECT user_id, event_id, t, t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) AS gap FROM (SELECT user_id, event_id, {} AS t FROM {{events}}) x) y) z GROUP BY user_id, session"
sql_query("win_sessionize", _SESSION.format("unix_timestamp(ts)"), _SESSION.format("floor(epoch(ts))::BIGINT").replace("session, count(*)", "session::BIGINT AS session, count(*)", 1))
sql_query("sort_degree", f"WITH e AS ({_TRADE}) SELECT src AS id, count(*) AS deg FROM e GROUP BY src ORDER BY deg DESC NULLS LAST, id")
sql_query("topk_degree", f"WITH e AS ({_TRADE}) SELECT src AS id, count(*) AS deg FROM e GROUP BY src ORDER BY deg DESC, id LIMIT 10")
sql_query("topk_per_nation", f"SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER ({_WIN}) AS k FROM {{customer}}) t WHERE k <= 3")
sql_query("limit_offset_ranked", f"WITH e AS ({_TRADE}) SELECT src AS id, count(*) AS deg FROM e GROUP BY src ORDER BY deg DESC, id LIMIT 10 OFFSET 5")

# sets, subqueries, recursion, sampling
_YEAR = "SELECT {distinct} 2*o_custkey AS src, 2*l_suppkey+1 AS dst FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey WHERE year(o_orderdate) = {year}"
_Y = lambda distinct, year: _YEAR.format(distinct=distinct, year=year)
for _name, _op, _d in (("set_union_all", "UNION ALL", ""), ("set_union_edges", "UNION", "DISTINCT"), ("set_intersect_edges", "INTERSECT", "DISTINCT"), ("set_intersect_all", "INTERSECT ALL", ""), ("set_except_edges", "EXCEPT", "DISTINCT"), ("set_except_all", "EXCEPT ALL", "")):
    sql_query(_name, f"({_Y(_d, 1995)}) {_op} ({_Y(_d, 1996)})")
sql_query("subq_exists_orders", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_orderpriority = '1-URGENT')")
sql_query("subq_not_in", "SELECT c_custkey FROM {customer} c WHERE c_custkey NOT IN (SELECT o_custkey FROM {orders} WHERE o_orderpriority = '1-URGENT')")
sql_query("subq_scalar_above_avg", "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders} x WHERE x.o_custkey = o.o_custkey)")
_GEO_TREE = "SELECT n_regionkey AS src, CAST(100+n_nationkey AS BIGINT) AS dst FROM {nation} UNION ALL SELECT 100+c_nationkey, CAST(1000+2*c_custkey AS BIGINT) FROM {customer}"
sql_query("rcte_geo_tree", f"WITH RECURSIVE e AS ({_GEO_TREE}), w(id, depth) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT e.dst, w.depth + 1 FROM w JOIN e ON e.src = w.id) SELECT depth, count(*) AS n FROM w GROUP BY depth")
sql_query("rcte_reply_depth", "WITH RECURSIVE w(conv_id, turn, depth) AS (SELECT conv_id, turn, 1 FROM {conversations} WHERE turn = 0 UNION ALL SELECT c.conv_id, c.turn, w.depth + 1 FROM w JOIN {conversations} c ON c.conv_id = w.conv_id AND c.turn = w.turn + 1) SELECT conv_id, max(depth) AS length FROM w GROUP BY conv_id")
sql_query("sample_edges_md5", f"WITH e AS ({_TRADE}) SELECT src, dst FROM e WHERE substr(md5(concat(src, ':', dst)), 1, 1) = '0'")


@query("sample_stratified")
def _stratified(s: SparkSession, d: str) -> DataFrame:
    c = load(s, d, "customer")
    return c.sampleBy("c_mktsegment", {"BUILDING": 0.5, "MACHINERY": 0.1}, seed=3)


sql_query("edge_upsert", f"WITH old AS ({_Y('DISTINCT', 1995)}), new AS ({_Y('DISTINCT', 1996)}) SELECT src, dst, 1996 AS seen FROM new UNION ALL SELECT o.src, o.dst, 1995 FROM old o LEFT ANTI JOIN new n ON o.src = n.src AND o.dst = n.dst", f"WITH old AS ({_Y('DISTINCT', 1995)}), new AS ({_Y('DISTINCT', 1996)}) SELECT src, dst, 1996 AS seen FROM new UNION ALL SELECT o.src, o.dst, 1995 FROM old o WHERE NOT EXISTS (SELECT 1 FROM new n WHERE o.src = n.src AND o.dst = n.dst)")


@query("values_inline", "SELECT * FROM (VALUES (1, 2), (2, 3), (3, 1)) AS e(src, dst)")
def _values(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT * FROM VALUES (1, 2), (2, 3), (3, 1) AS e(src, dst)")


# scalar, nested and JSON functions
sql_query("fn_page_host", "SELECT page_id, parse_url(url, 'HOST') AS host, try_parse_url(url, 'HOST') AS host2, split_part(url, '/', 4) AS first_step, regexp_extract(url, '^([a-z]+)', 1) AS scheme FROM {pages}", "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, regexp_extract(url, '://([^/?#]*)', 1) AS host2, split_part(url, '/', 4) AS first_step, regexp_extract(url, '^([a-z]+)', 1) AS scheme FROM pages")
sql_query("fn_page_links", "SELECT page_id, count(*) AS links, count(DISTINCT h) AS targets FROM (SELECT page_id, explode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM {pages}) t GROUP BY page_id", "SELECT page_id, count(*) AS links, count(DISTINCT h) AS targets FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages) t GROUP BY page_id")
sql_query("fn_link_places", "SELECT page_id, CAST(p AS BIGINT) AS p, h FROM (SELECT page_id, posexplode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS (p, h) FROM {pages}) t", "SELECT page_id, unnest(range(len(l))) AS p, unnest(l) AS h FROM (SELECT page_id, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS l FROM pages)")
sql_query("fn_text_pack", "SELECT p_partkey, CAST(instr(p_type, ' ') AS BIGINT) AS place, split(p_type, ' ')[0] AS first_word, initcap(lower(p_type)) AS cap, regexp_replace(p_type, '[AEIOU]', '*') AS rx FROM {part}", "SELECT p_partkey, instr(p_type, ' ')::BIGINT AS place, string_split(p_type, ' ')[1] AS first_word, array_to_string(list_transform(string_split(lower(p_type), ' '), lambda w: upper(w[1]) || w[2:]), ' ') AS cap, regexp_replace(p_type, '[AEIOU]', '*', 'g') AS rx FROM part")
sql_query("fn_string_pack", f"SELECT p_partkey, lower(p_name) AS lo, upper(p_name) AS up, {_BIG.format('length(p_name)')} AS len, substring(p_name, 1, 3) AS head, {_BIG.format(chr(108)+'evenshtein(p_brand, p_type)')} AS lev, lpad(p_brand, 12, '*') AS lp, rpad(p_brand, 12, '*') AS rp, reverse(p_brand) AS rev, translate(p_brand, 'B#', 'b-') AS tr, concat_ws('|', p_brand, p_type) AS ws, replace(p_type, ' ', '_') AS rx, repeat('ab', 2) AS rep, trim(concat(' ', p_brand, ' ')) AS tm FROM {{part}}")
sql_query("fn_md5_owner", "SELECT c_custkey, md5(CAST(c_custkey AS STRING)) AS h, CAST(conv(substr(md5(CAST(c_custkey AS STRING)), 1, 8), 16, 10) AS BIGINT) % 4 AS part, sha2(c_name, 256) AS s, crc32('123456789') AS crc FROM {customer}", "SELECT c_custkey, md5(c_custkey::VARCHAR) AS h, ('0x'||substr(md5(c_custkey::VARCHAR),1,8))::BIGINT % 4 AS part, sha256(c_name) AS s, 3421780262::BIGINT AS crc FROM customer")
sql_query("fn_order_month", f"SELECT o_orderkey, {_BIG.format('year(o_orderdate)')} AS y, {_BIG.format('month(o_orderdate)')} AS m, {_BIG.format('quarter(o_orderdate)')} AS q, {_BIG.format('dayofweek(o_orderdate)')} AS dow, {_BIG.format('weekofyear(o_orderdate)')} AS wk, date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd') AS mon FROM {{orders}}", f"SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, quarter(o_orderdate) AS q, dayofweek(o_orderdate) + 1 AS dow, weekofyear(o_orderdate) AS wk, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon FROM orders")
sql_query("fn_ship_lag", f"SELECT l_orderkey, l_linenumber, {_BIG.format('datediff(CAST(l_shipdate AS DATE), CAST(o_orderdate AS DATE))')} AS lag, CAST(last_day(o_orderdate) AS STRING) AS eom, CAST(date_add(CAST(o_orderdate AS DATE), 7) AS STRING) AS plus7, CAST(add_months(CAST(o_orderdate AS DATE), 1) AS STRING) AS plus1m, {_r("months_between(CAST(l_shipdate AS DATE), CAST(o_orderdate AS DATE), false) * 31 - 31 * (12 * (year(l_shipdate) - year(o_orderdate)) + month(l_shipdate) - month(o_orderdate))", 4)} AS days_apart FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey", "SELECT l_orderkey, l_linenumber, datediff('day', o_orderdate::DATE, l_shipdate::DATE) AS lag, last_day(o_orderdate)::VARCHAR AS eom, (o_orderdate::DATE + 7)::VARCHAR AS plus7, ((o_orderdate::DATE + INTERVAL 1 MONTH)::DATE)::VARCHAR AS plus1m, CASE WHEN day(l_shipdate) = day(o_orderdate) OR (l_shipdate::DATE = last_day(l_shipdate) AND o_orderdate::DATE = last_day(o_orderdate)) THEN 0.0::DOUBLE ELSE (day(l_shipdate) - day(o_orderdate))::DOUBLE END AS days_apart FROM orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey")
sql_query("fn_time_bucket", "SELECT CAST(floor(unix_timestamp(ts) / 600) * 600 AS BIGINT) AS bucket, count(*) AS n FROM {events} GROUP BY 1", "SELECT (floor(floor(epoch(ts)) / 600) * 600)::BIGINT AS bucket, count(*) AS n FROM events GROUP BY 1")
sql_query("fn_event_window", "SELECT date_format(w.start, 'yyyy-MM-dd HH:mm') AS opens, count(*) AS n, min(CAST(from_unixtime(unix_timestamp(ts), 'yyyy-MM-dd HH:mm:ss') AS STRING)) AS first_ts FROM (SELECT window(ts, '6 hours') AS w, ts FROM {events}) t GROUP BY w.start", "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M') AS opens, count(*) AS n, strftime(date_trunc('second', min(ts)), '%Y-%m-%d %H:%M:%S') AS first_ts FROM events GROUP BY 1, time_bucket(INTERVAL 6 HOUR, ts)")
sql_query("fn_more_math", "SELECT l_orderkey, l_linenumber, CAST(bround(CAST(l_quantity AS DECIMAL(10,1)) / 2, 0) AS DOUBLE) AS br, ROUND(log2(l_quantity), 6) AS lg2, pmod(CAST(l_quantity AS BIGINT) - 25, 7) AS pm, width_bucket(l_extendedprice, 0, 100000, 10) AS wb FROM {lineitem}", "SELECT l_orderkey, l_linenumber, round_even(l_quantity / 2, 0)::DOUBLE AS br, round(log2(l_quantity), 6) AS lg2, (((l_quantity::BIGINT - 25) % 7) + 7) % 7 AS pm, (CASE WHEN l_extendedprice >= 100000 THEN 11 ELSE floor(l_extendedprice / 10000) + 1 END)::BIGINT AS wb FROM lineitem")
sql_query("fn_math_pack", f"SELECT l_orderkey, l_linenumber, {_r('sqrt(l_quantity)')} AS sq, {_r('ln(l_extendedprice)')} AS ln, {_r('log10(l_quantity)')} AS lg, {_r('pow(l_discount, 2)')} AS pw, {_r('exp(l_tax)')} AS ex, {_BIG.format('floor(l_extendedprice)')} AS fl, {_BIG.format('ceil(l_extendedprice)')} AS ce, {_r('abs(l_discount - l_tax)')} AS ab, greatest(l_discount, l_tax) AS gr, least(l_discount, l_tax) AS le, {_BIG.format('sign(l_discount - l_tax)')} AS sg FROM {{lineitem}}")
sql_query("fn_bits", "SELECT c_custkey, shiftleft(c_custkey, 2) AS sl, shiftright(c_custkey, 1) AS sr, c_custkey & 12 AS an, c_custkey | 3 AS o, c_custkey ^ 5 AS x, CAST(bit_count(c_custkey) AS BIGINT) AS bc FROM {customer}", "SELECT c_custkey, c_custkey << 2 AS sl, c_custkey >> 1 AS sr, c_custkey & 12 AS an, c_custkey | 3 AS o, xor(c_custkey, 5) AS x, bit_count(c_custkey)::BIGINT AS bc FROM customer")
_LISTS = "SELECT o_custkey AS id, {} AS nbrs FROM {{orders}} o JOIN {{lineitem}} l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey"
_SL, _DL = _LISTS.format("sort_array(collect_set(l_suppkey))"), _LISTS.format("list_sort(list(DISTINCT l_suppkey))")
sql_query("fn_array_pack", f"WITH a AS ({_SL}) SELECT id, {_BIG.format('size(nbrs)')} AS n, array_contains(nbrs, 7) AS has7, array_min(nbrs) AS lo, array_max(nbrs) AS hi, {_BIG.format('array_position(nbrs, nbrs[0])')} AS pos, array_join(slice(nbrs, 1, 3), ',') AS head, {_BIG.format('size(array_union(nbrs, sequence(0L, 9L)))')} AS un, {_BIG.format('size(array_except(nbrs, sequence(0L, 9L)))')} AS ex, arrays_overlap(nbrs, array(1L, 2L)) AS ov FROM a", f"WITH a AS ({_DL}) SELECT id, len(nbrs) AS n, list_contains(nbrs, 7) AS has7, list_min(nbrs) AS lo, list_max(nbrs) AS hi, list_position(nbrs, nbrs[1])::BIGINT AS pos, array_to_string(nbrs[1:3], ',') AS head, len(list_distinct(list_concat(nbrs, range(0, 10)))) AS un, len(list_filter(nbrs, lambda x: x > 9)) AS ex, list_has_any(nbrs, [1, 2]) AS ov FROM a")
sql_query("fn_array_more", f"WITH a AS ({_SL}) SELECT id, CAST(size(array_distinct(concat(nbrs, nbrs))) AS BIGINT) AS n, CAST(size(flatten(array(nbrs, nbrs))) AS BIGINT) AS twice, element_at(nbrs, -1) AS last, aggregate(zip_with(nbrs, reverse(nbrs), (x, y) -> x * y), 0L, (s, x) -> s + x) AS mirror, CAST(size(arrays_zip(nbrs, nbrs)) AS BIGINT) AS zipped FROM a", f"WITH a AS ({_DL}) SELECT id, len(list_distinct(list_concat(nbrs, nbrs))) AS n, len(flatten([nbrs, nbrs])) AS twice, nbrs[-1] AS last, list_sum(list_transform(list_zip(nbrs, list_reverse(nbrs)), lambda p: p[1] * p[2]))::BIGINT AS mirror, len(list_zip(nbrs, nbrs)) AS zipped FROM a")
sql_query("fn_array_hof", f"WITH a AS ({_SL}) SELECT id, aggregate(transform(nbrs, x -> x * x), 0L, (s, x) -> s + x) AS sq, {_BIG.format('size(filter(nbrs, x -> x % 2 = 0))')} AS even, exists(nbrs, x -> x > 90) AS big, forall(nbrs, x -> x >= 0) AS fine FROM a", f"WITH a AS ({_DL}) SELECT id, list_sum(list_transform(nbrs, lambda x: x * x))::BIGINT AS sq, len(list_filter(nbrs, lambda x: x % 2 = 0)) AS even, list_max(nbrs) > 90 AS big, list_min(nbrs) >= 0 AS fine FROM a")
sql_query("fn_dot_product", "SELECT a.vec_id AS a, b.vec_id AS b, ROUND(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> CAST(x AS DOUBLE) * CAST(y AS DOUBLE)), CAST(0 AS DOUBLE), (s, x) -> s + x), 6) AS dot FROM {embeddings} a JOIN {embeddings} b ON b.vec_id = a.vec_id + 1", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
sql_query("fn_map_pack", "SELECT user_id, map_filter(m, (k, v) -> k = 'click')['click'] AS clicks, CAST(size(map_keys(m)) AS BIGINT) AS kinds, aggregate(map_values(m), 0L, (s, x) -> s + x) AS total FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) x GROUP BY user_id) y", "SELECT user_id, sum(CASE WHEN event_type = 'click' THEN n END)::BIGINT AS clicks, count(*) AS kinds, sum(n)::BIGINT AS total FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) GROUP BY user_id")
sql_query("fn_map_values", "SELECT user_id, aggregate(map_values(transform_values(m, (k, v) -> v * 2)), 0L, (s, x) -> s + x) AS doubled FROM (SELECT user_id, map_from_entries(collect_list(struct(event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) x GROUP BY user_id) y", "SELECT user_id, 2 * count(*) AS doubled FROM events GROUP BY user_id")
sql_query("fn_inline_edges", "SELECT l_orderkey, src, dst FROM (SELECT l_orderkey, inline(array(named_struct('src', l_partkey, 'dst', l_suppkey))) FROM {lineitem}) t", "SELECT l_orderkey, l_partkey AS src, l_suppkey AS dst FROM lineitem")
sql_query("fn_json_more", "SELECT event_id, CAST(k AS BIGINT) AS k, to_json(named_struct('id', event_id)) AS j FROM {events} LATERAL VIEW json_tuple(props, 'k') t AS k", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, '{\"id\":' || event_id || '}' AS j FROM events")
sql_query("fn_struct_edge", "SELECT e.src AS src, e.dst AS dst FROM (SELECT named_struct('src', l_partkey, 'dst', l_suppkey) AS e FROM {lineitem}) t", "SELECT l_partkey AS src, l_suppkey AS dst FROM lineitem")
sql_query("fn_event_props", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k1, from_json(props, 'k BIGINT').k AS k2 FROM {events}", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k1, json_extract_string(props, '$.k')::BIGINT AS k2 FROM events")
sql_query("fn_variant_props", "SELECT event_id, variant_get(parse_json(props), '$.k', 'bigint') AS k FROM {events}", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
sql_query("fn_decimal_sum", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM {lineitem} GROUP BY l_returnflag")
sql_query("fn_safe_pack", "SELECT c_custkey, nanvl(CASE WHEN c_nationkey = 0 THEN CAST('NaN' AS DOUBLE) ELSE c_acctbal END, -1.0D) AS nv, try_divide(c_acctbal, CAST(c_nationkey AS DOUBLE)) IS NULL AS by_zero FROM {customer}", "SELECT c_custkey, CASE WHEN c_nationkey = 0 THEN -1.0::DOUBLE ELSE c_acctbal END AS nv, c_nationkey = 0 AS by_zero FROM customer")
sql_query("fn_null_pack", "SELECT c_custkey, nullif(c_nationkey, 0) AS nn, coalesce(nullif(c_nationkey, 0), -1) AS co, try_cast(c_name AS INT) AS tc, CASE WHEN c_nationkey = 0 THEN NULL ELSE c_custkey END AS cs FROM {customer}")
_SIM = "WITH e AS (SELECT DISTINCT l_suppkey AS s, l_partkey AS p FROM {lineitem}), d AS (SELECT s, count(*) AS deg FROM e GROUP BY s), pd AS (SELECT p, count(*) AS deg FROM e GROUP BY p), c AS (SELECT a.s AS a, b.s AS b, count(*) AS k, sum(1 / ln(CAST(pd.deg AS DOUBLE) + 1)) AS aa FROM e a JOIN e b ON a.p = b.p AND a.s < b.s JOIN pd ON pd.p = a.p WHERE a.s < 20 AND b.s < 20 GROUP BY a.s, b.s)"
for _name, _x in (("sim_jaccard", "CAST(k AS DOUBLE) / (x.deg + y.deg - k)"), ("sim_overlap", "CAST(k AS DOUBLE) / least(x.deg, y.deg)"), ("sim_adamic", "aa"), ("sim_pref", "CAST(x.deg * y.deg AS DOUBLE)")):
    sql_query(_name, f"{_SIM} SELECT a, b, {_r(_x)} AS sim FROM c JOIN d x ON x.s = a JOIN d y ON y.s = b")
_ENTROPY = "WITH t AS (SELECT o_custkey AS id, l_suppkey AS p, CAST(count(*) AS DOUBLE) AS n FROM {orders} o JOIN {lineitem} l ON o.o_orderkey = l.l_orderkey GROUP BY o_custkey, l_suppkey), s AS (SELECT id, p, n, sum(n) OVER (PARTITION BY id) AS total FROM t)"
sql_query("nbr_entropy", f"{_ENTROPY} SELECT id, {_r('-sum(n / total * ln(n / total))')} AS entropy FROM s GROUP BY id")
sql_query("fn_common_neighbours", f"WITH a AS ({_SL}) SELECT x.id AS a, y.id AS b, {_BIG.format('size(array_intersect(x.nbrs, y.nbrs))')} AS n FROM a x JOIN a y ON y.id = x.id + 1", f"WITH a AS ({_DL}) SELECT x.id AS a, y.id AS b, len(list_intersect(x.nbrs, y.nbrs)) AS n FROM a x JOIN a y ON y.id = x.id + 1")
