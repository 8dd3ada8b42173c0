"""A spread of registered queries against their SQL on the smallest tables; and the entry point."""

import duckdb
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

import __spark_entry__ as entry
from graphloom.plans.graph import Graph
from graphloom.registry import TABLES

NAMES = """graph_edges_trade graph_edges_hop csr_offsets tri_oriented_hop tri_sparsified pr_iter10_hop pr_dangling bfs_parent_trade
bfs_multi_trade cc_geo base_vprog_bfs_trade cost_ghosts_hop asof_purchase_view interval_join_events win_sessionize set_except_all
rcte_reply_depth fn_array_pack stream_tumbling stream_triangles udf_intersect_arrow io_edgelist_roundtrip""".split()


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(r[i] for i in order) for r in data), key=repr)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = entry.queries()[name](spark, sf)
    got = con.execute(entry.oracle_sql()[name])
    columns = [d[0] for d in got.description]
    assert sorted(columns) == sorted(df.columns)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(columns, got.fetchall())


@pytest.mark.parametrize("name", ["graph_edges_kron", "kron_edges", "graph_edges_urand", "ds_urand_source", "cost_degree_skew_kron", "tri_naive_kron", "bfs_parent_urand"])
def test_drawn_graphs_come_from_events(spark, sf, name):
    assert "FROM events" in entry.oracle_sql()[name] and "range(" not in entry.oracle_sql()[name]
    if "edges" in name:
        assert [f.rsplit("/", 1)[1] for f in entry.queries()[name](spark, sf).inputFiles()] == ["events.parquet"]
    test_query_equals_sql(spark, sf, name)


@pytest.mark.parametrize("name", ["graph_edges_coact", "graph_edges_knn", "project_supply", "project_link", "theta_part_price"])
def test_tiled_pairs_equal_sql(spark, sf, name):
    test_query_equals_sql(spark, sf, name)
    plan = entry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "mapinarrow" in plan.lower() or "band" in plan


def test_projection_of_scattered_ids_exchanges_no_pairs(spark, sf, tmp_path):
    con = duckdb.connect()
    con.execute(f"COPY (SELECT l_partkey * 7919 % 1200091 - 500000 AS l_partkey, l_suppkey * 104729 % 60101 AS l_suppkey FROM '{sf}/lineitem.parquet') TO '{tmp_path}/lineitem.parquet'")
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    want = con.execute("SELECT a.p, b.p FROM (SELECT DISTINCT 2 * l_partkey AS p, l_suppkey AS s FROM lineitem) a JOIN (SELECT DISTINCT 2 * l_partkey AS p, l_suppkey AS s FROM lineitem) b ON a.s = b.s AND a.p < b.p GROUP BY 1, 2 HAVING count(*) >= 3").fetchall()
    edges = spark.read.parquet(str(tmp_path / "lineitem.parquet")).selectExpr("2 * l_partkey AS src", "2 * l_suppkey + 1 AS dst")
    got = Graph(edges.union(spark.createDataFrame([(None, 1), (2, None)], edges.schema))).project(3).edges
    assert want and sorted(tuple(r) for r in got.collect()) == sorted(want)
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()


def test_theta_part_price_at_the_ends_of_its_range(spark, tmp_path):
    tiny = 5e-324
    prices = [None, *map(float, ("nan nan inf inf -inf -inf".split())), 0.0, -0.0, -1.0, -1.0, 1.7976931348623157e308, 1.797e308, 1.796e308, 1.79e308, tiny, tiny, *(k * tiny for k in (498, 499, 500, 501, 502, 1500, 1501, 1502)), *(900 + 0.1 * k for k in range(40))]
    pq.write_table(pa.table({"p_partkey": pa.array(range(len(prices)), pa.int64()), "p_brand": ["x"] * len(prices), "p_retailprice": pa.array(prices, pa.float64())}), tmp_path / "part.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet'")
    want = con.execute(entry.oracle_sql()["theta_part_price"]).fetchall()
    assert sorted(tuple(r) for r in entry.queries()["theta_part_price"](spark, str(tmp_path)).collect()) == sorted(want)


def test_entry(spark):
    assert entry.entry(spark).count() == 20


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_registries_need_no_session():
    import subprocess
    import sys
    from pathlib import Path

    code = "import __spark_entry__ as e; assert len(e.queries()) > 250 and len(e.oracle_sql()) > 230"
    subprocess.run([sys.executable, "-c", code], cwd=Path(entry.__file__).parent, check=True)
