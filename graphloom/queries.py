"""All graph queries: methods, variants, baselines and measures over the experiment graphs, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphloom.operators import baselines, bfs, measures, pagerank, triangles
from graphloom.plans.graph import Graph, adjacency_edges, owner
from graphloom.registry import ORACLES, QUERIES, query
from graphloom.sources.graphs import GRAPH_SQL, UNDIRECTED, build


def _g(spark: SparkSession, sf_dir: str, name: str, repeats: bool = False) -> Graph:
    return build(spark, sf_dir, name, repeats)


def _sym(name: str) -> str:
    return f"SELECT src, dst FROM ({GRAPH_SQL[name]}) UNION SELECT dst, src FROM ({GRAPH_SQL[name]})"


def _und(name: str) -> str:
    return GRAPH_SQL[name] if name in UNDIRECTED else f"SELECT DISTINCT least(src,dst) AS src, greatest(src,dst) AS dst FROM ({GRAPH_SQL[name]}) WHERE src <> dst"


def _with(name: str, kind: str = "raw") -> str:
    body = {"raw": GRAPH_SQL[name], "sym": _sym(name), "und": _und(name)}[kind]
    return f"WITH e AS MATERIALIZED ({body}), v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e)), dg AS MATERIALIZED (SELECT src AS id, count(*) AS deg FROM e GROUP BY src)"


_OWNER = "(('0x'||substr(md5(({})::VARCHAR),1,8))::BIGINT % 4)"
_ID_TRIANGLES = "JOIN e y ON x.dst = y.src JOIN e z ON x.src = z.src AND y.dst = z.dst"


def _triangle_sql(name: str) -> str:
    return f"{_with(name, 'und')} SELECT count(*) AS triangles FROM e x {_ID_TRIANGLES}"


def _pagerank_sql(name: str, kind: str, iters: int = 10, d: float = 0.85, uniform: bool = False, select: str = "SELECT id, round(rank, 9) AS rank FROM r{last}") -> str:
    out = [_with(name, kind), ", n AS (SELECT count(*)::DOUBLE AS n FROM v), r0 AS (SELECT id, 1.0::DOUBLE / n AS rank FROM v, n)"]
    for k in range(iters):
        lost = f" + {d}::DOUBLE * (SELECT coalesce(sum(rank), 0) FROM r{k} WHERE id NOT IN (SELECT src FROM e)) / n" if uniform else ""
        out.append(
            f", r{k + 1} AS MATERIALIZED (SELECT v.id, {1 - d}::DOUBLE / n + {d}::DOUBLE * coalesce(a.s, 0){lost} AS rank FROM v CROSS JOIN n LEFT JOIN "
            f"(SELECT e.dst AS id, sum(r.rank / dg.deg) AS s FROM e JOIN r{k} r ON r.id = e.src JOIN dg ON dg.id = e.src GROUP BY e.dst) a ON a.id = v.id)"
        )
    return "".join(out) + " " + select.format(last=iters)


def _bfs_sql(name: str, kind: str, depth: int, source: str = "(SELECT min(id) FROM v)", select: str = "SELECT id, parent, level FROM t") -> str:
    out = [_with(name, kind), f", l0 AS MATERIALIZED (SELECT id, id AS parent, 0 AS level FROM v WHERE id IN {source})"]
    for k in range(1, depth + 1):
        seen = " UNION ALL ".join(f"SELECT id FROM l{i}" for i in range(k))
        out.append(f", l{k} AS MATERIALIZED (SELECT e.dst AS id, min(e.src) AS parent, {k} AS level FROM e JOIN l{k - 1} f ON f.id = e.src WHERE e.dst NOT IN ({seen}) GROUP BY e.dst)")
    union = " UNION ALL ".join(f"SELECT * FROM l{i}" for i in range(depth + 1))
    return "".join(out) + f", t AS ({union}) " + select


def _components_sql(name: str, rounds: int = 12) -> str:
    out = [_with(name, "sym"), ", c0 AS (SELECT id, id AS c FROM v)"]
    for k in range(rounds):
        out.append(f", c{k + 1} AS MATERIALIZED (SELECT p.id, least(p.c, coalesce(min(q.c), p.c)) AS c FROM c{k} p LEFT JOIN e ON e.src = p.id LEFT JOIN c{k} q ON q.id = e.dst GROUP BY p.id, p.c)")
    return "".join(out) + f" SELECT id, c AS component FROM c{rounds}"


def _source(g: Graph) -> int:
    return g.vertices().agg(F.min("id")).first()[0]


def _ranks(df: DataFrame) -> DataFrame:
    return df.select("id", F.round("rank", 9).alias("rank"))


# ---- views -------------------------------------------------------------------------------------

for _name in GRAPH_SQL:
    query(f"graph_edges_{_name}", f"SELECT src, dst FROM ({GRAPH_SQL[_name]})")(lambda s, d, n=_name: _g(s, d, n).edges.select("src", "dst"))

for _name in ("trade", "hop", "copart"):
    query(f"adjacency_{_name}", f"{_with(_name)} SELECT src AS id, count(*) AS deg, min(dst) AS first_nbr, max(dst) AS last_nbr, sum(dst)::BIGINT AS nbr_sum FROM e GROUP BY src")(
        lambda s, d, n=_name: _g(s, d, n).adjacency(64).select("id", "deg", F.explode("nbrs").alias("x")).groupBy("id", "deg").agg(F.min("x").alias("first_nbr"), F.max("x").alias("last_nbr"), F.sum("x").alias("nbr_sum"))
    )
query("adj_roundtrip", f"SELECT src, dst FROM ({GRAPH_SQL['hop']})")(lambda s, d: adjacency_edges(_g(s, d, "hop").adjacency(16)))
query("csr_offsets", f"{_with('hop')} SELECT id, (sum(deg) OVER (ORDER BY id) - deg)::BIGINT AS first, deg FROM dg")(lambda s, d: _g(s, d, "hop").csr()[0])
query("csr_targets", f"{_with('hop')} SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pos, dst FROM e")(lambda s, d: _g(s, d, "hop").csr()[1])
query("edges_reverse", f"SELECT dst AS src, src AS dst FROM ({GRAPH_SQL['trade']})")(lambda s, d: _g(s, d, "trade").reverse().edges)
query("edges_symmetric", _sym("hop"))(lambda s, d: _g(s, d, "hop").symmetrize().edges)
_RELABEL = "l AS (SELECT id, row_number() OVER (ORDER BY deg DESC, id) - 1 AS label FROM (SELECT id, count(*) AS deg FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id))"
query("relabel_degree", f"{_with('hop')}, {_RELABEL} SELECT a.label AS src, b.label AS dst FROM e JOIN l a ON a.id = e.src JOIN l b ON b.id = e.dst")(lambda s, d: _g(s, d, "hop").relabel("degree")[0].edges)
query("degree_out", f"{_with('hop')} SELECT id, deg FROM dg")(lambda s, d: _g(s, d, "hop").degrees("out"))
query("degree_in", f"{_with('hop')} SELECT dst AS id, count(*) AS deg FROM e GROUP BY dst")(lambda s, d: _g(s, d, "hop").degrees("in"))
query("degree_hist", f"{_with('link', 'sym')} SELECT deg, count(*) AS n FROM dg GROUP BY deg")(lambda s, d: _g(s, d, "link").degree_histogram())
_ORIENT = "SELECT CASE WHEN (a.deg, x.src) < (b.deg, x.dst) THEN x.src ELSE x.dst END AS src, CASE WHEN (a.deg, x.src) < (b.deg, x.dst) THEN x.dst ELSE x.src END AS dst FROM u x JOIN dg a ON a.id = x.src JOIN dg b ON b.id = x.dst"
query("orient_degree", f"{_with('hop', 'sym')}, u AS (SELECT src, dst FROM e WHERE src < dst) {_ORIENT}")(lambda s, d: _g(s, d, "hop").orient("degree").edges)
query("bfs_range_trade", _bfs_sql("trade", "sym", 5, select="SELECT row_number() OVER (ORDER BY level, id) - 1 AS place, id, level FROM t"))(lambda s, d: bfs.bfs_range(g := _g(s, d, "trade").symmetrize(), _source(g)))
_DFS = f"""WITH RECURSIVE e AS ({GRAPH_SQL['geo']}), w AS (SELECT 0::BIGINT AS id, lpad('0', 19, '0') AS path, 0 AS depth
  UNION ALL SELECT e.dst, path || '/' || lpad(e.dst::VARCHAR, 19, '0'), depth + 1 FROM w JOIN e ON e.src = w.id) SELECT path, id, depth FROM w"""
query("dfs_preorder_geo", _DFS)(lambda s, d: bfs.dfs_preorder(_g(s, d, "geo").edges, 0))
query("placement_hash", f"{_with('trade')} SELECT id, {_OWNER.format('id')} AS part FROM v")(lambda s, d: _g(s, d, "trade").place(4))
query("placement_random", f"{_with('trade')} SELECT id, {_OWNER.format(chr(39) + 'r:' + chr(39) + '||id')} AS part FROM v")(lambda s, d: _g(s, d, "trade").place(4, "random"))
query("placement_label_prop")(lambda s, d: _g(s, d, "copart").place(4, "label_prop"))
query("cost_cut_label_prop")(lambda s, d: measures.cut_of(g := _g(s, d, "copart"), g.place(4, "label_prop")))
query("kron_edges", f"SELECT src, dst FROM ({GRAPH_SQL['kron']})")(lambda s, d: _g(s, d, "kron").edges.select("src", "dst"))
for _how in ("range", "degree_balanced"):
    query(f"placement_{_how}")(lambda s, d, h=_how: _g(s, d, "trade").place(4, h))
query("subgraph_trade_low", f"{_with('trade')} SELECT src, dst FROM e WHERE src < 400 AND dst < 400")(lambda s, d: (g := _g(s, d, "trade")).subgraph(g.vertices().where("id < 400")).edges)
query("project_supply", f"{_with('supply')} SELECT a.src AS src, b.src AS dst FROM e a JOIN e b ON a.dst = b.dst AND a.src < b.src GROUP BY 1, 2 HAVING count(*) >= 12")(lambda s, d: _g(s, d, "supply", repeats=True).project(12).edges)
query("project_link", f"{_with('link')} SELECT DISTINCT a.src AS src, b.src AS dst FROM e a JOIN e b ON a.dst = b.dst AND a.src < b.src")(lambda s, d: _g(s, d, "link").project().edges)

# ---- triangles ---------------------------------------------------------------------------------

_TRI = ("copart", "hop", "cosupp", "coact", "trade", "nation", "urand", "kron")
for _name in _TRI:
    query(f"tri_naive_{_name}", _triangle_sql(_name))(lambda s, d, n=_name: triangles.naive(_g(s, d, n, repeats=True)))
    query(f"tri_oriented_{_name}", _triangle_sql(_name))(lambda s, d, n=_name: triangles.oriented(_g(s, d, n, repeats=True)))
for _name in ("copart", "hop", "urand"):
    query(f"tri_partitioned_{_name}", _triangle_sql(_name))(lambda s, d, n=_name: triangles.partitioned(_g(s, d, n)))
    query(f"tri_join_{_name}", _triangle_sql(_name))(lambda s, d, n=_name: triangles.by_edges(_g(s, d, n, repeats=True)))
query("tri_tiled_hop", _triangle_sql("hop"))(lambda s, d: triangles.tiled(_g(s, d, "hop")))
query("tri_outer_seq", _triangle_sql("copart"))(lambda s, d: triangles.partitioned(_g(s, d, "copart"), outer="seq"))
query("tri_outer_par", _triangle_sql("copart"))(lambda s, d: triangles.partitioned(_g(s, d, "copart"), outer="par"))
query("tri_broadcast", _triangle_sql("copart"))(lambda s, d: triangles.broadcast_lists(_g(s, d, "copart")))
_SPARSE = "e2 AS (SELECT src, dst FROM e WHERE ('0x'||substr(md5('e:'||src||':'||dst),1,8))::BIGINT % 16 < 8)"
_SPARSE_SQL = f"{_with('copart', 'und')}, {_SPARSE} SELECT count(*) * 8.0::DOUBLE AS estimate FROM e2 x JOIN e2 y ON x.dst = y.src JOIN e2 z ON x.src = z.src AND y.dst = z.dst"
query("tri_sparsified", _SPARSE_SQL)(lambda s, d: triangles.sparsified(_g(s, d, "copart")))
query("tri_wedge_sampled")(lambda s, d: triangles.wedge_sampled(_g(s, d, "copart")))
_LIST = "tri AS (SELECT x.src AS u, x.dst AS v, y.dst AS w FROM e x " + _ID_TRIANGLES + ")"
_PER_VERTEX = f"{_with('hop', 'und')}, {_LIST}, k AS (SELECT id, count(*) AS n FROM (SELECT u AS id FROM tri UNION ALL SELECT v FROM tri UNION ALL SELECT w FROM tri) GROUP BY id)"
query("tri_per_vertex", f"{_PER_VERTEX} SELECT v.id, coalesce(k.n, 0) AS n FROM v LEFT JOIN k ON k.id = v.id")(lambda s, d: triangles.per_vertex(_g(s, d, "hop")))
query("tri_per_edge", f"{_with('hop', 'sym')} SELECT x.src, x.dst, (SELECT count(*) FROM e a JOIN e b ON a.dst = b.dst WHERE a.src = x.src AND b.src = x.dst) AS n FROM e x WHERE x.src < x.dst")(lambda s, d: triangles.per_edge(_g(s, d, "hop")))
_DEG2 = "dt AS (SELECT id, count(*) AS deg FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id)"
query("clustering_hop", f"{_PER_VERTEX}, {_DEG2} SELECT dt.id, round(CASE WHEN deg > 1 THEN 2.0::DOUBLE * coalesce(k.n, 0) / (deg * (deg - 1)) ELSE 0 END, 9) AS coefficient FROM dt LEFT JOIN k ON k.id = dt.id")(lambda s, d: triangles.clustering(_g(s, d, "hop")))
query("transitivity_hop", f"{_with('hop', 'und')}, {_LIST}, {_DEG2}, a AS (SELECT count(*) AS triangles FROM tri), b AS (SELECT sum(deg * (deg - 1) // 2)::BIGINT AS wedges FROM dt) SELECT triangles, wedges, round(3.0::DOUBLE * triangles / wedges, 9) AS transitivity FROM a, b")(lambda s, d: triangles.transitivity(_g(s, d, "hop")))
query("tri_list_hop", f"{_with('hop', 'und')}, {_LIST} SELECT u, v, w FROM tri")(lambda s, d: triangles.list_triangles(_g(s, d, "hop")))

# ---- PageRank ----------------------------------------------------------------------------------

_STEP_SQL = _pagerank_sql("hop", "raw", 1, select="SELECT r1.id, round(r0.rank, 9) AS old, round(r1.rank, 9) AS rank FROM r1 JOIN r0 ON r0.id = r1.id")
query("pr_step_hop", _STEP_SQL)(lambda s, d: pagerank.step(_g(s, d, "hop")).select("id", F.round("old", 9).alias("old"), F.round("rank", 9).alias("rank")))
for _name, _kind in (("hop", "raw"), ("trade", "sym"), ("copart", "sym"), ("link", "raw"), ("urand", "sym"), ("kron", "sym"), ("geo", "sym")):
    query(f"pr_iter10_{_name}", _pagerank_sql(_name, _kind))(lambda s, d, n=_name, k=_kind: _ranks(pagerank.pagerank(_g(s, d, n) if k == "raw" else _g(s, d, n).symmetrize())))
query("pr_tol_hop", _pagerank_sql("hop", "raw", 12, select="SELECT id, round(rank, 6) AS rank FROM r12"))(lambda s, d: pagerank.pagerank_residuals(_g(s, d, "hop"), tol=1e-9)[0].select("id", F.round("rank", 6).alias("rank")))
query("pr_residuals_hop")(lambda s, d: measures.residual_table(s, pagerank.pagerank_residuals(_g(s, d, "hop"), tol=1e-7)[1]))
query("pr_partitioned_hop", _pagerank_sql("hop", "raw"))(lambda s, d: _ranks(pagerank.pagerank_partitioned(_g(s, d, "hop"))))
query("pr_pull_hop", _pagerank_sql("hop", "raw"))(lambda s, d: _ranks(pagerank.pagerank_pull(_g(s, d, "hop"))))
query("pr_blockgs_hop", _pagerank_sql("hop", "raw", 14, select="SELECT id, round(rank, 6) AS rank FROM r14"))(lambda s, d: pagerank.pagerank_block_sweeps(_g(s, d, "hop"), sweeps=100).select("id", F.round("rank", 6).alias("rank")))
query("pr_leak", _pagerank_sql("trade", "raw"))(lambda s, d: _ranks(pagerank.pagerank(_g(s, d, "trade"))))
query("pr_dangling", _pagerank_sql("trade", "raw", uniform=True))(lambda s, d: _ranks(pagerank.pagerank(_g(s, d, "trade"), dangling="uniform")))
query("pr_d50", _pagerank_sql("hop", "raw", d=0.5))(lambda s, d: _ranks(pagerank.pagerank(_g(s, d, "hop"), d=0.5)))
query("pr_d95", _pagerank_sql("hop", "raw", d=0.95))(lambda s, d: _ranks(pagerank.pagerank(_g(s, d, "hop"), d=0.95)))
query("pr_combine_off", _pagerank_sql("hop", "raw"))(lambda s, d: _ranks(pagerank.pagerank(_g(s, d, "hop"), combine=False)))
query("pr_personal", _pagerank_sql("hop", "raw").replace(f"{1 - 0.85}::DOUBLE / n", f"{1 - 0.85}::DOUBLE * (CASE WHEN v.id < 10 THEN 1.0::DOUBLE / (SELECT count(*) FROM v WHERE id < 10) ELSE 0.0::DOUBLE END)"))(lambda s, d: _ranks(pagerank.pagerank(g := _g(s, d, "hop"), restart=g.vertices().where("id < 10"))))
query("pr_weighted", _pagerank_sql("hop", "raw").replace("sum(r.rank / dg.deg)", "sum(r.rank * (1.0::DOUBLE + e.dst % 3) / (SELECT sum(1.0::DOUBLE + x.dst % 3) FROM e x WHERE x.src = e.src))"))(lambda s, d: _ranks(pagerank.pagerank(Graph((g := _g(s, d, "hop")).edges.withColumn("w", 1.0 + F.col("dst") % 3)), weight="w")))
query("pr_topk_trade", _pagerank_sql("trade", "sym", select="SELECT id, round(rank, 9) AS rank FROM r{last} ORDER BY r{last}.rank DESC, id LIMIT 20"))(lambda s, d: _ranks(pagerank.top_ranked(pagerank.pagerank(_g(s, d, "trade").symmetrize()), 20)))
query("pr_scale_n", _pagerank_sql("hop", "raw", select="SELECT id, round(rank * (SELECT n FROM n), 7) AS rank FROM r{last}"))(lambda s, d: pagerank.pagerank(_g(s, d, "hop"), scale="n").select("id", F.round("rank", 7).alias("rank")))
query("pr_mass", _pagerank_sql("link", "raw", select="SELECT round(sum(rank), 9) AS mass FROM r{last}"))(lambda s, d: pagerank.pagerank(_g(s, d, "link")).agg(F.round(F.sum("rank"), 9).alias("mass")))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["pr_topk_trade"](spark, sf_dir)


# ---- BFS ---------------------------------------------------------------------------------------

_DEPTH = {"trade": 5, "copart": 4, "hop": 4, "geo": 4, "reply": 9, "urand": 6, "kron": 6}
for _name, _depth in _DEPTH.items():
    query(f"bfs_parent_{_name}", _bfs_sql(_name, "sym", _depth))(lambda s, d, n=_name: bfs.bfs(g := _g(s, d, n).symmetrize(), _source(g)))
_LEVELS = "SELECT id, level FROM t"
query("bfs_level_hop", _bfs_sql("hop", "raw", 6, select=_LEVELS))(lambda s, d: bfs.bfs_levels(g := _g(s, d, "hop"), _source(g)))
query("bfs_two_level", _bfs_sql("copart", "sym", 4))(lambda s, d: bfs.bfs(g := _g(s, d, "copart").symmetrize(), _source(g), dedupe="two_level"))
for _name in ("trade", "hop"):
    query(f"bfs_async_{_name}", _bfs_sql(_name, "sym", 5))(lambda s, d, n=_name: bfs.bfs_async_blocks(g := _g(s, d, n).symmetrize(), _source(g)))
    query(f"bfs_auto_{_name}", _bfs_sql(_name, "sym", 5))(lambda s, d, n=_name: bfs.bfs(g := _g(s, d, n).symmetrize(), _source(g), direction="auto"))
query("bfs_multi_trade", _bfs_sql("trade", "sym", 5, source="(SELECT id FROM v WHERE id % 100 = 0)"))(lambda s, d: bfs.bfs(g := _g(s, d, "trade").symmetrize(), g.vertices().where("id % 100 = 0")))
query("bfs_2hop_copart", _bfs_sql("copart", "sym", 2))(lambda s, d: bfs.bfs(g := _g(s, d, "copart").symmetrize(), _source(g), max_depth=2))
_PATH_SQL = _bfs_sql("geo", "sym", 4, select="SELECT level AS hop, id FROM t WHERE id = 1000 OR id = (SELECT parent FROM t WHERE id = 1000) OR id = (SELECT parent FROM t WHERE id = (SELECT parent FROM t WHERE id = 1000)) OR id = (SELECT parent FROM t WHERE id = (SELECT parent FROM t WHERE id = (SELECT parent FROM t WHERE id = 1000)))", source="(SELECT n_regionkey FROM nation JOIN customer ON c_nationkey = n_nationkey WHERE c_custkey = 0)")


@query("sp_path_geo", _PATH_SQL)
def _path(s: SparkSession, d: str) -> DataFrame:
    from graphloom.registry import load

    root = load(s, d, "customer").where("c_custkey = 0").join(load(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).first().n_regionkey
    return bfs.shortest_path(_g(s, d, "geo").symmetrize(), root, 1000)


for _name in ("geo", "reply", "link", "neardup"):
    query(f"cc_{_name}", _components_sql(_name))(lambda s, d, n=_name: bfs.components(_g(s, d, n)))
query("bfs_sql_nation", _bfs_sql("nation", "sym", 4, select=_LEVELS))(lambda s, d: bfs.bfs_sql(g := _g(s, d, "nation").symmetrize(), _source(g), 2))
query("bfs_profile_trade", _bfs_sql("trade", "sym", 5, select="SELECT level, count(*) AS vertices, coalesce(sum(deg), 0)::BIGINT AS arcs_out FROM t LEFT JOIN dg ON dg.id = t.id GROUP BY level"))(lambda s, d: bfs.bfs_profile(g := _g(s, d, "trade").symmetrize(), _source(g)))
_REACH = _bfs_sql("hop", "sym", 6, source="(@)").removeprefix("WITH ").replace(" SELECT id, parent, level FROM t", "")
query("closeness_sample", " UNION ALL ".join(f"SELECT * FROM (WITH {_REACH.replace('@', str(k))} SELECT {k}::BIGINT AS source, count(*) AS reached, sum(level)::BIGINT AS distance_sum, round((count(*) - 1)::DOUBLE / sum(level), 9) AS closeness FROM t)" for k in range(4)))(lambda s, d: bfs.closeness(_g(s, d, "hop").symmetrize(), [0, 1, 2, 3]))
query("bfs_validate", "SELECT rule, 0::BIGINT AS violations FROM (VALUES ('tree_arc_missing'), ('level_step'), ('extra_roots'), ('arc_spans_levels'), ('unreached_neighbour')) r(rule)")(lambda s, d: measures.bfs_violations(g := _g(s, d, "trade").symmetrize(), bfs.bfs(g, _source(g))))

# ---- primitive operations ----------------------------------------------------------------------

_COMMON = f"{_with('hop', 'sym')} SELECT x.src, x.dst, (SELECT count(*) FROM e a JOIN e b ON a.dst = b.dst WHERE a.src = x.src AND b.src = x.dst) AS n FROM e x"
query("op_intersect_count", _COMMON)(lambda s, d: triangles._with_lists(g := _g(s, d, "hop").symmetrize().edges, Graph(g).neighbour_lists()).select("src", "dst", triangles.intersect_count(F.col("near"), F.col("far")).alias("n")))
query("op_owner_local", f"{_with('hop')} SELECT src, dst, {_OWNER.format('src')} AS part, {_OWNER.format('src')} = {_OWNER.format('dst')} AS is_local FROM e")(lambda s, d: _g(s, d, "hop").edges.select("src", "dst", owner(F.col("src"), 4).alias("part"), (owner(F.col("src"), 4) == owner(F.col("dst"), 4)).alias("is_local")))
query("op_contribution", f"{_with('hop')} SELECT id, round(1.0::DOUBLE / deg, 9) AS share FROM dg")(lambda s, d: _g(s, d, "hop").degrees("out").select("id", F.round(1.0 / F.col("deg"), 9).alias("share")))
query("op_fold_sum", f"{_with('hop')} SELECT dst AS id, sum(src)::BIGINT AS total, min(src) AS least FROM e GROUP BY dst")(lambda s, d: _g(s, d, "hop").edges.groupBy(F.col("dst").alias("id")).agg(F.sum("src").alias("total"), F.min("src").alias("least")))
query("op_for_range", f"{_with('hop')} SELECT id, deg FROM dg WHERE id >= 20 AND id < 60")(lambda s, d: _g(s, d, "hop").edges.where("src >= 20 and src < 60").repartition(3).groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg")))

# ---- baselines ---------------------------------------------------------------------------------

query("base_tri_sequential", _triangle_sql("hop"))(lambda s, d: baselines.triangles_sequential(_g(s, d, "hop")))
query("base_tri_probes", f"{_with('hop', 'und')} SELECT count(z.src) AS triangles, count(*) AS probes FROM e x JOIN e y ON x.dst = y.src LEFT JOIN e z ON x.src = z.src AND y.dst = z.dst")(lambda s, d: baselines.triangles_by_probes(_g(s, d, "hop")))
query("base_ghost_pr_hop", _pagerank_sql("hop", "raw"))(lambda s, d: _ranks(baselines.ghost_pagerank(_g(s, d, "hop"))))
query("base_ghost_bfs_trade", _bfs_sql("trade", "sym", 5))(lambda s, d: baselines.ghost_bfs(g := _g(s, d, "trade").symmetrize(), _source(g)))
query("base_vprog_bfs_trade", _bfs_sql("trade", "sym", 5, select=_LEVELS))(lambda s, d: baselines.vertex_program_bfs(g := _g(s, d, "trade").symmetrize(), _source(g)))
query("base_vprog_pr_hop", _pagerank_sql("hop", "raw"))(lambda s, d: _ranks(baselines.vertex_program_pagerank(_g(s, d, "hop"))))
query("base_rdd_pr_hop", _pagerank_sql("hop", "raw", select="SELECT id, round(rank * (SELECT n FROM n) / (SELECT sum(rank) FROM r{last}), 6) AS rank FROM r{last}"))(lambda s, d: baselines.rdd_library(_g(s, d, "hop"), "pagerank").select("id", F.round("value", 6).alias("rank")))
query("base_rdd_bfs_hop", _bfs_sql("hop", "sym", 6, select=_LEVELS))(lambda s, d: baselines.rdd_library(g := _g(s, d, "hop").symmetrize(), "bfs", source=_source(g)))
query("base_rdd_tri_hop", f"{_PER_VERTEX} SELECT v.id, coalesce(k.n, 0) AS n FROM v LEFT JOIN k ON k.id = v.id")(lambda s, d: baselines.rdd_library(_g(s, d, "hop").undirected(), "triangles").select("id", F.col("value").cast("bigint").alias("n")))
query("spmv_sum_times", f"{_with('hop')} SELECT dst AS id, count(*)::DOUBLE AS value FROM e GROUP BY dst")(lambda s, d: baselines.spmv(g := _g(s, d, "hop"), g.vertices().select("id", F.lit(1.0).alias("x"))))
query("spmv_min_plus", f"{_with('hop')} SELECT dst AS id, min(src) + 1 AS value FROM e GROUP BY dst")(lambda s, d: baselines.spmv(g := _g(s, d, "hop"), g.vertices().select("id", F.col("id").alias("x")), "min_plus"))
query("spmv_masked_square", _triangle_sql("hop"))(lambda s, d: baselines.masked_square(_g(s, d, "hop")))

# ---- measures ----------------------------------------------------------------------------------

_P = f"p AS (SELECT src, dst, {_OWNER.format('src')} AS p, {_OWNER.format('dst')} AS q FROM e)"
for _name, _kind in (("trade", "raw"), ("copart", "sym"), ("hop", "raw")):
    _w, _build = f"{_with(_name, _kind)}, {_P}", (lambda s, d, n=_name, k=_kind: _g(s, d, n) if k == "raw" else _g(s, d, n).symmetrize())
    query(f"cost_cut_{_name}", f"{_w} SELECT count(*) FILTER (p = q) AS local, count(*) FILTER (p <> q) AS remote, round(count(*) FILTER (p <> q)::DOUBLE / count(*), 9) AS ratio, 0.75::DOUBLE AS expected FROM p")(lambda s, d, b=_build: measures.edge_cut(b(s, d)))
    query(f"cost_remote_{_name}", f"{_w} SELECT p AS part, count(*) FILTER (p = q) AS local, count(*) FILTER (p <> q) AS remote FROM p GROUP BY p")(lambda s, d, b=_build: measures.remote_ratio(b(s, d)))
    query(f"cost_ghosts_{_name}", f"{_w} SELECT p AS part, count(DISTINCT dst) AS n FROM p WHERE p <> q GROUP BY p")(lambda s, d, b=_build: measures.ghosts(b(s, d)))
    query(f"cost_replication_{_name}", f"{_w}, g AS (SELECT count(DISTINCT (p, dst)) AS ghosts FROM p WHERE p <> q), n AS (SELECT count(*) AS n FROM v) SELECT ghosts, round((ghosts + n)::DOUBLE / n, 9) AS factor FROM g, n")(lambda s, d, b=_build: measures.replication_factor(b(s, d)))
    query(f"cost_messages_{_name}", f"{_w} SELECT count(*) AS raw, count(DISTINCT (p, dst)) AS combined FROM p WHERE p <> q")(lambda s, d, b=_build: measures.messages(b(s, d)))
    query(f"cost_imbalance_{_name}", f"{_w}, a AS (SELECT p AS part, count(*) AS arcs FROM p GROUP BY p) SELECT part, arcs, round((SELECT max(arcs)::DOUBLE / avg(arcs) FROM a), 9) AS max_over_mean FROM a")(lambda s, d, b=_build: measures.imbalance(b(s, d)))
    query(f"cost_granularity_{_name}", f"{_w} SELECT p AS part, count(*) AS arcs, count(DISTINCT src) AS vertices FROM p GROUP BY p")(lambda s, d, b=_build: measures.granularity(b(s, d)))
for _name in ("urand", "kron", "link"):
    query(f"cost_degree_skew_{_name}", f"{_with(_name, 'sym')} SELECT count(*) AS n, (sum(deg) // 2)::BIGINT AS m, max(deg) AS max_degree, round(avg(deg), 6) AS mean_degree, round(max(deg) / avg(deg), 6) AS skew FROM dg")(lambda s, d, n=_name: measures.degree_skew(_g(s, d, n)))
query("cost_frontier_trade", _bfs_sql("trade", "sym", 5, select=f"SELECT level, {_OWNER.format('e.src')} AS part, count(*) AS arcs FROM t JOIN e ON e.src = t.id GROUP BY 1, 2"))(lambda s, d: measures.frontier_imbalance(g := _g(s, d, "trade").symmetrize(), bfs.bfs(g, _source(g))))
query("tri_error", f"{_with('copart', 'und')}, {_SPARSE}, a AS (SELECT count(*) * 8.0::DOUBLE AS est FROM e2 x JOIN e2 y ON x.dst = y.src JOIN e2 z ON x.src = z.src AND y.dst = z.dst), b AS (SELECT count(*) AS n FROM e x {_ID_TRIANGLES}) SELECT round(abs(est - n), 3) AS abs_error, round(abs(est - n) / n, 9) AS rel_error FROM a, b")(lambda s, d: measures.triangle_error(triangles.sparsified(g := _g(s, d, "copart")), triangles.oriented(g)))
query("rank_agreement_hop", "SELECT 0.0::DOUBLE AS l1, 0.0::DOUBLE AS linf, 10::BIGINT AS overlap")(lambda s, d: measures.rank_agreement(pagerank.pagerank(g := _g(s, d, "hop")), pagerank.pagerank_pull(g)).select(F.round("l1", 6).alias("l1"), F.round("linf", 6).alias("linf"), "overlap"))


def graph_queries() -> dict:
    import graphloom.operators.relational  # noqa: F401
    import graphloom.streaming.streams  # noqa: F401

    return QUERIES


def graph_oracle_sql() -> dict[str, str]:
    graph_queries()
    return ORACLES
