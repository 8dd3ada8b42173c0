"""Hand-made graphs, closed forms and invariants of the graph methods."""

import itertools

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphloom.functions import joins, kernels, tiles
from graphloom.operators import baselines, bfs, measures, pagerank, triangles
from graphloom.plans.graph import Graph, adjacency_edges
from graphloom.sources.generators import kron, urand


def graph(spark, pairs):
    return Graph.from_edges(spark.createDataFrame(pairs or [], "src bigint, dst bigint"), "src", "dst")


def complete(n):
    return list(itertools.combinations(range(n), 2))


FIXTURES = {
    "empty": ([], 0),
    "loop": ([(1, 1)], 0),
    "double": ([(1, 2), (1, 2), (2, 1)], 0),
    "path": ([(i, i + 1) for i in range(6)], 0),
    "star": ([(0, i) for i in range(1, 11)], 0),
    "triangle": ([(0, 1), (1, 2), (2, 0)], 1),
    "k4": (complete(4), 4),
    "k5_less_one": (complete(5)[1:], 7),
    "tail": ([(0, 1), (1, 2), (2, 0), (2, 3)], 1),
    "wide_ids": ([(-1, 2**40), (2**40, 7), (7, -1)], 1),
}


@pytest.mark.parametrize("name", FIXTURES)
def test_triangle_variants(spark, name):
    pairs, n = FIXTURES[name]
    g = graph(spark, pairs)
    for count in (triangles.naive(g), triangles.oriented(g), triangles.oriented(g, "id"), triangles.by_edges(g), triangles.partitioned(g, 2), triangles.broadcast_lists(g)):
        assert count.first()[0] == n
    if pairs:
        assert triangles.tiled(g, 3).first()[0] == n
        assert baselines.triangles_sequential(g).agg(F.sum("triangles")).first()[0] in (n, None)
        assert triangles.per_vertex(g).agg(F.sum("n")).first()[0] in (3 * n, None)
        assert triangles.per_edge(g).agg(F.sum("n")).first()[0] in (3 * n, None)


@pytest.mark.parametrize("density", [0.02, 0.6])
def test_triangle_lists_are_sent_once_a_part(spark, density, monkeypatch):
    monkeypatch.setattr(triangles, "HELD_ARCS", 700)
    rng = np.random.default_rng(5)
    a = np.triu(rng.random((130, 130)) < density, 1)
    a[:3, 3:] = True  # hubs
    want = int(np.einsum("ij,jk,ik->", *[a.astype(int)] * 3))
    g = graph(spark, [(int(i) * 2**33 - 50, int(j) * 2**33 - 50) for i, j in np.argwhere(a)])
    for count in (triangles.naive(g), triangles.oriented(g), triangles.by_edges(g), triangles.partitioned(g, 3), triangles.partitioned(g, 3, outer="seq")):
        plan = count._jdf.queryExecution().executedPlan().toString()
        assert "Join" not in plan  # a join of arcs with lists exchanges the squares of degrees
        assert count.first()[0] == want


def test_null_ends_are_dropped(spark):
    df = spark.createDataFrame([(1, None), (None, 2), (1, 2)], "src bigint, dst bigint")
    assert [tuple(r) for r in Graph.from_edges(df, "src", "dst").edges.collect()] == [(1, 2)]


def test_adjacency_chunks_hubs_and_round_trips(spark):
    g = graph(spark, FIXTURES["star"][0])
    a = g.adjacency(4)
    assert sorted(len(r.nbrs) for r in a.collect()) == [2, 4, 4]
    assert sorted(tuple(r) for r in adjacency_edges(a).collect()) == sorted(FIXTURES["star"][0])


def test_csr(spark):
    g = graph(spark, [(5, 1), (5, 2), (9, 1), (-3, 5)])
    offsets, targets = g.csr()
    assert sorted(tuple(r) for r in offsets.collect()) == [(-3, 0, 1), (5, 1, 2), (9, 3, 1)]
    assert [r.dst for r in targets.orderBy("pos").collect()] == [5, 1, 2, 1]


def reference_ranks(pairs, d=0.85, iters=10):
    v = sorted({x for p in pairs for x in p})
    r = {x: 1 / len(v) for x in v}
    out = {x: sum(a == x for a, _ in pairs) for x in v}
    for _ in range(iters):
        got = dict.fromkeys(v, 0.0)
        for a, b in pairs:
            got[b] += r[a] / out[a]
        r = {x: (1 - d) / len(v) + d * got[x] for x in v}
    return r


@pytest.mark.parametrize("pairs", [[(0, 1), (1, 2), (2, 0), (2, 3), (3, 0)], [(0, 1), (1, 2), (2, 0), (2, 3)]])
def test_pagerank_variants_agree_with_a_plain_loop(spark, pairs):
    want = reference_ranks(pairs)
    g = graph(spark, pairs)
    for got in (pagerank.pagerank(g), pagerank.pagerank_pull(g), pagerank.pagerank_partitioned(g, 2), baselines.ghost_pagerank(g, 2), baselines.vertex_program_pagerank(g)):
        have = {r.id: r["rank"] for r in got.collect()}
        assert have.keys() == want.keys()
        assert all(abs(have[k] - want[k]) < 1e-12 for k in want)


def test_pagerank_residual_shrinks_and_mass_stays(spark):
    g = graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 0)])
    ranks, log = pagerank.pagerank_residuals(g, tol=1e-4)
    assert log[-1][1] <= 1e-4
    assert all(b[1] <= 0.85 * a[1] + 1e-12 for a, b in itertools.pairwise(log))
    assert abs(log[-1][3] - 1) < 1e-9
    regular = graph(spark, [(i, (i + 1) % 5) for i in range(5)])
    assert all(abs(r["rank"] - 0.2) < 1e-12 for r in pagerank.pagerank(regular).collect())


def test_dangling_uniform_keeps_mass(spark):
    g = graph(spark, [(0, 1), (1, 2)])
    assert abs(pagerank.pagerank(g, dangling="uniform").agg(F.sum("rank")).first()[0] - 1) < 1e-9
    assert pagerank.pagerank(g).agg(F.sum("rank")).first()[0] < 1


def test_bfs_variants(spark):
    pairs = [(0, 1), (0, 2), (1, 3), (2, 3), (3, 4), (7, 8)]
    g = graph(spark, pairs).symmetrize()
    want = {(0, 0, 0), (1, 0, 1), (2, 0, 1), (3, 1, 2), (4, 3, 3)}
    for tree in (bfs.bfs(g, 0), bfs.bfs(g, 0, dedupe="two_level"), bfs.bfs(g, 0, direction="auto"), bfs.bfs_async_blocks(g, 0, 2), baselines.ghost_bfs(g, 0, 2)):
        assert {tuple(r) for r in tree.select("id", "parent", "level").collect()} == want
    assert {tuple(r) for r in baselines.vertex_program_bfs(g, 0).collect()} == {(i, lv) for i, _, lv in want}
    assert all(r.violations == 0 for r in measures.bfs_violations(g, bfs.bfs(g, 0)).collect())
    assert [r.id for r in bfs.shortest_path(g, 0, 4).orderBy("hop").collect()] == [0, 1, 3, 4]
    assert bfs.shortest_path(g, 0, 8).count() == 0
    with pytest.raises(ValueError):
        bfs.bfs(g, 99)
    assert {(r.id, r.component) for r in bfs.components(g).collect()} == {(0, 0), (1, 0), (2, 0), (3, 0), (4, 0), (7, 7), (8, 7)}


def test_bfs_variants_on_a_deep_path(spark):
    n = 104
    g = graph(spark, [(i, i + 1) for i in range(n)])
    assert {tuple(r) for r in baselines.vertex_program_bfs(g, 0).collect()} == {(i, i) for i in range(n + 1)}
    short = graph(spark, [(i, i + 1) for i in range(30)])
    for cut in (lambda: bfs.bfs_async_blocks(short, 0, max_rounds=4), lambda: baselines.vertex_program_bfs(short, 0, supersteps=4)):
        with pytest.raises(RuntimeError):
            cut()
    assert {(r.id, r.level) for r in bfs.bfs_async_blocks(short, 0).collect()} == {(i, i) for i in range(31)}


def test_components_of_a_long_chain(spark):
    n = 200
    g = graph(spark, [(i * 7919 % 1009, (i + 1) * 7919 % 1009) for i in range(n)])
    assert bfs.components(g).select("component").distinct().count() == 1


def test_dfs_preorder(spark):
    tree = spark.createDataFrame([(0, 1), (0, 2), (1, 3), (2, 4)], "src bigint, dst bigint")
    assert [r.id for r in bfs.dfs_preorder(tree, 0).orderBy("path").collect()] == [0, 1, 3, 2, 4]


def test_placement_does_not_change_results(spark):
    g = graph(spark, complete(7))
    assert {triangles.partitioned(g, p).first()[0] for p in (1, 2, 5)} == {35}
    for how in ("hash", "range", "random", "degree_balanced"):
        assert g.place(3, how).count() == 7
    cut = measures.edge_cut(g, 4).first()
    assert cut.local + cut.remote == 21


def test_generators_follow_the_expected_triangles(spark):
    u, k = Graph(urand(spark, 8)), Graph(kron(spark, 8))
    d = 2 * u.edges.count() / 256
    assert abs(triangles.oriented(u).first()[0] - d**3 / 6) < 0.3 * d**3 / 6
    assert k.degrees().agg(F.max("deg")).first()[0] > u.degrees().agg(F.max("deg")).first()[0]


def test_kernels_agree():
    rng = np.random.default_rng(0)
    for _ in range(50):
        a, b = (np.unique(rng.integers(0, 60, rng.integers(0, 40))) for _ in range(2))
        assert {k(a, b) for k in kernels.KERNELS.values()} == {len(set(a) & set(b))}


def test_shared_pairs_equal_a_plain_count(spark):
    rng = np.random.default_rng(1)
    rows = [(int(k), int(i) * 37 - 900) for k, i in {*zip(rng.integers(0, 40, 900), rng.integers(0, 60, 900), strict=True)}]
    by, common = {}, {}
    for k, i in rows:
        by.setdefault(k, set()).add(i)
    for items in by.values():
        for p in itertools.combinations(sorted(items), 2):
            common[p] = common.get(p, 0) + 1
    df = spark.createDataFrame([*rows, *rows[:50], (None, 5), (1, None)], "k int, i bigint")
    for least in (1, 6):
        got = tiles.shared_pairs(df, "k", "i", least, 256)
        assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
        assert sorted(map(tuple, got.collect())) == sorted(p for p, n in common.items() if n >= least)


def test_cosine_pairs_equal_sums_in_order(spark):
    rng = np.random.default_rng(2)
    v = [[float(x) for x in r] for r in rng.integers(-3, 4, (70, 5))]
    v += [[3.0, 4.0, 0.0, 0.0, 0.0], [1.0, 0.0, 0.0, 0.0, 0.0], v[0], None, [1.0, None, 0.0, 0.0, 0.0], [1.0, 0.0]]
    want = []
    for (i, a), (j, b) in itertools.combinations(enumerate(v), 2):
        if a and b and len(a) == len(b) and None not in a and None not in b:
            d, x, y = (sum((p * q for p, q in zip(s, t, strict=True)), 0.0) for s, t in ((a, b), (a, a), (b, b)))
            r = x**0.5 * y**0.5
            if r == 0 or d / r >= 0.6:
                want.append((i, j))
    got = tiles.cosine_pairs(spark.createDataFrame(list(enumerate(v)), "id bigint, e array<double>"), "id", "e", 0.6, 16)
    assert sorted(map(tuple, got.collect())) == want and (70, 71) in want


def test_asof_and_range_join(spark):
    left = spark.createDataFrame([(1, 10, "a"), (1, 3, "b"), (2, 5, "c")], "k int, t int, v string")
    right = spark.createDataFrame([(1, 4, 40), (1, 9, 90), (2, 6, 60)], "k int, t int, r int")
    assert {(x.v, x.r) for x in joins.asof_join(left, right, "k", "t", "r").collect()} == {("a", 90), ("b", None), ("c", None)}
    bands = spark.createDataFrame([(0, 0.0, 7.0), (1, 7.0, 20.0)], "band int, lo double, hi double")
    vals = spark.createDataFrame([(0.0,), (6.9,), (7.0,), (19.0,), (20.0,)], "x double")
    assert sorted((r.x, r.band) for r in joins.range_join(vals, bands, "x", "lo", "hi", 5.0).collect()) == [(0.0, 0), (6.9, 0), (7.0, 1), (19.0, 1)]


def test_bucketed_edges_join_without_exchange(spark):
    g = graph(spark, complete(12)).persist_as("graphloom_bucket_test", 4)
    spark.sql("SET spark.sql.autoBroadcastJoinThreshold=-1")
    try:
        ranks = spark.table("graphloom_bucket_test").select("src").distinct()
        plan = g.edges.join(ranks, "src")._jdf.queryExecution().executedPlan().toString()
        assert "Exchange hashpartitioning" not in plan
    finally:
        spark.sql("RESET spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE graphloom_bucket_test")


def test_speedup_table(spark):
    rows = measures.speedup(spark.createDataFrame([(1, 8.0), (2, 3.0), (4, 2.0)], "cores int, sec double")).orderBy("cores").collect()
    assert [r.superlinear for r in rows] == [False, True, False]


def test_packed_lists_round_trip():
    from graphloom.functions import packed

    rng = np.random.default_rng(3)
    for lo, hi in ((0, 50), (-40, 40), (-(1 << 62), 1 << 62), (1 << 40, (1 << 40) + 500)):
        src, dst = rng.integers(lo, hi, 400), rng.integers(lo, hi, 400)
        ids, sizes, nbrs = packed.unpack_lists(*packed.pack_lists(*packed.lists_of(np.r_[src, src], np.r_[dst, dst])))
        got = list(zip(np.repeat(ids, sizes).tolist(), nbrs.tolist(), strict=True))
        assert got == sorted(set(zip(src.tolist(), dst.tolist(), strict=True)))


def test_triangle_counts_exchange_packed_arcs(spark, monkeypatch):
    """Each arc is exchanged packed; repeats, loops and nulls add nothing, and several blocks give what one gives."""
    from graphloom.functions import packed

    n = 240
    e = [(a * 7919 - 500_000, b * 7919 - 500_000) for a in range(n) for b in range(a + 1, n) if (a * b) % 3]
    df = spark.createDataFrame(e + e[:500] + [(b, a) for a, b in e[:500]] + [(e[0][0], e[0][0]), (None, 1)], "src bigint, dst bigint")
    near = {}
    for a, b in e:
        near.setdefault(a, set()).add(b)
    want = sum(len(near[a] & near.get(b, set())) for a, b in e)
    store = spark.sparkContext._jsc.sc().statusStore()

    def written():
        stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))

    before = written()
    assert triangles.naive(Graph(df)).first()[0] == want
    assert 0 < written() - before < 4 * 2 * len(e)  # fewer than four bytes an arc of either direction
    assert {triangles.oriented(Graph(df)).first()[0], triangles.oriented(Graph(df), "id").first()[0]} == {want}
    assert triangles.naive(Graph(df.where("src is null"))).first()[0] == 0
    monkeypatch.setattr(packed, "FLUSH_ROWS", 3000)  # in this process: many flushes give the arcs of one
    src, dst = (np.array(x) for x in zip(*e, strict=True))
    cut = [pa.RecordBatch.from_pydict({"s": src[i : i + 2000], "d": dst[i : i + 2000]}) for i in range(0, len(e), 2000)]
    wire = list(packed._pack(True, 5)(iter(cut)))
    lists = [packed.unpack_lists(r["ids"], r["sizes"], r["nbrs"]) for b in wire for r in b.to_pylist()]
    arcs = [p for ids, sizes, nbrs in lists for p in zip(np.repeat(ids, sizes).tolist(), nbrs.tolist(), strict=True)]
    assert len(wire) > 1 and sorted(arcs) == sorted(e + [(b, a) for a, b in e])
