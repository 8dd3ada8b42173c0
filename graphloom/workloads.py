"""The experiment workloads: strong scaling, rivals, memory and tuning grids, as rows of seconds.

    python -m graphloom.workloads scaling --cores 1,2,4 --graphs urand,copart,trade
    python -m graphloom.workloads rivals --graphs hop,link,kron
    python -m graphloom.workloads grid --graphs copart

Every measurement runs in a process of its own with local[cores], graph building apart from the
algorithm. A run beyond the limit is stopped and kept as a row with status 'dnf'.
"""

from __future__ import annotations

import argparse
import json
import os
import subprocess
import sys
import time

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def _algorithms():
    from graphloom.operators import baselines, bfs, pagerank, triangles
    from graphloom.queries import _source

    return {
        "triangles": lambda g: triangles.oriented(g),
        "triangles_naive": lambda g: triangles.naive(g),
        "triangles_partitioned": lambda g: triangles.partitioned(g),
        "triangles_seq_outer": lambda g: triangles.partitioned(g, outer="seq"),
        "triangles_rdd": lambda g: baselines.rdd_library(g.undirected(), "triangles"),
        "triangles_sequential": lambda g: baselines.triangles_sequential(g),
        "pagerank": lambda g: pagerank.pagerank(g.symmetrize()),
        "pagerank_partitioned": lambda g: pagerank.pagerank_partitioned(g.symmetrize()),
        "pagerank_ghost": lambda g: baselines.ghost_pagerank(g.symmetrize()),
        "pagerank_rdd": lambda g: baselines.rdd_library(g.symmetrize(), "pagerank"),
        "pagerank_vertex_program": lambda g: baselines.vertex_program_pagerank(g.symmetrize()),
        "bfs": lambda g: bfs.bfs(s := g.symmetrize(), _source(s)),
        "bfs_auto": lambda g: bfs.bfs(s := g.symmetrize(), _source(s), direction="auto"),
        "bfs_blocks": lambda g: bfs.bfs_async_blocks(s := g.symmetrize(), _source(s)),
        "bfs_ghost": lambda g: baselines.ghost_bfs(s := g.symmetrize(), _source(s)),
        "bfs_vertex_program": lambda g: baselines.vertex_program_bfs(s := g.symmetrize(), _source(s)),
    }


SCALING = ("triangles", "pagerank", "bfs")
RIVALS = ("triangles", "triangles_rdd", "triangles_sequential", "pagerank", "pagerank_ghost", "pagerank_rdd", "pagerank_vertex_program", "bfs", "bfs_ghost", "bfs_vertex_program")
GRID = ("triangles_naive", "triangles", "triangles_partitioned", "triangles_seq_outer", "pagerank", "pagerank_partitioned", "bfs", "bfs_auto", "bfs_blocks")


def measure(algorithm: str, graph: str, cores: int, factor: int, sf_dir: str) -> dict:
    """One run in this process: seconds to build, to run, edges traversed a second, and peak memory."""
    from pyspark.sql import SparkSession

    from graphloom.plans.graph import Graph
    from graphloom.plans.scratch import Scratch
    from graphloom.sources.graphs import build

    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(max(2, factor * cores))).config("spark.ui.enabled", "false").config("spark.driver.memory", "4g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    t = time.time()
    g = Graph(Scratch(spark, "workload").save(build(spark, sf_dir, graph).edges.select("src", "dst"), "edges"))
    arcs = g.edges.count()
    built = time.time() - t
    t = time.time()
    _algorithms()[algorithm](g).write.format("noop").mode("overwrite").save()
    sec = time.time() - t
    with open("/proc/self/status") as f:
        mine = next(int(x.split()[1]) / 1024 for x in f if x.startswith("VmHWM"))
    heap = spark._jvm.java.lang.Runtime.getRuntime()
    return {"algorithm": algorithm, "graph": graph, "cores": cores, "factor": factor, "arcs": arcs, "build_sec": round(built, 3), "sec": round(sec, 3), "edges_a_sec": round(arcs / sec), "heap_mb": round(heap.totalMemory() / 1e6), "python_mb": round(mine), "status": "ok"}


def apart(algorithm: str, graph: str, cores: int, factor: int, sf_dir: str, limit: float) -> dict:
    """measure() in a process of its own, stopped at the limit."""
    row = {"algorithm": algorithm, "graph": graph, "cores": cores, "factor": factor, "sec": None}
    command = [sys.executable, "-m", "graphloom.workloads", "one", "--algorithm", algorithm, "--graphs", graph, "--cores", str(cores), "--factor", str(factor), "--sf", sf_dir]
    try:
        out = subprocess.run(command, cwd=ROOT, env=os.environ | {"PYTHONPATH": ROOT}, capture_output=True, text=True, timeout=limit)
    except subprocess.TimeoutExpired:
        return row | {"status": "dnf"}
    lines = [x for x in out.stdout.splitlines() if x.startswith("{")]
    return json.loads(lines[-1]) if out.returncode == 0 and lines else row | {"status": "error"}


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("what", choices=["one", "scaling", "rivals", "grid"])
    p.add_argument("--algorithm")
    p.add_argument("--graphs", default="urand,copart")
    p.add_argument("--cores", default="1,2,4")
    p.add_argument("--factor", type=int, default=3)
    p.add_argument("--sf", default="/root/testdata/sf0.1")
    p.add_argument("--limit", type=float, default=600)
    a = p.parse_args()
    cores = [int(x) for x in a.cores.split(",")]
    if a.what == "one":
        print(json.dumps(measure(a.algorithm, a.graphs, cores[0], a.factor, a.sf)))
        return
    for graph in a.graphs.split(","):
        if a.what == "scaling":
            for algorithm in SCALING:
                base = None
                for c in cores:
                    row = apart(algorithm, graph, c, a.factor, a.sf, a.limit)
                    base = base or row["sec"]
                    if row["sec"] and base:
                        speedup = base / row["sec"]
                        row |= {"speedup": round(speedup, 3), "efficiency": round(speedup * cores[0] / c, 3), "superlinear": speedup > c / cores[0]}
                    print(json.dumps(row), flush=True)
        elif a.what == "rivals":
            for algorithm in RIVALS:
                print(json.dumps(apart(algorithm, graph, cores[-1], a.factor, a.sf, a.limit)), flush=True)
        else:
            for algorithm in GRID:
                for factor in (1, 3, 8):
                    print(json.dumps(apart(algorithm, graph, cores[-1], factor, a.sf, a.limit)), flush=True)


if __name__ == "__main__":
    main()
