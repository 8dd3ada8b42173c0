"""The graph as a relation: edges, and the views that algorithms ask for.

A Graph is an edge DataFrame (src, dst[, w]); vertices are the ends of its edges unless a vertex table
is given. All views are lazy plans; nothing here collects anything that grows with the graph.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphloom.functions.packed import sharing_pairs
from graphloom.functions.tiles import shared_pairs
from graphloom.plans.scratch import Scratch

MAX_CHUNK = 65_536


def md5_32(text: Column) -> Column:
    """First eight hex digits of the md5 of a text, as a bigint: a hash that SQL engines agree on."""
    return F.conv(F.substring(F.md5(text.cast("string").cast("binary")), 1, 8), 16, 10).cast("bigint")


def owner(vertex: Column, parts: int) -> Column:
    """Which part owns a vertex (portable placement)."""
    return F.pmod(md5_32(vertex), F.lit(parts)).cast("int")


@dataclass(frozen=True)
class Graph:
    edges: DataFrame
    vertex_table: DataFrame | None = None

    @staticmethod
    def from_edges(df: DataFrame, src: str | Column, dst: str | Column, dedupe: bool = True, drop_loops: bool = True, weight: str | None = None) -> Graph:
        """Edges of any relation. Rows with a null end are dropped; so are loops and repeats unless told otherwise."""
        s, d = (F.col(c) if isinstance(c, str) else c for c in (src, dst))
        cols = [s.cast("bigint").alias("src"), d.cast("bigint").alias("dst")]
        if weight:
            cols.append(F.col(weight).cast("double").alias("w"))
        out = df.select(*cols).where("src is not null and dst is not null")
        if drop_loops:
            out = out.where("src <> dst")
        if dedupe:
            out = out.groupBy("src", "dst").agg(F.sum("w").alias("w")) if weight else out.distinct()
        return Graph(out)

    def vertices(self) -> DataFrame:
        if self.vertex_table is not None:
            return self.vertex_table.select(F.col("id").cast("bigint").alias("id")).distinct()
        return self.edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()

    def reverse(self) -> Graph:
        rest = [c for c in self.edges.columns if c not in ("src", "dst")]
        return replace(self, edges=self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))

    def symmetrize(self) -> Graph:
        """Both directions of every edge, once; one pass over the edges, not two scans."""
        both = self.edges.select(F.explode(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e"))
        return replace(self, edges=both.select("e.src", "e.dst").distinct())

    def undirected(self) -> Graph:
        """One row an unordered pair, smaller id first."""
        return replace(self, edges=self.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src <> dst").distinct())

    def degrees(self, kind: str = "total") -> DataFrame:
        """(id, deg) of vertices with at least one such edge; kind: out, in, total."""
        ends = {"out": F.col("src"), "in": F.col("dst")}.get(kind)
        if ends is None:
            ends = F.explode(F.array("src", "dst"))
        return self.edges.select(ends.alias("id")).groupBy("id").agg(F.count("*").alias("deg"))

    def degree_histogram(self, kind: str = "total") -> DataFrame:
        return self.degrees(kind).groupBy("deg").agg(F.count("*").alias("n"))

    def orient(self, by: str = "degree") -> Graph:
        """One arc an undirected edge, towards the larger id or the larger (degree, id); an acyclic graph with short hub lists."""
        base = self.undirected()
        if by == "id":
            return base
        deg = base.degrees("total")
        left, right = deg.toDF("src", "ds"), deg.toDF("dst", "dd")
        ranked = base.edges.join(left, "src").join(right, "dst")
        forward = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
        return replace(self, edges=ranked.select(F.when(forward, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(forward, F.col("dst")).otherwise(F.col("src")).alias("dst")))

    def adjacency(self, max_chunk: int = MAX_CHUNK) -> DataFrame:
        """(id, chunk, nbrs sorted, deg): neighbour lists in chunks, so that a hub is many rows of bounded size."""
        place = F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1
        deg = F.count("*").over(Window.partitionBy("src"))
        rows = self.edges.select("src", "dst", (place / max_chunk).cast("int").alias("chunk"), deg.alias("deg"))
        return rows.groupBy(F.col("src").alias("id"), "chunk", "deg").agg(F.sort_array(F.collect_list("dst")).alias("nbrs")).select("id", "chunk", "nbrs", "deg")

    def neighbour_lists(self) -> DataFrame:
        """(id, nbrs sorted): one row a vertex, for graphs whose lists are short (oriented by degree)."""
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))

    def csr(self) -> tuple[DataFrame, DataFrame]:
        """(offsets(id, first, deg), targets(pos, dst)): dense positions by per-range counts and their prefix sums, never one global window."""
        deg = self.degrees("out")
        buckets = 64
        lo_hi = deg.agg(F.min("id"), F.max("id")).first()
        if lo_hi[0] is None:
            return deg.select("id", F.lit(0).cast("bigint").alias("first"), "deg"), self.edges.select(F.lit(0).cast("bigint").alias("pos"), "dst")
        width = (lo_hi[1] - lo_hi[0]) // buckets + 1
        ranged = deg.withColumn("b", F.floor((F.col("id") - lo_hi[0]) / width).cast("int"))
        sums = sorted((r.b, r.n) for r in ranged.groupBy("b").agg(F.sum("deg").alias("n")).collect())  # at most `buckets` rows
        base, before = [], 0
        for b, n in sums:
            base.append((b, before))
            before += n
        bases = F.broadcast(deg.sparkSession.createDataFrame(base, "b int, base bigint"))
        inside = F.coalesce(F.sum("deg").over(Window.partitionBy("b").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        offsets = ranged.withColumn("inside", inside).join(bases, "b").select("id", (F.col("base") + F.col("inside")).alias("first"), "deg")
        place = F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1
        targets = self.edges.select("src", "dst", place.alias("k")).join(offsets, F.col("src") == F.col("id")).select((F.col("first") + F.col("k")).alias("pos"), "dst")
        return offsets, targets

    def relabel(self, by: str = "degree") -> tuple[Graph, DataFrame]:
        """Dense ids 0..n-1 by descending degree (ties by id), by id, or by hash; and the dictionary (id, label)."""
        deg = self.degrees("total")
        key = {"degree": F.struct((-F.col("deg")).alias("k"), "id"), "id": F.struct(F.lit(0).alias("k"), "id"), "hash": F.struct(md5_32(F.col("id")).alias("k"), "id")}[by]
        ranked = Scratch(deg.sparkSession, "relabel").save(deg.select("id", key.alias("key")).repartitionByRange(8, "key").sortWithinPartitions("key").select("id", "key", F.spark_partition_id().alias("p")), "ranked")
        counts = sorted((r.p, r.n) for r in ranked.groupBy("p").agg(F.count("*").alias("n")).collect())
        base, before = [], 0
        for p, n in counts:
            base.append((p, before))
            before += n
        bases = F.broadcast(deg.sparkSession.createDataFrame(base, "p int, base bigint"))
        inside = F.row_number().over(Window.partitionBy("p").orderBy("key")) - 1
        labels = ranked.withColumn("inside", inside).join(bases, "p").select("id", (F.col("base") + F.col("inside")).alias("label"))
        edges = self.edges.join(labels.toDF("src", "a"), "src").join(labels.toDF("dst", "b"), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))
        return Graph(edges), labels

    def subgraph(self, vertices: DataFrame | None = None, edge_filter: str | None = None) -> Graph:
        """Edges that pass the filter and whose ends are both among the given ids."""
        e = self.edges.where(edge_filter) if edge_filter else self.edges
        if vertices is not None:
            ids = vertices.select("id")
            e = e.join(ids.toDF("src"), "src", "left_semi").join(ids.toDF("dst"), "dst", "left_semi").select(*self.edges.columns)
        return replace(self, edges=e)

    def project(self, min_common: int = 1) -> Graph:
        """Pairs of sources that share at least min_common targets (one side of a bipartite graph). Edges may repeat."""
        return Graph(sharing_pairs(self.edges, min_common) if min_common > 1 else shared_pairs(self.edges, "dst", "src", min_common, 8192))

    def place(self, parts: int, how: str = "hash") -> DataFrame:
        """(id, part) by hash, range of ids, seeded random, or balanced by degree (snake order over degree ranks within hash cells)."""
        v = self.vertices()
        if how == "hash":
            return v.select("id", owner(F.col("id"), parts).alias("part"))
        if how == "random":
            return v.select("id", F.pmod(md5_32(F.concat(F.lit("r:"), F.col("id").cast("string"))), F.lit(parts)).cast("int").alias("part"))
        if how == "range":
            cuts = v.approxQuantile("id", [i / parts for i in range(1, parts)], 0.001) if parts > 1 else []
            part = F.lit(0)
            for c in cuts:
                part = part + (F.col("id") > F.lit(int(c))).cast("int")
            return v.select("id", part.alias("part"))
        if how == "degree_balanced":
            deg = v.join(self.degrees("total"), "id", "left").select("id", F.coalesce("deg", F.lit(0)).alias("deg"), F.pmod(md5_32(F.col("id")), F.lit(16)).alias("cell"))
            k = F.row_number().over(Window.partitionBy("cell").orderBy(F.desc("deg"), "id")) - 1
            turn = F.pmod(k, F.lit(2 * parts))
            return deg.withColumn("t", turn + 0).select("id", F.pmod(F.when(F.col("t") < parts, F.col("t")).otherwise(2 * parts - 1 - F.col("t")) + F.col("cell"), F.lit(parts)).cast("int").alias("part"))
        if how == "label_prop":
            return self._place_by_labels(parts)
        raise ValueError(how)

    def _place_by_labels(self, parts: int, rounds: int = 4) -> DataFrame:
        """Few rounds of label propagation (the commonest label around, the least of equals), labels dealt to parts by their hash. Large labels are split by id."""
        spark = self.edges.sparkSession
        scratch = Scratch(spark, "labels")
        e = scratch.save_by(self.symmetrize().edges.select("src", "dst"), "arcs", "src")
        labels = scratch.save(self.vertices().select("id", F.col("id").alias("label")), "labels")
        for _ in range(rounds):
            seen = e.join(labels.select(F.col("id").alias("src"), "label"), "src").groupBy(F.col("dst").alias("id"), "label").agg(F.count("*").alias("n"))
            best = seen.groupBy("id").agg(F.max(F.struct("n", (-F.col("label")).alias("label"))).alias("best"))
            new = scratch.save(labels.select("id", F.col("label").alias("old")).join(best, "id", "left").select("id", F.coalesce(-F.col("best.label"), "old").alias("label")), "labels")
            scratch.drop(labels)
            labels = new
        n = labels.count()
        sizes = labels.groupBy("label").agg(F.count("*").alias("n"))
        share = F.floor(F.col("n") * (2 * parts) / max(n, 1)) + 1  # a label of more than half a part's due goes to several
        cell = F.concat_ws(":", "label", F.pmod(md5_32(F.col("id").cast("string")), share))
        return labels.join(sizes, "label").select("id", F.pmod(md5_32(cell), F.lit(parts)).cast("int").alias("part"))

    def persist_as(self, table: str, buckets: int) -> Graph:
        """Store the edges bucketed by src, so that joins on src need no exchange of them."""
        self.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(table)
        return replace(self, edges=self.edges.sparkSession.table(table))

    def register(self, prefix: str) -> None:
        """SQL views <prefix>_edges, <prefix>_vertices, <prefix>_adjacency."""
        self.edges.createOrReplaceTempView(f"{prefix}_edges")
        self.vertices().createOrReplaceTempView(f"{prefix}_vertices")
        self.adjacency().createOrReplaceTempView(f"{prefix}_adjacency")


def adjacency_edges(adjacency: DataFrame) -> DataFrame:
    """Back from neighbour lists to edges; narrow."""
    return adjacency.select(F.col("id").alias("src"), F.explode("nbrs").alias("dst"))
