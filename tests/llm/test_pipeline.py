"""The pipeline's stages: what they drop, what they keep, and their columns."""

from pyspark.sql import functions as F

import corpus_pipeline as pipeline


def test_stages_in_order(spark, sf):
    assert [n for n, _ in pipeline.STAGES] == ["toxicity", "quality", "line_dedup", "minhash", "packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    for _, stage in pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == columns
        kept = {r.doc_id for r in docs.select("doc_id").collect()}
        assert kept <= ids and len(kept) > 0.6 * len(ids)
        ids = kept
    packed = pipeline.packing(spark, docs, sf)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == ids


def test_copies_go_and_others_stay(make_docs, spark, sf):
    base = " ".join(f"word{i}" for i in range(100))
    docs = make_docs([base, base, base.replace("word50", "other"), " ".join(f"else{i}" for i in range(100)), None, ""])
    assert {r.doc_id for r in pipeline.minhash(spark, docs, sf).collect()} == {0, 3, 4, 5}


def test_copy_with_a_short_line_goes(make_docs, spark, sf):
    long = "a line of more than twelve symbols\n"
    docs = make_docs([long + "Les.", long + "Les.", "Les.\nanother line that stands here", "Short.", None])
    got = {r.doc_id: r.text for r in pipeline.line_dedup(spark, docs, sf).collect()}
    assert got == {0: long + "Les.", 2: "another line that stands here", 3: "Short.", 4: None}


def test_null_and_repeated_ids_are_decided_by_row(make_docs, spark, sf):
    def words(name):
        return " ".join(f"{name}{i}" for i in range(100))

    docs = make_docs([words("a"), words("b"), words("c"), words("d"), words("d"), words("e"), words("e")])
    docs = docs.unionByName(docs.where("doc_id = 0")).unionByName(make_docs([words("f")], start=1))
    null = F.when(~F.col("doc_id").isin(2, 4, 5, 6), F.col("doc_id"))
    got = pipeline.minhash(spark, docs.withColumn("doc_id", null), sf).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text[0]) for r in got) == [(False, 0, "a"), (False, 1, "b"), (False, 1, "f"), (False, 3, "d"), (True, 0, "c"), (True, 0, "e")]


def test_run(spark, sf):
    assert pipeline.run(spark, sf).count() > 0
