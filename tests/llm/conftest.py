import pytest
from pyspark.sql import functions as F

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="session")
def make_docs(spark):
    def make(texts, start=0):
        rows = [(start + i, t, "en", "s", len(t) if t is not None else 0) for i, t in enumerate(texts)]
        return spark.createDataFrame(rows, DOC)

    return make


@pytest.fixture(scope="session")
def odd_docs(make_docs):
    """Nulls, empties, blanks, a long text, equal texts, and extra columns whose names clash with inner ones."""
    texts = [None, "", "   \n", "word", "two words", "same text here now " * 3, "same text here now " * 3, "long " * 30_000, "<|endoftext|> É ñ 漢字   x"]
    docs = make_docs(texts)
    for c in ("n_lines", "places", "score", "cls", "component", "shard", "size", "h", "key", "c0"):
        docs = docs.withColumn(c, F.lit(c))
    return docs.unionByName(docs.where("doc_id = 4"))


@pytest.fixture(scope="session")
def no_docs(make_docs, spark):
    return spark.createDataFrame([], DOC)


@pytest.fixture(scope="session")
def labels(spark):
    return spark.createDataFrame([(i, int(i % 3 > 0), int(i % 4 == 0)) for i in range(60)], "doc_id bigint, quality int, toxic int")
